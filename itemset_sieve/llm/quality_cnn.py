"""Quality classifier: a byte-level convolutional network in numpy.

Filters as wide as WIDTH bytes slide over the whole text with stride STRIDE, so that neighbouring windows
overlap; each filter keeps its largest response, and a logistic unit combines these into one probability.
A filter is a table of one weight per offset and byte value, so that a response is a sum of WIDTH look-ups.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import fold, trimmed

WIDTH, STRIDE, FILTERS = 8, 4, 16
#: Labelled documents of each class that the fit sees at most, and the longest it takes: the bound of the sample.
PER_CLASS, LONGEST = 700, 60_000
#: Windows that are computed at once: bounds memory, the text is covered whole.
BLOCK = 1 << 16


@dataclass
class Net:
    """Weights: table (WIDTH, 256, FILTERS), shift (FILTERS), out (FILTERS), bias."""

    table: np.ndarray
    shift: np.ndarray
    out: np.ndarray
    bias: float

    def responses(self, data: np.ndarray) -> np.ndarray:
        """Of every window of a padded text: (windows, FILTERS)."""
        n = (len(data) - WIDTH) // STRIDE + 1
        r = self.table[0][data[: n * STRIDE : STRIDE]]
        for k in range(1, WIDTH):
            r += self.table[k][data[k : k + n * STRIDE : STRIDE][:n]]
        return r

    def pooled(self, data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Largest response of each filter over the whole text, where it is, and the padded text."""
        x = padded(data)
        best, at = np.full(FILTERS, -np.inf, np.float32), np.zeros(FILTERS, np.int64)
        for start in range(0, len(x) - WIDTH + 1, BLOCK * STRIDE):
            r = self.responses(x[start : start + (BLOCK - 1) * STRIDE + WIDTH])
            top = r.argmax(0)
            value = r[top, np.arange(FILTERS)]
            better = value > best
            best[better], at[better] = value[better], start + top[better] * STRIDE
        return best + self.shift, at, x

    def score(self, data: bytes) -> float:
        h = np.maximum(self.pooled(data)[0], 0)
        return float(1 / (1 + np.exp(-float(h @ self.out) - self.bias)))


def padded(data: bytes) -> np.ndarray:
    """The bytes with zeros behind, so that windows cover every byte; an empty text is one window of zeros."""
    n = max(1, -(-max(0, len(data) - WIDTH) // STRIDE) + 1)
    x = np.zeros((n - 1) * STRIDE + WIDTH, np.uint8)
    x[: len(data)] = np.frombuffer(data, np.uint8)
    return x


def fit(texts: list[bytes], labels: list[int], rounds: int = 14, rate: float = 0.02, seed: int = 7) -> Net:
    """Adam on the class-balanced log loss; only the window that each filter keeps gets a gradient."""
    rng = np.random.default_rng(seed)
    net = Net(rng.normal(0, 0.15, (WIDTH, 256, FILTERS)).astype(np.float32), np.zeros(FILTERS, np.float32), rng.normal(0, 0.3, FILTERS).astype(np.float32), 0.0)
    y = np.asarray(labels, float)
    if not len(y):
        net.out[:] = 0
        return net
    share = y.mean()
    weight = np.where(y == 1, 0.5 / max(share, 1e-9), 0.5 / max(1 - share, 1e-9))
    params = [net.table, net.shift, net.out, np.zeros(1, np.float32)]
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in params]
    offsets, step = np.arange(WIDTH)[:, None], 0
    for epoch in range(rounds):
        order = rng.permutation(len(texts))
        for some in np.array_split(order, max(1, len(order) // 24)):
            grads = [np.zeros_like(p) for p in params]
            for i in some:
                h, at, x = net.pooled(texts[i])
                on = h > 0
                h = np.maximum(h, 0)
                p = 1 / (1 + np.exp(-float(h @ net.out) - float(params[3][0])))
                d = (p - y[i]) * weight[i] / len(some)
                back = (d * net.out * on).astype(np.float32)
                # An off filter gets a small pull, so that none stays off for good.
                back = np.where(on, back, (0.01 * d * net.out).astype(np.float32))
                grads[0][offsets, x[at[None, :] + offsets], np.arange(FILTERS)[None, :]] += back[None, :]
                grads[1] += back
                grads[2] += (d * h).astype(np.float32)
                grads[3] += d
            step += 1
            lr = rate * (1 - 0.8 * epoch / rounds)
            for p, g, (m, v) in zip(params, grads, moments):
                g = g + 1e-5 * p
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                p -= lr * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-6)
    net.bias = float(params[3][0])
    return net


def training_rows(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, longest: int = LONGEST) -> tuple[list[bytes], list[int]]:
    """At most per_class labelled documents of each class, by hash of their id, outside the held-out third.

    A document with both labels, or with none of 0 and 1, is not learnt from.
    """
    named = labels.where("quality in (0, 1)").where(fold(F.col("doc_id")) % 3 != 1)
    named = named.groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("quality").alias("q2")).where("q = q2")
    sample = None
    for q in (0, 1):
        part = named.where(F.col("q") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        sample = part if sample is None else sample.union(part)
    rows = docs.where(F.octet_length("text") <= longest).join(F.broadcast(sample), "doc_id").select("doc_id", "q", "text").collect()  # at most 2 * per_class
    rows = sorted(rows, key=lambda r: (r["doc_id"], r["text"]))
    return [r["text"].encode() for r in rows], [r["q"] for r in rows]


def scored(docs: DataFrame, net: Net, name: str = "score") -> DataFrame:
    """docs with the score of every whole text, of any length; null counts as empty, rows that repeat get the same score.

    The score depends on the text's bytes alone; other columns pass through, but for one of the score's name, which gives way. An empty table gives an empty result.
    """
    docs = docs.drop(name)
    shared = docs.sparkSession.sparkContext.broadcast(net)  # a fixed size: WIDTH * 256 * FILTERS numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).cast(pa.binary()).to_pylist()
            scores = pa.array([model.score(x or b"") for x in texts], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, scores], names=[*batch.schema.names, name])

    return docs.mapInArrow(trimmed(run), StructType([*docs.schema.fields, StructField(name, DoubleType())]))


def judged(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Fits on a bounded labelled sample and judges all: doc_id, held_out, score, predicted."""
    docs = docs.select("doc_id", "text")
    out = scored(docs, fit(*training_rows(docs, labels.select("doc_id", "quality"))))
    return out.select("doc_id", (fold(F.col("doc_id")) % 3 == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
