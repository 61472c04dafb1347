"""Approximate nearest neighbours: a forest of random-projection trees, one priority queue, exact reranking.

The trees are split on a bounded sample; every vector is then put into its leaf of every tree. A query ranks
the leaves of all trees together by the worst margin on the way to them, as a queue shared by the trees pops
them, and looks into the first ones. How many is measured: a few probes are compared with all rows, and so many leaves
are popped that TARGET of their nearest neighbours are met. Leaf members travel as packed arrays and meet the queries that look into
their leaf; cosines are exact on the original numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors that the trees are split on at most, and trees.
SAMPLE, TREES = 8192, 8
#: Probes by which the number of leaves is measured, and the share of their neighbours that must be met.
PROBES, TARGET = 128, 0.96
#: Sampled vectors that a leaf has at least: few vectors make fewer leaves, and very few are all compared.
LEAST = 64
SEED = 11


class Forest:
    """Complete trees of depth levels over unit vectors: normals and thresholds by level order."""

    def __init__(self, sample: np.ndarray, trees: int = TREES, depth: int = 5, seed: int = SEED) -> None:
        rng = np.random.default_rng(seed)
        nodes, dims = (1 << depth) - 1, sample.shape[1]
        self.depth, self.trees, self.leaves = depth, trees, 1 << depth
        self.normals, self.cuts = np.zeros((trees, nodes, dims)), np.zeros((trees, nodes))
        counts = np.zeros((trees, self.leaves), np.int64)
        for t in range(trees):
            members = {0: np.arange(len(sample))}
            for node in range(nodes):
                own = members.pop(node, np.arange(0))
                normal = rng.normal(size=dims)
                if len(own) > 1:  # between the means of two random halves, so that splits follow the data
                    pick = rng.permutation(own)[:32]
                    normal = sample[pick[::2]].mean(0) - sample[pick[1::2]].mean(0) + 1e-9 * normal
                self.normals[t, node] = normal / np.linalg.norm(normal)
                side = sample[own] @ self.normals[t, node]
                self.cuts[t, node] = np.median(side) if len(own) else 0.0
                right = side > self.cuts[t, node]
                for k, part in ((2 * node + 1, own[~right]), (2 * node + 2, own[right])):
                    if k < nodes:
                        members[k] = part
                    else:
                        counts[t, k - nodes] = len(part)
        #: Pieces into which a leaf is dealt that holds far more than its share, as repeated vectors make it.
        self.pieces = np.maximum(1, -(-counts * self.leaves // max(1, 2 * len(sample)))).astype(np.int64)

    def margins(self, unit: np.ndarray, t: int) -> np.ndarray:
        return unit @ self.normals[t].T - self.cuts[t]

    def leaf(self, unit: np.ndarray, t: int) -> np.ndarray:
        """The leaf of each vector in tree t."""
        m, node = self.margins(unit, t), np.zeros(len(unit), np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (m[np.arange(len(unit)), node] > 0)
        return node - (self.leaves - 1)

    def order(self, unit: np.ndarray) -> np.ndarray:
        """All leaves of all trees, (queries, trees * leaves), in the order in which the shared queue pops them:
        by the smallest signed margin on the way, the largest first."""
        worst = []
        for t in range(self.trees):
            m = self.margins(unit, t)
            reach = np.full((len(unit), 1), np.inf)
            for level in range(self.depth):
                first = (1 << level) - 1
                here = m[:, first : 2 * first + 1]
                reach = np.minimum(np.repeat(reach, 2, 1), np.stack([-here, here], 2).reshape(len(unit), -1))
            worst.append(reach)
        return np.argsort(-np.concatenate(worst, 1), axis=1, kind="stable")


def vectors_of(column: pa.Array, dims: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The usable rows of a list column: their places and their numbers in double precision.

    Null, zero and differently long vectors, and those with null or non-finite components, are none.
    """
    lists = pa.array(column).cast(pa.list_(pa.float64()))
    lengths = np.array([-1 if n is None else n for n in lists.value_lengths().to_pylist()])
    dims = dims if dims is not None else (int(np.bincount(lengths[lengths > 0]).argmax()) if (lengths > 0).any() else 1)
    at = np.nonzero(lengths == dims)[0]
    flat = lists.take(pa.array(at)).flatten().to_numpy(zero_copy_only=False).reshape(-1, dims) if len(at) else np.zeros((0, dims))
    norms = np.linalg.norm(flat, axis=1)
    good = np.isfinite(flat).all(1) & (norms > 0) & np.isfinite(norms)
    return at[good], flat[good]


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def best_of(queries: np.ndarray, ids: np.ndarray, qx: np.ndarray, x: np.ndarray, k: int, places: bool = False) -> Iterator[tuple]:
    """The k nearest of x to each query, exactly and with ties to the smaller id, in blocks: (query, id, score), and the place in x if asked.

    A fast product finds what can be among them; their cosines are then computed one by one, each in the same
    order of operations wherever the pair is met.
    """
    u, norms = unit(x), np.sqrt((x * x).sum(1))
    for start in range(0, len(queries), 512):
        some, own = qx[start : start + 512], queries[start : start + 512]
        rough = unit(some) @ u.T
        rough[own[:, None] == ids[None, :]] = -9.0
        least = np.partition(rough, -k, axis=1)[:, -k] if rough.shape[1] > k else np.full(len(some), -8.0)
        i, j = np.nonzero(rough >= np.maximum(least - 1e-9, -8.0)[:, None])
        score = (some[i] * x[j]).sum(1) / (np.sqrt((some * some).sum(1))[i] * norms[j])
        order = np.lexsort((ids[j], -score, i))
        i, j, score = i[order], j[order], score[order]
        rank = np.arange(len(i)) - np.searchsorted(i, i)
        i, j, score = i[rank < k], j[rank < k], score[rank < k]
        yield (own[i], ids[j], score, j) if places else (own[i], ids[j], score)


def probed(d: DataFrame, forest: Forest, ids: np.ndarray, x: np.ndarray, k: int, target: float) -> int:
    """Leaves that must be popped for a share of target of the k nearest of the probes: these are found among all rows."""
    shared = d.sparkSession.sparkContext.broadcast((ids, x))  # at most PROBES vectors

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, qx = shared.value
        for batch in batches:
            at, y = vectors_of(batch.column(1), qx.shape[1])
            for q, i, score, j in best_of(own, batch.column(0).to_numpy(zero_copy_only=False)[at], qx, y, k, places=True):
                yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(i), pa.array(score), pa.array(unit(y)[j].tolist(), pa.list_(pa.float64()))], names=["q", "id", "score", "u"])

    found = d.mapInArrow(run, "q long, id long, score double, u array<double>").dropDuplicates(["q", "id"])
    found = found.withColumn("rank", F.row_number().over(Window.partitionBy("q").orderBy(F.col("score").desc(), "id"))).where(F.col("rank") <= k).select("q", "u").toArrow()  # at most PROBES * k rows
    if not found.num_rows:
        return 1
    u = np.array(found.column("u").to_pylist())
    row = {int(q): i for i, q in enumerate(ids)}
    place = np.empty((len(ids), forest.trees * forest.leaves), np.int64)
    np.put_along_axis(place, forest.order(unit(x)), np.arange(place.shape[1])[None, :], 1)
    which = np.array([row[q] for q in found.column("q").to_pylist()])
    met = np.min([place[which, t * forest.leaves + forest.leaf(u, t)] for t in range(forest.trees)], axis=0)
    return int(np.sort(met)[int(np.ceil(target * len(met))) - 1]) + 1


def nearest(rows: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 50, k: int = 5, sample: int = SAMPLE, trees: int = TREES, target: float = TARGET) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found by cosine of every row whose id is divisible by every.

    All rows are indexed; the trees are split on at most sample of them, those with the smallest hashes of
    their ids. With fewer than k candidates all are returned. A target of 1.0 or more is the exact way: one tree, all of whose leaves are looked into. Rows with unusable vectors (also those of another length than most of the sample) or
    null ids take no part; an id that repeats with the same vector counts once; other columns are not read. An empty table gives an empty result.
    """
    spark = rows.sparkSession
    trees = 1 if target >= 1 else trees
    d = rows.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("v")).where("id is not null and v is not null")
    single = "array<float>" in d.schema["v"].dataType.simpleString()  # numbers travel in their own precision
    width = "<f4" if single else "<f8"
    picked = d.orderBy(F.xxhash64("id"), "id").limit(sample).select("id", "v").toArrow()  # at most sample rows
    at, x = vectors_of(picked.column("v").combine_chunks())
    dims = x.shape[1]
    depth = max(0, int(np.log2(max(1, len(x)) / LEAST)))
    forest = Forest(unit(x), trees, depth)
    ids, first = np.unique(picked.column("id").to_numpy()[at], return_index=True)
    some = np.random.default_rng(SEED).permutation(len(ids))[:PROBES]
    pops = trees * forest.leaves if target >= 1 or not depth else probed(d, forest, ids[some], x[first[some]], k, target)
    shared = spark.sparkContext.broadcast(forest)  # trees * 2^depth * dims numbers

    def deal(ids: np.ndarray, x: np.ndarray, cell: np.ndarray, kind: int) -> pa.RecordBatch:
        order = np.argsort(cell, kind="stable")
        cells, starts = np.unique(cell[order], return_index=True)
        ends = [*starts[1:], len(order)]
        packed = [(ids[order[a:b]].astype("<i8").tobytes(), x[order[a:b]].astype(width).tobytes()) for a, b in zip(starts, ends)]
        return pa.RecordBatch.from_arrays([pa.array(cells.astype(np.int64)), pa.array([kind] * len(cells), pa.int32()), pa.array([p[0] for p in packed], pa.binary()), pa.array([p[1] for p in packed], pa.binary())], names=["cell", "kind", "ids", "xs"])

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = shared.value
        most = int(forest.pieces.max())
        for batch in batches:
            at, x = vectors_of(batch.column(1), dims)
            ids, u = batch.column(0).to_numpy(zero_copy_only=False)[at], unit(x)
            if not len(ids):
                continue
            salt = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)
            for t in range(forest.trees):
                leaf = forest.leaf(u, t)
                piece = (salt % forest.pieces[t][leaf].astype(np.uint64)).astype(np.int64)
                yield deal(ids, x, (t * forest.leaves + leaf) * most + piece, 0)
            asks = ids % every == 0
            if asks.any():
                qi, qx = ids[asks], x[asks]
                look = forest.order(u[asks])[:, :pops]
                who = np.repeat(np.arange(len(qi)), look.shape[1])
                pieces = forest.pieces.reshape(-1)[look.reshape(-1)]
                within = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
                yield deal(qi[np.repeat(who, pieces)], qx[np.repeat(who, pieces)], np.repeat(look.reshape(-1), pieces) * most + within, 1)

    def search(table: pa.Table) -> pa.Table:
        kind = np.array(table.column("kind").to_pylist())
        ids = [np.frombuffer(b, "<i8") for b in table.column("ids").to_pylist()]
        xs = [np.frombuffer(b, width).astype(np.float64).reshape(-1, dims) for b in table.column("xs").to_pylist()]
        out: list[tuple] = []
        if (kind == 0).any() and (kind == 1).any():
            side = lambda what, of: np.concatenate([what[i] for i in np.nonzero(kind == of)[0]])
            qi, qx = side(ids, 1), side(xs, 1)
            members, mx = side(ids, 0), side(xs, 0)
            for start in range(0, len(members), 65_536):
                out += best_of(qi, members[start : start + 65_536], qx, mx[start : start + 65_536], k)
        q, v, s = (np.concatenate([o[i] for o in out]) if out else np.zeros(0, np.float64 if i == 2 else np.int64) for i in range(3))
        return pa.table({"query_id": pa.array(q, pa.int64()), "vec_id": pa.array(v, pa.int64()), "score": pa.array(s, pa.float64())})

    dealt = d.mapInArrow(index, "cell long, kind int, ids binary, xs binary")
    found = dealt.groupBy("cell").applyInArrow(search, "query_id long, vec_id long, score double").distinct()
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
