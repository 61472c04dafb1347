"""Language-model scoring with a hierarchical Pitman-Yor process.

Three levels: a restaurant for each previous word, all of which share one unigram restaurant as parent, above a
uniform base over the vocabulary and one unknown word. A dish is a word; the customers of a dish in a restaurant
sit at tables, and each table is a customer of the same dish in the parent. Only the number of tables of each dish
matters; it is sampled by Gibbs.

Given a gamma variable for each restaurant, with the restaurant's tables as its shape, the table counts of all its
dishes are independent: P(t) is proportional to S(c, t) a^t, with S the generalised Stirling numbers, c the dish's customers
and a the discount times the gamma variable times the dish's probability in the parent. So a sweep draws the gamma
variables from the last totals, then all table counts at once, and then every total is summed anew: the counts of a
sweep, at both levels, always belong together, and predictive probabilities add up to one in every context. The parent
enters as its predictive distribution. Predictive probabilities are averaged over the samples.

Words are told apart by 64-bit hashes. Tasks pack whole documents into blocks and send each block's different pairs
of words to chunks; a chunk holds all dishes of a range of contexts, and a context with very many customers is dealt to
several chunks by dish. Chunks and the unigram restaurant exchange sums by word after every sweep. At the end chunks
answer every block with the probabilities of its pairs, and blocks add them up by document.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, forget, materialize, trim
from .ngram_join import LOWERED

#: Discount and strength of the context level and of the unigram level.
D2, T2, D1, T1 = 0.75, 2.0, 0.6, 1.0
#: Sweeps before the first sample, and samples whose predictive probabilities are averaged.
BURN_IN, SAMPLES = 2, 3
#: Tokens that make a block of documents, and a chunk of contexts; bytes of a text that are split at once. Bounds on memory.
BLOCK, CHUNK, PIECE = 800_000, 1_500_000, 1 << 21
#: Different words that a task counts at once.
WINDOW = 150_000
#: Customers of a dish up to which table counts are drawn from the table of Stirling numbers; beyond, from the limit law.
EXACT = 128
SEED = 5
SPACE = re.compile(rb"[\x20\x09-\x0D]")


def packed(a: np.ndarray) -> bytes:
    """Numbers byte plane by byte plane, compressed."""
    planes = np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T) if len(a) else np.zeros(0, np.uint8)
    return len(a).to_bytes(8, "little") + (pa.compress(planes.tobytes(), "zstd", asbytes=True) if len(a) else b"")


def unpacked(data: bytes, kind: str) -> np.ndarray:
    n, size = int.from_bytes(data[:8], "little"), np.dtype(kind).itemsize
    if not n:
        return np.zeros(0, kind)
    planes = np.frombuffer(pa.decompress(data[8:], n * size, "zstd", asbytes=True), np.uint8).reshape(size, n)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def share(h: np.ndarray, parts: int | np.ndarray) -> np.ndarray:
    """Which of so many equal ranges of hashes each is in."""
    return ((h >> np.uint64(32)) * np.asarray(parts, np.uint64) >> np.uint64(32)).astype(np.int64)


def stirling(discount: float, most: int = EXACT) -> np.ndarray:
    """Logs of the generalised Stirling numbers S(c, t): the weight of all seatings of c customers at t tables."""
    s = np.full((most + 1, most + 1), -np.inf)
    s[0, 0] = 0.0
    for c in range(1, most + 1):
        t = np.arange(1, c + 1)
        with np.errstate(divide="ignore"):
            s[c, 1 : c + 1] = np.logaddexp(s[c - 1, t - 1], np.where(t < c, s[c - 1, t] + np.log(np.maximum(c - 1 - discount * t, 1e-300)), -np.inf))
    return s


def many_tables(c: np.ndarray, a: np.ndarray, discount: float, rng: np.random.Generator) -> np.ndarray:
    """Tables of dishes with very many customers. Seatings are tables in Poisson number, of independent sizes, given
    that the sizes sum to c; for large c the number follows a normal law, or a Poisson law where it is small."""
    lo, hi = np.zeros(len(c)), np.full(len(c), 700.0)  # x = 1 - exp(-y): the tilt at which sizes sum to c on average
    for _ in range(60):
        y = (lo + hi) / 2
        above = np.log(a) + np.log(-np.expm1(-y)) + (1 - discount) * y > np.log(c)
        lo, hi = np.where(above, lo, y), np.where(above, y, hi)
    y = (lo + hi) / 2
    mean = a * -np.expm1(-discount * y) / discount
    spread = np.sqrt(np.maximum(mean - c / (1 + (1 - discount) * np.expm1(y)), 0.0))
    t = np.where(mean < 30, 1 + rng.poisson(np.minimum(mean, 30.0)), np.rint(rng.normal(mean, spread)))
    return np.clip(t, 1, c).astype(np.int64)


def tables(c: np.ndarray, log_a: np.ndarray, discount: float, table: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Draws the number of tables of each dish with P(t) in proportion to S(c, t) a^t. A dish with one customer has one."""
    t = np.minimum(c, 1)
    low = 1
    while low < EXACT:
        high = min(2 * low, EXACT)
        at, k = np.nonzero((c > low) & (c <= high))[0], np.arange(1, high + 1)
        for start in range(0, len(at), step := max(1, 400_000 // high)):
            some = at[start : start + step]
            w = table[c[some], 1 : high + 1] + log_a[some][:, None] * k
            t[some] = 1 + (w + rng.gumbel(size=w.shape)).argmax(1)
        low = high
    at = np.nonzero(c > EXACT)[0]
    if len(at):
        t[at] = many_tables(c[at], np.exp(log_a[at]), discount, rng)
    return t


def words_of(text: bytes | None) -> Iterator[list[bytes]]:
    """The words of a text in order, piece by piece, and an empty one at the end."""
    at, text = 0, text or b""
    while len(text) - at > PIECE:
        m = SPACE.search(text, at + PIECE)
        end = m.end() if m else len(text)
        yield text[at:end].translate(LOWERED).split()
        at = end
    yield [*text[at:].translate(LOWERED).split(), b""]


def few(batch: pa.RecordBatch, at_once: int = 128) -> Iterator[tuple]:
    """The rows of a batch, a few of them as Python objects at a time."""
    for start in range(0, batch.num_rows, at_once):
        yield from zip(*(c.to_pylist() for c in batch.slice(start, at_once).columns))


def hash_of(word: bytes) -> int:
    import xxhash

    return xxhash.xxh3_64_intdigest(word)


def crowded(docs: DataFrame, chunk: int) -> tuple[int, dict[int, int]]:
    """Tokens of all texts, and the words that occur more often than half a chunk's tokens: fewer than two a chunk."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()

        def given() -> pa.RecordBatch:
            h = np.fromiter(map(hash_of, seen), np.uint64, len(seen)).view(np.int64)
            n = np.fromiter(seen.values(), np.int64, len(seen))
            mask = np.zeros(len(h) + 1, bool)
            mask[-1] = True  # the sum of all goes without a word
            return pa.RecordBatch.from_arrays([pa.array(np.append(h, 0), pa.int64(), mask=mask), pa.array(np.append(n, n.sum()))], names=["h", "n"])

        for batch in batches:
            for (text,) in few(batch):
                for words in words_of(text):
                    seen.update(words)
                    if len(seen) > WINDOW:
                        yield given()
                        seen.clear()
        yield given()
        seen.clear()
        trim()

    counted = docs.select(F.col("text").cast("string").cast("binary")).mapInArrow(run, "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))
    rows = materialize(counted.where(f"h is null or n > {chunk // 2}"), "crowded").collect()  # fewer than two a chunk
    total = sum(r["n"] for r in rows if r["h"] is None)
    return total, {r["h"] % (1 << 64): r["n"] for r in rows if r["h"] is not None}


class Deal:
    """Which chunk a pair of words belongs to: by range of its context, or for crowded contexts by context and range of its dish."""

    def __init__(self, total: int, often: dict[int, int], chunk: int) -> None:
        self.chunks = self.ranges = max(1, -(-total // chunk))
        self.names = np.array(sorted(often), np.uint64)
        self.pieces = np.array([-(-2 * often[int(h)] // chunk) for h in self.names], np.int64)
        self.first = self.ranges + np.cumsum(self.pieces) - self.pieces
        self.chunks += int(self.pieces.sum())

    def places(self, names: np.ndarray) -> np.ndarray:
        """The place of each context among the crowded ones, or -1."""
        if not len(self.names):
            return np.full(len(names), -1)
        at = np.minimum(np.searchsorted(self.names, names), len(self.names) - 1)
        return np.where(self.names[at] == names, at, -1)

    def of(self, names: np.ndarray, ctx: np.ndarray, dish: np.ndarray) -> np.ndarray:
        """names: hashes; ctx and dish: their places in names, of each pair."""
        out, hot = share(names, self.ranges)[ctx], self.places(names)[ctx]
        at = np.nonzero(hot >= 0)[0]
        out[at] = self.first[hot[at]] + share(names[dish[at]], self.pieces[hot[at]])
        return out


ROWS = "chunk long, block long, a binary, b binary, c binary, d binary, e binary"


def batch_of(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "binary": pa.binary(), "double": pa.float64()}
    fields = [f.split() for f in schema.split(", ")]
    cols = list(zip(*rows)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields)], names=[n for n, _ in fields])


def blocks_of(docs: DataFrame, deal: Deal) -> DataFrame:
    """Packs the pairs of words of whole documents. Rows of a chunk >= 0 have a block's pairs for that chunk, by context and
    dish: contexts, pairs of each, dishes, occurrences to learn from. Rows with chunk -1 keep for a block: keys and ids of its documents, their lengths, which ids are null;
    and for all pairs of the block, by chunk, context and dish, how often each occurs and in which documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), 0
        local: dict[bytes, int] = {b"": 0}
        held: list[tuple] = []  # key, id, learnt, lengths, local words, the one before the first
        count = row = 0

        def given() -> Iterator[pa.RecordBatch]:
            nonlocal made, count
            block, made = (part << 28) + made, made + 1
            names = np.fromiter(map(hash_of, local), np.uint64, len(local))
            order = np.argsort(names)
            rank = np.empty(len(order), np.int64)
            rank[order] = np.arange(len(order))
            names = names[order]
            lens = np.array([len(x[3]) for x in held])
            key = np.concatenate([x[3] for x in held])
            dish = rank[key].astype(np.int32)
            key = np.empty(len(dish), np.int64)  # context and dish in one number
            key[1:] = dish[:-1]
            key[np.cumsum(lens) - lens] = rank[[x[4] for x in held]]
            key *= len(names)
            key += dish
            del dish
            by = np.argsort(key, kind="stable").astype(np.int32)
            key = key[by]
            doc = np.repeat(np.arange(len(held), dtype=np.int32), lens)[by]
            del by
            starts = np.nonzero(np.concatenate([[True], key[1:] != key[:-1]]))[0]
            key = key[starts]
            times = np.diff(np.append(starts, len(doc))).astype(np.int32)
            learnt = np.add.reduceat(np.array([x[2] for x in held], np.int32)[doc], starts)
            ctx, dish = (x.astype(np.int32) for x in np.divmod(key, len(names)))
            del key
            chunk = deal.of(names, ctx, dish).astype(np.int32)
            by = np.argsort(chunk, kind="stable")
            ctx, dish, chunk, learnt, times, where = ctx[by], dish[by], chunk[by], learnt[by], times[by], starts[by]
            del by, starts
            place = np.arange(len(doc), dtype=np.int32)
            place += np.repeat((where - np.cumsum(times, dtype=np.int64) + times).astype(np.int32), times)
            doc = doc[place]
            del place, where
            ids = np.array([x[1] or 0 for x in held], "<i8")
            null = np.array([x[1] is None for x in held], "u1")
            rows = [(-1, block, packed(np.array([x[0] for x in held], "<i8")) , packed(ids) + null.tobytes(), packed(lens.astype("<u4")), packed(times.astype("<u4")), packed(doc.astype("<u2" if len(held) <= 1 << 16 else "<u4")))]
            edges = np.nonzero(np.concatenate([[True], chunk[1:] != chunk[:-1], [True]]))[0]
            for lo, hi in zip(edges[:-1], edges[1:]):
                new = np.nonzero(np.concatenate([[True], ctx[lo + 1 : hi] != ctx[lo : hi - 1], [True]]))[0]
                rows.append((int(chunk[lo]), block, names[ctx[lo:hi][new[:-1]]].astype("<u8").tobytes(), packed(np.diff(new).astype("<u4")), names[dish[lo:hi]].astype("<u8").tobytes(), packed(learnt[lo:hi].astype("<u4")), b""))
            held.clear()
            local.clear()
            local[b""] = count = 0
            for start in range(0, len(rows), 256):
                yield batch_of(rows[start : start + 256], ROWS)

        for batch in batches:
            for doc, out, text in few(batch):
                row += 1
                before = b""
                for words in words_of(text):
                    if not words:
                        continue
                    first = local.setdefault(before, len(local))
                    numbers = np.fromiter((local.setdefault(w, len(local)) for w in words), np.int32, len(words))
                    held.append(((part << 36) + row, doc, not out, numbers, first))
                    before = words[-1]
                    count += len(words)
                    if count >= BLOCK or len(held) >= 1 << 16:
                        yield from given()
        if held:
            yield from given()
        trim()

    d = docs.select(F.col("doc_id").cast("long"), F.coalesce(fold(F.col("doc_id")) % 7 == 2, F.lit(False)).alias("out"), F.col("text").cast("string").cast("binary"))
    return d.mapInArrow(run, ROWS)


def merged(dealt: DataFrame) -> DataFrame:
    """Chunks with all their dishes, in ROWS: rows with block -1 hold what Dishes reads; rows with block -2 the tokens and dishes of
    each; the other rows say where a block's pairs are among the chunk's. Rows with chunk -1 pass through."""

    def join(table: pa.Table) -> pa.Table:
        if table.column("chunk")[0].as_py() < 0:
            return table
        chunk = table.column("chunk")[0].as_py()
        col = lambda name: table.column(name).to_pylist()
        given = [np.frombuffer(x, "<u8") for x in col("a")]
        sizes = [unpacked(x, "<u4") for x in col("b")]
        dishes = [np.frombuffer(x, "<u8") for x in col("c")]
        learnt = np.concatenate([unpacked(x, "<u4") for x in col("d")])
        ends = np.cumsum([len(x) for x in dishes])
        names, ctx = np.unique(np.concatenate(given), return_inverse=True)
        words, dish = np.unique(np.concatenate(dishes), return_inverse=True)
        del dishes
        key = np.repeat(ctx, np.concatenate(sizes)) * len(words) + dish
        del dish
        pairs, at = np.unique(key, return_inverse=True)
        c = np.bincount(at, learnt, len(pairs)).astype("<u4")
        ctx, dish = np.divmod(pairs, len(words))
        rows = [(chunk, -1, names.astype("<u8").tobytes(), packed(np.bincount(ctx, minlength=len(names)).astype("<u4")), words.astype("<u8").tobytes(), packed(dish.astype("<u4")), packed(c))]
        for block, some in zip(col("block"), np.split(at, ends[:-1])):
            rows.append((chunk, block, packed(np.diff(some, prepend=0).astype("<u4")), b"", b"", b"", b""))
        del key, at, ctx, dish, pairs
        trim()
        return pa.Table.from_batches([batch_of(rows, ROWS)])

    return dealt.groupBy(F.when(F.col("chunk") < 0, -1 - F.col("block")).otherwise(F.col("chunk")).alias("key")).applyInArrow(join, ROWS)


class Dishes:
    """The dishes of a chunk's contexts: which dish and context each is of, and its customers."""

    def __init__(self, row: dict) -> None:
        self.names, self.words = np.frombuffer(row["a"], "<u8"), np.frombuffer(row["c"], "<u8")
        self.ctx = np.repeat(np.arange(len(self.names)), unpacked(row["b"], "<u4"))
        self.word, self.c = unpacked(row["d"], "<u4").astype(np.int64), unpacked(row["e"], "<u4").astype(np.int64)

    def by_context(self, x: np.ndarray) -> np.ndarray:
        return np.bincount(self.ctx, x, len(self.names))

    def by_word(self, x: np.ndarray) -> np.ndarray:
        return np.bincount(self.word, x, len(self.words))


def gammas(names: np.ndarray, totals: np.ndarray, sweep: int, chunk: int, shared: np.ndarray) -> np.ndarray:
    """The gamma variable of each context; one whose dishes lie in several chunks (shared) draws the same in each."""
    g = np.random.default_rng([SEED, sweep, chunk, 1]).standard_gamma(T2 / D2 + totals)
    for i in np.nonzero(shared)[0]:
        g[i] = np.random.default_rng([SEED, sweep, int(names[i])]).standard_gamma(T2 / D2 + totals[i])
    return g


def predictive(c: np.ndarray, t: np.ndarray, customers: np.ndarray, opened: np.ndarray, parent: np.ndarray) -> np.ndarray:
    """Probability of a dish with c customers at t tables where all dishes have `customers` at `opened` tables, given its probability in the parent."""
    return (c - D2 * t + (T2 + D2 * opened) * parent) / (T2 + customers)


class Unigrams:
    """What a sweep leaves of the parent restaurant as a whole: words known, customers, tables."""

    def __init__(self, vocabulary: int, customers: int, opened: int) -> None:
        self.vocabulary, self.customers, self.opened = vocabulary, customers, opened

    def probability(self, n: np.ndarray, t: np.ndarray) -> np.ndarray:
        """Of a word with n customers at t tables."""
        return (n - D1 * t + (T1 + D1 * self.opened) / (self.vocabulary + 1)) / (T1 + self.customers)


STATE = "chunk long, part long, a binary, b binary, c binary, n long, m long"


def sums_of(x: Dishes, chunk: int, parts: int, t: np.ndarray, extra: np.ndarray | None = None) -> list[tuple]:
    """Tables by word, dealt by range of words."""
    total, part = x.by_word(t).astype("<u4"), share(x.words, parts)
    edges = np.searchsorted(part, np.arange(parts + 1))
    return [(chunk, p, x.words[lo:hi].tobytes(), packed(total[lo:hi]), packed(extra[lo:hi]) if extra is not None else b"", 0, 0) for p, (lo, hi) in enumerate(zip(edges[:-1], edges[1:])) if lo < hi]


class Model:
    """The chain over written tables: dishes of chunks, last table counts, last sums by word."""

    def __init__(self, docs: DataFrame, chunk: int = CHUNK) -> None:
        total, often = crowded(docs, chunk)
        self.deal, self.sweeps = Deal(total, often, chunk), 0
        self.chunks = materialize(merged(blocks_of(docs, self.deal)), "dishes")
        self.dishes = self.chunks.where("chunk >= 0 and block = -1").drop("block")
        deal, parts = self.deal, self.deal.ranges

        def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    row = batch.slice(i, 1).to_pylist()[0]
                    x, t = Dishes(row), None
                    t = np.minimum(x.c, 1)
                    yield batch_of([*hot_rows(x, t, deal, row["chunk"], True), *sums_of(x, row["chunk"], parts, t, x.by_word(x.c).astype("<u4")), (row["chunk"], -1, packed(t.astype("<u4")), b"", b"", int(x.c.sum()), 0)], STATE)

        self.state = materialize(self.dishes.mapInArrow(start, STATE), "seats")
        self.tokens = self.state.where("part = -1").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        self.hot = self.hot_totals("customers")
        self.words = self.up = None
        self.samples: list[tuple[Unigrams, np.ndarray, DataFrame]] = []
        self.exchange()

    def hot_totals(self, what: str) -> np.ndarray:
        """Customers or tables of the crowded contexts, each summed over its chunks."""
        kind = -2 if what == "customers" else -3
        rows = {r["m"]: r["s"] for r in self.state.where(F.col("part") == kind).groupBy("m").agg(F.sum("n").alias("s")).collect()}  # one row for each crowded context
        return np.array([rows.get(i, 0) for i in range(len(self.deal.names))], np.int64)

    def exchange(self) -> None:
        """Sums tables by word, seats them in the parent, and answers every chunk: customers, tables, training tokens of its words."""
        first = self.words is None
        gamma = None if first else np.random.default_rng([SEED, self.sweeps]).standard_gamma(T1 / D1 + self.up.opened)
        sweep, vocabulary = self.sweeps, 0 if first else self.up.vocabulary

        def add(table: pa.Table) -> pa.Table:
            part, chunks = table.column("part")[0].as_py(), table.column("chunk").to_pylist()
            names = [np.frombuffer(x, "<u8") for x in table.column("a").to_pylist()]
            sums = np.concatenate([unpacked(x, "<u4") for x in table.column("b").to_pylist()])
            words, at = np.unique(np.concatenate(names), return_inverse=True)
            cuts = np.cumsum([len(x) for x in names])[:-1]
            n = np.bincount(at, sums, len(words)).astype(np.int64)
            tokens = None
            if first:
                t = np.minimum(n, 1)
                tokens = np.bincount(at, np.concatenate([unpacked(x, "<u4") for x in table.column("c").to_pylist()]), len(words)).astype("<u8")
            else:
                log_a = np.full(len(n), np.log(D1 * gamma / (vocabulary + 1)))
                t = tables(n, log_a, D1, stirling(D1), np.random.default_rng([SEED, sweep, part, 2]))
            split = lambda x, kind: [packed(y) for y in np.split(x.astype(kind)[at], cuts)]
            known = split(tokens, "<u8") if first else [b""] * len(chunks)
            rows = [(k, part, a, b, c, 0, 0) for k, a, b, c in zip(chunks, split(n, "<u8"), split(t, "<u8"), known)]
            rows.append((-1, part, b"", b"", b"", int(n.sum()), int(t.sum())))
            rows.append((-2, part, b"", b"", b"", int((n > 0).sum()), 0))
            return pa.Table.from_batches([batch_of(rows, STATE)])

        old, new = self.words, materialize(self.state.where("part >= 0").groupBy("part").applyInArrow(add, STATE), "words")
        sums = {r["chunk"]: r for r in new.where("chunk < 0").groupBy("chunk").agg(F.sum("n").alias("n"), F.sum("m").alias("m")).collect()}
        if first:
            self.known = new
            vocabulary = sums[-2]["n"] if sums else 0
        elif old is not self.known and not any(old is x[2] for x in self.samples):
            forget(old)
        self.up = Unigrams(vocabulary, sums[-1]["n"] if sums else 0, sums[-1]["m"] if sums else 0)
        self.words, self.opened = new, self.hot_totals("tables")

    def seats(self) -> DataFrame:
        """What a chunk needs besides its dishes: its last tables, and the last sums of its words."""
        return self.state.where("part = -1").union(self.words.where("chunk >= 0"))

    def step(self, keep: bool) -> None:
        """One sweep over all restaurants. keep: the state before it is a sample."""
        deal, up, parts, opened, sweep = self.deal, self.up, self.deal.ranges, self.opened, self.sweeps + 1
        if keep:
            self.samples.append((self.up, self.opened, self.words))

        def move(rows: pa.Table, seats: pa.Table) -> pa.Table:
            row = rows.to_pylist()[0]
            chunk, x = row["chunk"], Dishes(row)
            seen = Seats(seats)
            place = deal.places(x.names)
            totals = whole(x.by_context(seen.now), place, opened)
            g = gammas(x.names, totals, sweep, chunk, place >= 0)
            log_a = np.log(D2) + np.log(g)[x.ctx] + np.log(up.probability(*seen.parents()))[x.word]
            t = tables(x.c, log_a, D2, stirling(D2), np.random.default_rng([SEED, sweep, chunk]))
            past = np.concatenate([seen.past, seen.now]) if keep else seen.past
            mine = (chunk, -1, packed(t.astype("<u4")), packed(past.astype("<u4")), b"", 0, 0)
            return pa.Table.from_batches([batch_of([mine, *hot_rows(x, t, deal, chunk), *sums_of(x, chunk, parts, t)], STATE)])

        moved = self.dishes.groupBy("chunk").cogroup(self.seats().groupBy("chunk")).applyInArrow(move, STATE)
        old, self.state = self.state, materialize(moved, "seats")
        self.sweeps = sweep
        forget(old)
        self.exchange()

    def answers(self) -> DataFrame:
        """block, chunk, a, b: log10 probability of every pair of a block, averaged over the samples, and training tokens of its dish."""
        every = [*self.samples, (self.up, self.opened, self.words)]
        deal, hot, facts = self.deal, self.hot, [x[:2] for x in every]

        def answer(rows: pa.Table, seats: pa.Table) -> pa.Table:
            block = rows.column("block").to_pylist()
            own = block.index(-1)
            row = rows.slice(own, 1).to_pylist()[0]
            x, seen = Dishes(row), Seats(seats)
            place = deal.places(x.names)
            customers = whole(x.by_context(x.c), place, hot)[x.ctx]
            sat = [*seen.past.reshape(-1, len(x.c)), seen.now] if len(x.c) else [seen.now]
            p = np.zeros(len(x.c))
            for k, (up, opened) in enumerate(facts):
                p += predictive(x.c, sat[k], customers, whole(x.by_context(sat[k]), place, opened)[x.ctx], up.probability(*seen.parents(k))[x.word])
            log_p = np.log10(p / len(facts)).astype("<f4")
            known = seen.known()[x.word]
            kind = "<u4" if known.max(initial=0) < 1 << 32 else "<u8"
            out = []
            for i, b in enumerate(block):
                if i != own:
                    at = np.cumsum(unpacked(rows.column("a")[i].as_py(), "<u4").view("<i4").astype(np.int64))
                    out.append((b, row["chunk"], packed(log_p[at]), packed(known[at].astype(kind)), int(kind == "<u8")))
            return pa.Table.from_batches([batch_of(out, ANSWERS)])

        seats = self.state.where("part = -1").union(self.known.where("chunk >= 0").withColumn("n", F.lit(-1).cast("long")))
        for k, (_, _, words) in enumerate(every):
            seats = seats.union(words.where("chunk >= 0").withColumn("n", F.lit(k).cast("long")))
        return self.chunks.where("chunk >= 0").groupBy("chunk").cogroup(seats.groupBy("chunk")).applyInArrow(answer, ANSWERS)


ANSWERS = "block long, chunk long, a binary, b binary, wide long"


def hot_rows(x: Dishes, t: np.ndarray, deal: Deal, chunk: int, customers: bool = False) -> list[tuple]:
    """A chunk's share of the crowded contexts it has: tables, and at first customers."""
    place = deal.places(x.names)
    out = []
    for i in np.nonzero(place >= 0)[0]:
        out.append((chunk, -3, b"", b"", b"", int(t[x.ctx == i].sum()), int(place[i])))
        if customers:
            out.append((chunk, -2, b"", b"", b"", int(x.c[x.ctx == i].sum()), int(place[i])))
    return out


def whole(own: np.ndarray, place: np.ndarray, totals: np.ndarray) -> np.ndarray:
    """A chunk's sums by context, with those of crowded contexts over all their chunks in place of its own."""
    return np.where(place >= 0, totals[place], own) if len(totals) else own


class Seats:
    """A chunk's rows of the state and of sums by word: tables now and at earlier samples (past, one after another)."""

    def __init__(self, rows: pa.Table) -> None:
        self.rows, self.part, self.n = rows, rows.column("part").to_pylist(), rows.column("n").to_pylist()
        own = self.part.index(-1)
        self.now, self.past = (unpacked(rows.column(c)[own].as_py(), "<u4").astype(np.int64) for c in "ab")

    def joined(self, column: str, of: int) -> np.ndarray:
        order = sorted((p, i) for i, p in enumerate(self.part) if p >= 0 and self.n[i] == of)
        return np.concatenate([unpacked(self.rows.column(column)[i].as_py(), "<u8") for _, i in order])

    def parents(self, sample: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Customers and tables of the chunk's words in the parent."""
        return self.joined("a", sample).astype(np.int64), self.joined("b", sample).astype(np.int64)

    def known(self) -> np.ndarray:
        """Training tokens of the chunk's words."""
        return self.joined("c", -1)


def scored(docs: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of docs(doc_id, text).

    score and base_score are log10 probabilities under the model and under add-one unigrams. A null or empty
    text is one end token. Rows that repeat an id are scored each, and count each. A row with a null id is learnt from. A text of any length is
    read whole, in pieces. Without any document to learn from every token is unknown. Other columns than doc_id and text are not read.
    An empty table gives an empty result.
    """
    docs = docs.select("doc_id", "text")
    model = Model(docs, chunk)
    for k in range(BURN_IN + SAMPLES):
        model.step(keep=k > BURN_IN)
    n, v = model.tokens, model.up.vocabulary
    answers = materialize(model.answers(), "answers")
    forget(model.state, model.known, model.words, *(x[2] for x in model.samples))

    def total(own: pa.Table, given: pa.Table) -> pa.Table:
        row = own.to_pylist()[0]
        count = int.from_bytes(row["b"][:8], "little")
        ids, null = unpacked(row["b"][:-count], "<i8"), np.frombuffer(row["b"][-count:], "u1")
        lens, times = unpacked(row["c"], "<u4"), unpacked(row["d"], "<u4")
        doc = unpacked(row["e"], "<u2" if len(ids) <= 1 << 16 else "<u4")
        order = np.argsort(given.column("chunk").to_numpy())
        read = lambda name, kind: np.concatenate([unpacked(given.column(name)[i].as_py(), kind(i)) for i in order])
        wide = given.column("wide").to_pylist()
        log_p, known = read("a", lambda i: "<f4").astype(float), read("b", lambda i: "<u8" if wide[i] else "<u4")
        sums = [np.bincount(doc, np.repeat(y, times), len(ids)) for y in (log_p, np.log10((known + 1.0) / (n + v + 1.0)), known > 0)]
        return pa.table({"key": unpacked(row["a"], "<i8"), "doc_id": pa.array(ids, pa.int64(), mask=null > 0), "n_tokens": lens.astype(np.int64), "n_known": sums[2].astype(np.int64), "base_score": sums[1], "score": sums[0]})

    lists = model.chunks.where("chunk = -1").drop("chunk")
    out = lists.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(total, "key long, doc_id long, n_tokens long, n_known long, base_score double, score double")
    # A document cut into pieces has several rows.
    out = out.groupBy("key").agg(F.first("doc_id").alias("doc_id"), *(F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")))
    held = F.coalesce(fold(F.col("doc_id")) % 7 == 2, F.lit(False))
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")


def perplexity(scores: DataFrame) -> DataFrame:
    """held_out, tokens, perplexity, base_perplexity of scored(): ten to the mean of the negative log10 probabilities of tokens."""
    mean = lambda c: F.pow(F.lit(10.0), -F.sum(c) / F.sum("n_tokens"))
    return scores.groupBy("held_out").agg(F.sum("n_tokens").alias("tokens"), mean("score").alias("perplexity"), mean("base_score").alias("base_perplexity"))
