"""N-gram Jaccard join: a grouped prefix join on word shingles.

Documents with the same shingles form a class, classes with the same prefix and size form a group, and groups
meet on the shingles of their prefixes. Shingles are ordered with the frequent ones last, the others by how common
their words are, so that texts which share nothing but common words in chance order hardly meet, however many there are;
any order gives the same links, a good one only makes buckets small. Prefixes are some shingles longer than they must be, so that a
similar pair shares not one but that many more of them; a group may then leave crowded buckets as long as fewer
of its shingles are crowded than a pair must share. Candidates are tried in two steps: first each against the
smallest of its bucket, then, across the components this leaves, all that remain. Pairs inside one component
need no test, so no bucket is expanded into all its pairs, and no link between components is lost. What must stay
in crowded buckets is compared in tiles, by matrix products of their whole sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, forget, materialize, trimmed

SHINGLE, PERCENT = 5, 75
#: Frequent shingles that the order knows of at most, and how many documents make one frequent.
FREQUENT, MANY = 400_000, 12
#: log2 of the cells in which words are counted for the order, and rows in which a task hands its counts on.
CELL_BITS, CELL_ROWS = 17, 16
#: Shingles beyond the least prefix that a pair must share too, and groups that make a bucket crowded.
EXTRA, CROWD = 24, 24
#: Documents of a tile, in which dense clusters are compared pair by pair.
TILE = 512
#: Shingles that a task gathers before it counts or deals them: bounds memory.
GATHER = 1_500_000
#: log2 of the bits of the filter that skips documents without candidates; a full one skips none.
FILTER_BITS = 26
LOWERED = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


class Hashes(dict):
    """64-bit hashes of words, computed once each while remembered."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) > 200_000:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


def mixed(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    h = (h ^ np.uint64(salt)) * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(32))


def words_of(text: bytes | None, known: Hashes) -> np.ndarray:
    """Hashes of a text's words in order. A-Z count as a-z; words end at ASCII white space."""
    words = (text or b"").translate(LOWERED).split()
    return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def joined(h: np.ndarray, size: int) -> np.ndarray:
    """48-bit hashes of the shingles of words, in order and with repeats. Fewer words than size make one shingle of all
    of them; no words make none."""
    if not len(h):
        return h
    n = min(size, len(h))
    out = h[: len(h) - n + 1].copy()
    for i in range(1, n):
        out *= np.uint64(0x9E3779B97F4A7C15)
        out += h[i : len(h) - n + 1 + i]
    return mixed(out, n) >> np.uint64(16)


def shingles(text: bytes | None, known: Hashes, size: int = SHINGLE) -> np.ndarray:
    """The distinct shingles of a text as sorted 48-bit hashes."""
    return np.unique(joined(words_of(text, known), size))


def cells(h: np.ndarray) -> np.ndarray:
    """The cells in which words are counted."""
    return (h >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def weights_of(counts: np.ndarray) -> np.ndarray:
    """What a word of each cell adds to its shingles' weight: a rounded logarithm, so that sums are the same everywhere."""
    return np.round(16 * np.log2(1.0 + counts)).astype(np.uint64)


def weighed(text: bytes | None, known: Hashes, weight: np.ndarray, size: int = SHINGLE) -> np.ndarray:
    """The distinct shingles of a text, those of rarer words first. A shingle's weight follows from its words alone, so
    every text orders it alike."""
    h = words_of(text, known)
    out = joined(h, size)
    if not len(h):
        return out
    each, n = weight[cells(h)], min(size, len(h))
    total = each[: len(h) - n + 1].copy()
    for i in range(1, n):
        total += each[i : len(h) - n + 1 + i]
    # 16 bits are enough for weights of five words; longer shingles are weighed more coarsely.
    coarse = max(0, int(n * int(weight.max(initial=0))).bit_length() - 16)
    return np.unique(total >> np.uint64(coarse) << np.uint64(48) | out) & np.uint64(0xFFFFFFFFFFFF)


def packed(h: np.ndarray) -> bytes:
    """48-bit numbers in 6 bytes each."""
    return h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def unpacked(data: bytes) -> np.ndarray:
    wide = np.zeros((len(data) // 6, 8), np.uint8)
    wide[:, :6] = np.frombuffer(data, np.uint8).reshape(-1, 6)
    return wide.view("<u8").reshape(-1)


def share_of(n: int) -> int:
    """How many shingles of its prefix a set of n must share with a similar set that asks for no fewer."""
    return max(1, min(EXTRA, n // 12))


def prefix_length(n: int, percent: int = PERCENT) -> int:
    """Shingles of a set of n of which any set that is similar enough has at least share_of(n) in its own, in any
    order, or as many as the other set asks for if these are fewer."""
    return n - (percent * n + 99) // 100 + share_of(n)


def binary_texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("text"))


def frequent(docs: DataFrame, size: int, most: int = FREQUENT, many: int = MANY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The most frequent shingles and their counts, sorted by shingle: at most `most`, from all documents; and the weights
    of words by cell.

    Each task counts documents and reports what it has met at least twice, and the words it has met by cell.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, waiting, n = Hashes(), [], 0
        met = np.zeros(1 << CELL_BITS, np.int64)

        def given() -> pa.RecordBatch:
            h = np.sort(np.concatenate(waiting)) if waiting else np.zeros(0, np.uint64)
            starts = np.nonzero(np.concatenate([[True], h[1:] != h[:-1]]))[0] if len(h) else np.zeros(0, np.int64)
            counts = np.diff([*starts, len(h)]) if len(h) else starts
            twice = counts > 1
            return batch_of(h[starts[twice]].astype(np.int64), counts[twice].astype(np.int64), [None] * int(twice.sum()))

        def batch_of(h: np.ndarray, n: np.ndarray, words: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(n, pa.int64()), pa.array(words, pa.binary())], names=["h", "n", "words"])

        for batch in batches:
            for text in batch.column(1).to_pylist():
                words = words_of(text, known)
                np.add.at(met, cells(words), 1)
                waiting.append(np.unique(joined(words, size)))
                n += len(waiting[-1])
                if n > GATHER:
                    yield given()
                    waiting, n = [], 0
        yield given()
        yield batch_of(np.arange(CELL_ROWS), np.zeros(CELL_ROWS), [x.astype("<i8").tobytes() for x in np.split(met, CELL_ROWS)])

    def add(table: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, "<i8") for x in table.column("words").to_pylist())
        return pa.table({"h": table.column("h")[:1], "words": pa.array([total.tobytes()], pa.binary())})

    reported = materialize(binary_texts(docs).mapInArrow(trimmed(count), "h long, n long, words binary"), "counts")
    counted = reported.where("words is null").groupBy("h").agg(F.sum("n").alias("n"))
    top = counted.where(F.col("n") >= many).orderBy(F.col("n").desc(), "h").limit(most).toArrow()  # at most `most` rows
    words = reported.where("words is not null").select("h", "words").groupBy("h").applyInArrow(add, "h long, words binary").collect()  # CELL_ROWS rows
    forget(reported)
    h, n = top.column("h").to_numpy().astype(np.uint64), top.column("n").to_numpy()
    order = np.argsort(h)
    met = np.concatenate([np.frombuffer(r["words"], "<i8") for r in sorted(words, key=lambda r: r["h"])] or [np.zeros(1 << CELL_BITS, np.int64)])
    return h[order], n[order], weights_of(met)


def ordered(h: np.ndarray, often: tuple[np.ndarray, ...]) -> np.ndarray:
    """Shingles in the join's order: those not known as frequent as they come, then the others by count and hash."""
    if not len(often[0]):
        return h
    at = np.minimum(np.searchsorted(often[0], h), len(often[0]) - 1)
    hit = often[0][at] == h
    if not hit.any():
        return h
    late = at[hit]
    return np.concatenate([h[~hit], often[0][late[np.lexsort((late, often[1][late]))]]])


def print_of(h: np.ndarray) -> tuple[int, int]:
    """A 128-bit fingerprint of a set."""
    return tuple(int(mixed(h, salt).sum(dtype=np.uint64).astype(np.int64)) for salt in (0x5851F42D4C957F2D, 0x14057B7EF767814F))


def described(docs: DataFrame, often: tuple[np.ndarray, np.ndarray, np.ndarray], size: int, percent: int) -> DataFrame:
    """doc_id, n, fingerprints of set and prefix, and the prefix in order, of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(often)  # at most FREQUENT entries, and the cells

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Hashes()
        for batch in batches:
            rows = []
            for text in batch.column(1).to_pylist():
                h = weighed(text, known, shared.value[2], size)
                front = ordered(h, shared.value)[: prefix_length(len(h), percent)] if len(h) else h
                rows.append((len(h), *print_of(h), print_of(front)[0], packed(front)))
            cols = list(zip(*rows)) or [()] * 5
            kinds = [pa.int64()] * 4 + [pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=["doc_id", "n", "f1", "f2", "g1", "prefix"])

    return binary_texts(docs).mapInArrow(trimmed(run), "doc_id long, n long, f1 long, f2 long, g1 long, prefix binary")


def meetings(groups: DataFrame, parts: int) -> DataFrame:
    """h, grp, n, crowd: the prefix shingles that two or more groups(grp, n, prefix) share, these groups, and whether (1 or 0)
    they are more than CROWD.

    Prefixes are dealt by shingle range as packed arrays; shingles of one group alone end here.
    """

    crowd = CROWD

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hs, who, ids, ns, n = [], [], [], [], 0

        def given() -> pa.RecordBatch:
            h = np.concatenate(hs) if hs else np.zeros(0, np.uint64)
            owner = np.repeat(np.arange(len(ids), dtype=np.uint32), who)
            order = np.argsort(h, kind="stable")
            h, owner = h[order], owner[order]
            part = ((h >> np.uint64(16)) * np.uint64(parts)) >> np.uint64(32)
            edges = np.searchsorted(part, np.arange(parts + 1))
            rows = []
            for p in range(parts):
                a, b = edges[p], edges[p + 1]
                if a < b:
                    own, local = np.unique(owner[a:b], return_inverse=True)
                    rows.append((p, packed(h[a:b]), local.astype("<u4").tobytes(), np.array(ids, "<i8")[own].tobytes(), np.array(ns, "<i8")[own].tobytes()))
            cols = list(zip(*rows)) or [()] * 5
            return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["part", "hs", "who", "ids", "ns"])

        for batch in batches:
            for grp, size, prefix in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                hs.append(unpacked(prefix))
                who.append(len(hs[-1]))
                ids.append(grp)
                ns.append(size)
                n += len(hs[-1])
                if n > GATHER:
                    yield given()
                    hs, who, ids, ns, n = [], [], [], [], 0
        yield given()

    def meet(table: pa.Table) -> pa.Table:
        col = lambda name: table.column(name).to_pylist()
        h = np.concatenate([unpacked(x) for x in col("hs")])
        grp, size = [], []
        for who, ids, ns in zip(col("who"), col("ids"), col("ns")):
            at = np.frombuffer(who, "<u4")
            grp.append(np.frombuffer(ids, "<i8")[at])
            size.append(np.frombuffer(ns, "<i8")[at])
        order = np.argsort(h, kind="stable")
        h, grp, size = h[order], np.concatenate(grp)[order], np.concatenate(size)[order]
        starts = np.nonzero(np.concatenate([[True], h[1:] != h[:-1]]))[0] if len(h) else np.zeros(0, np.int64)
        k = np.diff(np.append(starts, len(h)))
        k = np.repeat(k, k)
        live = k > 1
        return pa.table({"h": pa.array(h[live].astype(np.int64)), "grp": pa.array(grp[live]), "n": pa.array(size[live]), "crowd": pa.array((k[live] > crowd).astype(np.int32))})

    dealt = groups.select("grp", "n", "prefix").mapInArrow(trimmed(deal), "part int, hs binary, who binary, ids binary, ns binary")
    return dealt.groupBy("part").applyInArrow(meet, "h long, grp long, n long, crowd int")


def id_filter(ids: DataFrame, bits: int = FILTER_BITS) -> bytes:
    """A bit for the hash of each id of ids(id): a fixed size, whatever their number."""
    at = F.pmod(F.xxhash64("id"), F.lit(1 << bits)) + 1
    rows = ids.select(at.alias("at")).groupBy(F.bitmap_bucket_number("at").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("at")).alias("m")).collect()  # at most 2^bits / 32768
    out = bytearray((1 << bits) // 8)
    for r in rows:
        out[(r["b"] - 1) * 4096 : (r["b"] - 1) * 4096 + 4096] = r["m"]
    return bytes(out)


def sets_of(ids: DataFrame, docs: DataFrame, size: int) -> DataFrame:
    """id, shingles (packed) of the documents of ids(id), as a written table. Others are skipped unread by a filter."""
    shared = docs.sparkSession.sparkContext.broadcast(id_filter(ids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, bits = Hashes(), np.frombuffer(shared.value, np.uint8)
        for batch in batches:
            at = batch.column(2).to_numpy()
            some = batch.take(pa.array(np.nonzero(bits[at >> 3] >> (at & 7).astype(np.uint8) & 1)[0]))
            blobs = [packed(shingles(t, known, size)) for t in some.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([some.column(0), pa.array(blobs, pa.binary())], names=["id", "shingles"])

    d = binary_texts(docs).where("doc_id is not null").select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(1 << FILTER_BITS)).alias("at"))
    return materialize(d.mapInArrow(trimmed(run), "id long, shingles binary").join(ids, "id", "left_semi").dropDuplicates(["id"]), "sets")


def verified(pairs: DataFrame, docs: DataFrame, size: int, percent: int) -> DataFrame:
    """Those of pairs(a, b) whose documents' whole shingle sets are similar enough, as a written table."""
    pairs = materialize(pairs, "pairs")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                both = np.concatenate([unpacked(x), unpacked(y)])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                good.append(100 * common >= percent * (len(both) - common) and len(both) > 0)
            yield pa.RecordBatch.from_arrays(batch.columns[:2], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    known = sets_of(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), docs, size)
    both = pairs.join(known.select(F.col("id").alias("a"), F.col("shingles").alias("x")), "a").join(known.select(F.col("id").alias("b"), F.col("shingles").alias("y")), "b")
    links = materialize(both.select("a", "b", "x", "y").mapInArrow(trimmed(compare), "a long, b long"), "links")
    forget(pairs, known)
    return links


def tile_links(units: DataFrame, docs: DataFrame, size: int, percent: int) -> DataFrame:
    """Links a, b between the components of units(unit, cluster, comp) of one cluster: all pairs are compared on whole
    sets, tile by tile, and of the links of two tiles those are returned that join components."""
    sizes = units.groupBy("cluster").agg(F.ceil(F.count(F.lit(1)) / TILE).cast("int").alias("tiles"))
    placed = materialize(units.join(sizes, "cluster").withColumn("tile", F.pmod(F.xxhash64("unit"), F.col("tiles")).cast("int")), "tiles")
    known = sets_of(placed.select(F.col("unit").alias("id")).distinct(), docs, size)
    full = placed.join(known, placed["unit"] == known["id"]).select("cluster", "unit", "comp", "tile", "tiles", "shingles")
    full = full.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    full = full.select("cluster", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"), "unit", "comp", "tile", "shingles")

    def compare(table: pa.Table) -> pa.Table:
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        unit, tile = table.column("unit").to_numpy(), table.column("tile").to_numpy()
        sets = [unpacked(x) for x in table.column("shingles").to_pylist()]
        n = np.array([len(x) for x in sets])
        h, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), n)
        order = np.argsort(h, kind="stable")
        h, owner = h[order], owner[order]
        new = np.concatenate([[True], h[1:] != h[:-1]])
        column = np.cumsum(new) - 1
        shared = np.bincount(column) > 1  # the others are in one set alone
        column, owner = (np.cumsum(shared) - 1)[column[shared[column]]], owner[shared[column]]
        a, b = np.nonzero(tile == i)[0], np.nonzero(tile == j)[0]
        common, wide = np.zeros((len(a), len(b)), np.float32), 8192
        for lo in range(0, int(column.max(initial=-1)) + 1, wide):
            here = (column >= lo) & (column < lo + wide)
            m = np.zeros((len(sets), wide), np.float32)
            m[owner[here], column[here] - lo] = 1
            common += m[a] @ m[b].T
        common = common.astype(np.int64)
        close = 100 * common >= percent * (n[a][:, None] + n[b][None, :] - common)
        root = {c: c for c in table.column("comp").to_pylist()}

        def top(c: int) -> int:
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        comp, out = table.column("comp").to_pylist(), []
        for p, q in zip(*np.nonzero(close & (unit[a][:, None] != unit[b][None, :]))):
            x, y = top(comp[a[p]]), top(comp[b[q]])
            if x != y:
                root[max(x, y)] = min(x, y)
                out.append((unit[a[p]], unit[b[q]]))
        return pa.table({"a": pa.array([x[0] for x in out], pa.int64()), "b": pa.array([x[1] for x in out], pa.int64())})

    links = materialize(full.groupBy("cluster", "i", "j").applyInArrow(compare, "a long, b long"), "links")
    forget(placed, known)
    return links


def near_duplicates(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT, frequent_most: int = FREQUENT, many: int = MANY) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of docs(doc_id, text).

    Two documents link when 100 * common >= percent * all of their distinct shingles; component_id is the
    smallest doc_id reachable by links, itself included. Null and empty texts have no shingles and link with
    nothing; rows that repeat an id count as one document; a null id gets its class's component. Shingles are
    compared by 48 bits of a hash, sets by 128. An empty table gives an empty result.
    """
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    info = materialize(described(docs, frequent(docs, size, frequent_most, many), size, percent), "described")
    some = info.where("n > 0")
    unit = some.groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("unit"), F.min("g1").alias("g1")).where("unit is not null")
    unit = materialize(unit.select("f1", "f2", "n", "g1", "unit"), "classes")
    grp = unit.groupBy("g1", "n").agg(F.min("unit").alias("grp"))
    member = materialize(unit.join(grp, ["g1", "n"]).select("unit", "n", "grp"), "members")
    heads = member.where("unit = grp").select("grp", "n")
    fronts = info.select(F.col("doc_id").alias("grp"), "n", "prefix").join(heads.select("grp"), "grp", "left_semi")
    met = materialize(meetings(fronts, max(8, parts)), "meetings")
    whole, info = info, materialize(info.select("doc_id", "n", "f1", "f2"), "names")
    forget(whole)  # prefixes are the larger part of it
    # Groups with few crowded shingles leave the crowded buckets; what a pair must share falls by as many.
    asks = F.greatest(F.lit(1), F.least(F.lit(EXTRA), F.floor(F.col("n") / 12))).cast("long")
    # A partner may be smaller and ask for less: the least that any can ask for decides.
    least = F.greatest(F.lit(1), F.least(F.lit(EXTRA), F.floor(F.col("n") * percent / 1200))).cast("long")
    held = met.where("crowd = 1").groupBy("grp").agg(F.count(F.lit(1)).alias("d"), F.max(least).alias("least"))
    held = held.select("grp", "d", (F.col("d") >= F.col("least")).alias("stays"))  # groups without crowded shingles leave none
    left = F.when(F.coalesce("stays", F.lit(False)), F.lit(None)).otherwise(F.coalesce("d", F.lit(0))).cast("long").alias("left")
    rows = met.join(held, "grp", "left").where("crowd = 0 OR stays").select("h", "grp", "n", "crowd", asks.alias("asks"), left)
    rows = materialize(rows, "live")
    forget(met)
    live, thick = rows.where("crowd = 0").drop("crowd"), rows.where("crowd = 1").select("h", "grp")
    need = F.least("asksx", "asksy") - F.coalesce(F.least("leftx", "lefty"), F.lit(0))  # nulls are passed over
    small = f"100 * nx >= {percent} * ny AND 100 * ny >= {percent} * nx"
    # First, everyone against the smallest of its group, and every group against the smallest of its bucket.
    first = live.groupBy("h").agg(F.min(F.struct("grp", "n", "asks", "left")).alias("s"))
    first = first.select("h", F.col("s.grp").alias("a"), F.col("s.n").alias("nx"), F.col("s.asks").alias("asksx"), F.col("s.left").alias("leftx"))
    other = live.select("h", F.col("grp").alias("b"), F.col("n").alias("ny"), F.col("asks").alias("asksy"), F.col("left").alias("lefty"))
    stars = other.join(first, "h").where("a <> b").where(small).groupBy("a", "b").agg(F.count(F.lit(1)).alias("k"), F.first(need).alias("need")).where("k >= need").select("a", "b")
    within = member.where("unit <> grp").select(F.col("grp").alias("a"), F.col("unit").alias("b"))
    tried = materialize(stars.union(within).distinct(), "tried")
    linked = verified(tried, docs, size, percent)
    comp = components(linked)
    # Then, across the components of each bucket, what is left; buckets have at most CROWD groups.
    placed = materialize(member.join(comp, member["unit"] == comp["node"], "left").select("unit", "n", "grp", F.coalesce("component", "unit").alias("comp")), "placed")
    spread = placed.groupBy("grp").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("units"))
    open_h = live.join(spread, "grp").groupBy("h").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).where("lo <> hi").select("h")
    many = spread.where(f"lo <> hi AND units > {CROWD}").select("grp")
    alone = placed.join(spread.where(f"lo <> hi AND units <= {CROWD}").select("grp"), "grp", "left_semi")
    meet = live.select("h", "grp", "asks", "left").join(open_h, "h", "left_semi").join(placed, "grp").select("h", "unit", "n", "comp", "asks", "left")
    own = alone.select((-F.col("grp") - 1).alias("h"), "unit", "n", "comp", F.lit(1).cast("long").alias("asks"), F.lit(None).cast("long").alias("left"))
    meet = materialize(meet.union(own), "open")
    x, y = (meet.select("h", *(F.col(c).alias(c + s) for c in ("unit", "n", "comp", "asks", "left"))) for s in "xy")
    cross = x.join(y, "h").where("compx < compy").where(small)
    cross = cross.select(F.least("unitx", "unity").alias("a"), F.greatest("unitx", "unity").alias("b"), need.alias("need"), (F.col("h") < 0).alias("own"))
    cross = cross.groupBy("a", "b").agg(F.count(F.lit(1)).alias("k"), F.max("need").alias("need"), F.max("own").alias("own")).where("own OR k >= need").select("a", "b")
    done = tried.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    more = verified(cross.join(done, ["a", "b"], "left_anti"), docs, size, percent)
    forget(tried, meet)
    # Last, groups that had to stay in crowded buckets, and the many units of one group: in tiles.
    ring = thick.join(thick.groupBy("h").agg(F.min("grp").alias("b")), "h").select(F.col("grp").alias("a"), "b").distinct()
    cluster = components(ring).select(F.col("node").alias("grp"), F.col("component").alias("cluster"))
    dense = placed.join(cluster, "grp").select("unit", "cluster", "comp")
    dense = dense.union(placed.join(many, "grp").select("unit", (-F.col("grp") - 1).alias("cluster"), "comp"))
    tiles = tile_links(dense, docs, size, percent)
    forget(rows, placed, member)
    final = components(linked.union(more).union(tiles))
    forget(linked, more, tiles)
    named = unit.join(final, unit["unit"] == final["node"], "left").select("f1", "f2", "n", F.coalesce("component", "unit").alias("component_id"))
    full = info.select("doc_id", "n", "f1", "f2").join(named, ["f1", "f2", "n"], "left")
    return full.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
