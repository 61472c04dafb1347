"""Pairs of frequent itemsets worth combining: exact joins, pruning, and hashed joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..families import Family, MinWise
from ..scratch import written
from .meetings import by_group, meetings
from .support import AT_ONCE, conjunction
from .vertical import Store, block_matrix


def union_of(a: Column, b: Column) -> Column:
    return F.array_sort(F.array_union(a, b))


def leave_one_out(items: Column) -> Column:
    """The subsets with one item less."""
    return F.transform(items, lambda x: F.array_remove(items, x))


def join_compatible(level: DataFrame, how: str = "subset_key") -> DataFrame:
    """items, parent_a, parent_q for every unordered pair of itemsets whose union has one item more.

    subset_key: two itemsets of l items are compatible iff they share exactly one subset of l - 1 items, so an
    equi-join on these finds each pair once; prefix: only pairs that agree in all but their last item; brute:
    all pairs, filtered.
    """
    rows = level.select("items")
    if how == "prefix":
        keyed = rows.withColumn("key", F.expr("slice(items, 1, size(items) - 1)"))
    elif how == "subset_key":
        keyed = rows.withColumn("key", F.explode(leave_one_out(F.col("items"))))
    elif how == "brute":
        keyed = rows
    else:
        raise ValueError(how)
    a, q = (keyed.withColumnRenamed("items", f"parent_{s}") for s in "aq")
    met = a.crossJoin(q) if how == "brute" else a.join(q, "key")
    met = met.where(F.col("parent_a") < F.col("parent_q"))
    if how == "brute":
        met = met.where(F.size(F.array_union("parent_a", "parent_q")) == F.size("parent_a") + 1)
    return met.select(union_of(F.col("parent_a"), F.col("parent_q")).alias("items"), "parent_a", "parent_q")


def prune_by_subsets(candidates: DataFrame, level: DataFrame) -> DataFrame:
    """Distinct candidates all of whose subsets with one item less are frequent."""
    each = candidates.select("items").distinct()
    subs = each.select("items", F.explode(leave_one_out(F.col("items"))).alias("sub"))
    held = subs.join(level.select(F.col("items").alias("sub")), "sub", "left_semi")
    return held.groupBy("items").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") == F.size("items")).select("items")


def hashed(members: np.ndarray, supports: np.ndarray, store: Store, family: Family, sides: tuple[str, ...] = ("stored", "query")) -> DataFrame:
    """iid, side, keys (packed 64-bit numbers, one a table, band or slot) of every itemset of a level.

    Blocks contribute in parallel; each task joins its own blocks' parts before the shuffle. Itemsets go in
    pieces, so that no row and no task holds a level's signatures.
    """
    spark, items = store.spark, len(store.labels)
    piece = max(1, min(AT_ONCE, (1 << 22) // max(1, family.empty(1).shape[1])))
    shared = spark.sparkContext.broadcast((members, supports, family))

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, _, fam = shared.value
        whole: dict[int, np.ndarray] = {}
        for batch in batches:
            for block, names, bits in zip(*(c.to_pylist() for c in batch.columns)):
                matrix = fam.view(block_matrix(names, bits, items), block)
                for lo in range(0, len(x), piece):
                    own = fam.partial_of(conjunction(matrix, x[lo : lo + piece]), block)
                    whole[lo] = fam.combine(whole[lo], own) if lo in whole else own
        for lo, a in whole.items():
            yield pa.RecordBatch.from_arrays([pa.array([lo], pa.int64()), pa.array([a.tobytes()], pa.binary())], names=["lo", "part"])

    def finish(table: pa.Table) -> pa.Table:
        x, s, fam = shared.value
        lo, whole = table.column("lo")[0].as_py(), None
        some = s[lo : lo + piece]
        for data in table.column("part").to_pylist():
            a = np.frombuffer(data, np.uint64).reshape(len(some), -1)
            whole = a if whole is None else fam.combine(whole, a)
        out = []
        for side in sides:
            keys = fam.finish(whole, some, side)
            if isinstance(fam, MinWise) and fam.bands:
                out.append((side, fam.band_keys(keys), keys))
            else:
                out.append((side, keys, keys))
        rows = [(lo + i, side, np.ascontiguousarray(k[i]).tobytes(), np.ascontiguousarray(full[i]).tobytes()) for side, k, full in out for i in range(len(some))]
        cols = list(zip(*rows))
        return pa.table({"iid": pa.array(cols[0], pa.int64()), "side": pa.array(cols[1]), "keys": pa.array(cols[2], pa.binary()), "slots": pa.array(cols[3], pa.binary())})

    read = store.blocks.select("block", "items", "bits")
    if family.blocks():
        read = read.where(F.col("block").isin(family.blocks()))
    parts = read.mapInArrow(part, "lo long, part binary")
    return parts.groupBy("lo").applyInArrow(finish, "iid long, side string, keys binary, slots binary")


def spread(signatures: DataFrame) -> DataFrame:
    """iid, side, table_no, key: one row a table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for iid, side, keys in zip(*(c.to_pylist() for c in batch.columns)):
                k = np.frombuffer(keys, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), iid)), pa.array([side] * len(k), pa.string()), pa.array(np.arange(len(k), dtype=np.int32)), pa.array(k)], names=["iid", "side", "table_no", "key"])

    return signatures.select("iid", "side", "keys").mapInArrow(run, "iid long, side string, table_no int, key long")


def same_keys(keys: DataFrame) -> DataFrame:
    """a, q, table_no: stored and query itemsets that agree in a key, and the first table where they do."""
    a = keys.where("side = 'stored'").select(F.col("iid").alias("a"), "table_no", "key")
    q = keys.where("side = 'query'").select(F.col("iid").alias("q"), "table_no", "key")
    return a.join(q, ["table_no", "key"]).where("a <> q").groupBy("a", "q").agg(F.min("table_no").alias("table_no"))


def join_hashed(members: np.ndarray, supports: np.ndarray, store: Store, family: Family, directions: bool = False) -> DataFrame:
    """items, parent_a, parent_q of the compatible pairs that meet in some table, or whose summaries agree enough.

    A pair counts if it meets in either direction. With directions, every meeting is a row instead: with the
    query's parent_q, the stored parent_a, and table_no. Where a level's covering keys are too many for a task, pairs are found
    by groups of positions, without a table of keys.
    """
    spark = store.spark
    names = spark.createDataFrame(pa.table({"iid": pa.array(np.arange(len(members))), "set": pa.array(members.tolist(), pa.list_(pa.int32()))}))
    size = members.shape[1]
    banded = isinstance(family, MinWise) and family.bands
    grouped = by_group(len(members), family)
    sig = None if grouped else written(hashed(members, supports, store, family), "signatures")
    if isinstance(family, MinWise) and not banded:
        pairs = join_compatible(names.select(F.col("set").alias("items")))
        ids = pairs.join(names.select(F.col("set").alias("parent_a"), F.col("iid").alias("a")), "parent_a").join(names.select(F.col("set").alias("parent_q"), F.col("iid").alias("q")), "parent_q")
        both = ids.select("items", "parent_a", "parent_q", "a", "q").unionByName(ids.select("items", F.col("parent_q").alias("parent_a"), F.col("parent_a").alias("parent_q"), F.col("q").alias("a"), F.col("a").alias("q")))
        good = agreeing(both, sig, family).withColumn("table_no", F.lit(0))
    else:
        met = meetings(members, supports, store, family, directions) if grouped else same_keys(spread(sig))
        named = met.join(names.select(F.col("iid").alias("a"), F.col("set").alias("parent_a")), "a").join(names.select(F.col("iid").alias("q"), F.col("set").alias("parent_q")), "q")
        good = named.withColumn("items", union_of(F.col("parent_a"), F.col("parent_q"))).where(F.size("items") == size + 1)
        if banded:
            good = agreeing(good, sig, family)
    if directions:
        return good.select("items", "parent_a", "parent_q", "table_no")
    return good.select("items", F.least("parent_a", "parent_q").alias("parent_a"), F.greatest("parent_a", "parent_q").alias("parent_q")).distinct()


def agreeing(pairs: DataFrame, signatures: DataFrame, family: MinWise) -> DataFrame:
    """Those of pairs(.., a, q) whose estimated similarity, the share of agreeing slots, reaches the limit."""
    limit = family.p["accept"]
    x = signatures.where("side = 'stored'").select(F.col("iid").alias("a"), F.col("slots").alias("x"))
    y = signatures.where("side = 'query'").select(F.col("iid").alias("q"), F.col("slots").alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            xs, ys = batch.column("x").to_pylist(), batch.column("y").to_pylist()
            share = [float((np.frombuffer(p, np.uint64) == np.frombuffer(r, np.uint64)).mean()) for p, r in zip(xs, ys)]
            yield batch.drop_columns(["x", "y"]).append_column("estimate", pa.array(share, pa.float64()))

    schema = ", ".join(f"`{n}` {t}" for n, t in pairs.dtypes) + ", estimate double"
    order = [n for n, _ in pairs.dtypes]
    joined = pairs.join(x, "a").join(y, "q").select(*order, "x", "y")
    return joined.mapInArrow(run, schema).where(F.col("estimate") >= limit - 1e-12)


def stop_early(meetings: DataFrame, similar: DataFrame, tries: int) -> DataFrame:
    """Of meetings(items, parent_a, parent_q, table_no), those a query tries: it gives up after `tries` tries if none
    of them was similar. similar: items of the candidates that are frequent. Order: table, then a hash."""
    flagged = meetings.join(similar.select("items").withColumn("hit", F.lit(1)), "items", "left")
    order = Window.partitionBy("parent_q").orderBy("table_no", F.xxhash64("parent_a"), "parent_a")
    earlier = F.coalesce(F.max("hit").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = flagged.withColumn("rn", F.row_number().over(order)).withColumn("earlier", earlier)
    return ranked.where((F.col("rn") <= tries) | (F.col("earlier") == 1)).drop("hit", "rn", "earlier")


def neighbours(pairs: DataFrame, itemset: list[int], frequent: DataFrame | None = None) -> DataFrame:
    """The partners of one itemset among pairs(parent_a, parent_q): with frequent(items), those whose union with it is frequent."""
    pairs = pairs if frequent is None else pairs.join(frequent.select("items"), "items", "left_semi")
    me = F.array(*[F.lit(i).cast("int") for i in sorted(itemset)])
    return pairs.where((F.col("parent_a") == me) | (F.col("parent_q") == me)).select(F.when(F.col("parent_a") == me, F.col("parent_q")).otherwise(F.col("parent_a")).alias("partner"), "items")
