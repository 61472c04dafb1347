"""Transactions stored by item: dense transaction numbers, a dictionary, and bitmap blocks.

Only items that can be frequent are stored. A block holds the bitmaps of all its items over BLOCK consecutive
transaction numbers in one row, so that counting a level is one map pass over blocks with partial sums.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from decimal import ROUND_CEILING, Decimal

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..scratch import written

#: Transactions of a block: the number of bits of Spark's own bitmaps.
BLOCK = 32_768


def min_support(theta: float | str | Decimal, n: int) -> int:
    """ceil(theta * n), exactly, at least 1."""
    return max(1, int((Decimal(str(theta)) * n).to_integral_value(rounding=ROUND_CEILING)))


#: Parts that keys are dealt to by their hash, to be ranked.
PARTS = 512


def dense_tids(long: DataFrame, parts: int | None = None) -> DataFrame:
    """tid (1-based, without gaps) of every key, in key order of hashed parts: ranks within a part plus the sizes
    of the parts before it, so that no task sees all keys."""
    parts = parts or PARTS
    keys = long.select("key").distinct().withColumn("p", F.pmod(F.xxhash64("key"), F.lit(parts)))
    sizes = keys.groupBy("p").agg(F.count(F.lit(1)).alias("s"))
    before = sizes.select("p", (F.sum("s").over(Window.orderBy("p")) - F.col("s")).alias("b"))  # `parts` rows
    rank = F.row_number().over(Window.partitionBy("p").orderBy("key"))
    return keys.withColumn("r", rank).join(F.broadcast(before), "p").select("key", (F.col("b") + F.col("r")).cast("long").alias("tid"))


def dictionary(long: DataFrame, least: int = 1) -> DataFrame:
    """item (0, 1, ... by falling frequency, then label), label, freq of the items with support of at least least."""
    freq = long.groupBy("label").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= least)
    return freq.select((F.row_number().over(Window.orderBy(F.col("freq").desc(), "label")) - 1).cast("int").alias("item"), "label", "freq")


@dataclass
class Store:
    """One database: n transactions, the dictionary of stored items, their long form and their blocks."""

    n: int
    s_min: int
    items: DataFrame
    long: DataFrame
    blocks: DataFrame
    labels: list[str]

    @property
    def spark(self):  # noqa: ANN201
        return self.long.sparkSession


def build(pairs: DataFrame, theta: float | str, universe: int | None = None) -> Store:
    """The store of rows (key, label) at a threshold, or of rows (key, labels). n counts keys with at least one item, or is given."""
    if "labels" in pairs.columns:
        return _build_wide(pairs, theta, universe)
    pairs = written(pairs, "pairs")
    n = universe if universe is not None else pairs.select("key").distinct().count()
    s_min = min_support(theta, n)
    items = written(dictionary(pairs, s_min), "items")
    # At most 1 / theta times the mean transaction length items are frequent: bounded by the threshold, not by n.
    labels = [r[0] for r in items.orderBy("item").select("label").collect()]
    kept = pairs.join(F.broadcast(items.select("label", "item")), "label")
    tids = dense_tids(pairs)
    long = written(kept.join(tids, "key").select("tid", "item"), "long")

    def pack(table: pa.Table) -> pa.Table:
        tid, item = table.column("tid").to_numpy() - 1, table.column("item").to_numpy()
        names, at = np.unique(item, return_inverse=True)
        packed, place = np.zeros((len(names), BLOCK // 8), np.uint8), tid % BLOCK
        np.bitwise_or.at(packed, (at, place >> 3), (1 << (place & 7)).astype(np.uint8))
        return pa.table({"block": pa.array([int(tid[0] // BLOCK)], pa.int64()), "items": pa.array([names.tolist()], pa.list_(pa.int32())), "bits": pa.array([packed.tobytes()], pa.binary())})

    block = long.withColumn("b", F.floor((F.col("tid") - 1) / BLOCK))
    blocks = written(block.groupBy("b").applyInArrow(pack, "block long, items array<int>, bits binary"), "blocks")
    return Store(n, s_min, items, long, blocks, labels)


def _build_wide(rows: DataFrame, theta: float | str, universe: int | None) -> Store:
    """The same store, with the same transaction numbers, of rows (key, labels) without repeated labels: they cross the network once, keys
    are ranked as they are brought together, and tasks set the bits of their own transactions, of which a block has a few parts."""
    spark = rows.sparkSession
    order, key = Window.partitionBy("p").orderBy("key"), F.col("key")
    dealt = rows.withColumn("p", F.pmod(F.xxhash64("key"), F.lit(PARTS))).repartition("p")
    again = F.coalesce(F.lag("key").over(order) == key, F.lit(False)) | F.coalesce(F.lead("key").over(order) == key, F.lit(False))
    ranked = written(dealt.select("p", F.dense_rank().over(order).cast("long").alias("r"), "labels", again.alias("again")), "baskets")
    sizes = dict(ranked.groupBy("p").agg(F.max("r")).collect())  # PARTS rows
    n = universe if universe is not None else sum(sizes.values())
    before, seen = {}, 0
    for part in sorted(sizes):
        before[part], seen = seen, seen + sizes[part]
    s_min = min_support(theta, n)
    first = spark.createDataFrame(list(before.items()), "p long, b long")
    tids = ranked.join(F.broadcast(first), "p").select((F.col("b") + F.col("r")).alias("tid"), "labels", "again")
    each = tids.select("tid", "again", F.explode("labels").alias("label"))
    each = each.where("not again").select("tid", "label").union(each.where("again").select("tid", "label").distinct())
    items = written(dictionary(each, s_min), "items")
    labels = [r[0] for r in items.orderBy("item").select("label").collect()]
    long = each.join(F.broadcast(items.select("label", "item")), "label").select("tid", "item")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, parts = pa.array(labels, pa.string()), {}
        for batch in batches:
            lists = batch.column("labels")
            item = pc.index_in(lists.flatten(), value_set=known)
            at = np.repeat(batch.column("tid").to_numpy() - 1, pc.list_value_length(lists).to_numpy())
            kept = item.is_valid().to_numpy(zero_copy_only=False)
            at, item = at[kept], item.drop_null().to_numpy()
            for block in np.unique(at // BLOCK).tolist():
                if block not in parts:
                    if len(parts) == 4:  # numbers of a part follow one another: what is put out is hardly needed again
                        yield packed_rows([parts.pop(next(iter(parts)))])
                    parts[block] = (block, np.zeros((len(labels), BLOCK // 8), np.uint8))
                own = at // BLOCK == block
                place = at[own] % BLOCK
                np.bitwise_or.at(parts[block][1].reshape(-1), item[own] * np.int64(BLOCK // 8) + (place >> 3), (1 << (place & 7)).astype(np.uint8))
        for part in parts.values():
            yield packed_rows([part])

    def merge(table: pa.Table) -> pa.Table:
        whole = np.zeros((len(labels), BLOCK // 8), np.uint8)
        for names, bits in zip(table.column("items").to_pylist(), table.column("bits").to_pylist()):
            whole[names] |= np.frombuffer(bits, np.uint8).reshape(len(names), -1)
        return pa.Table.from_batches([packed_rows([(table.column("block")[0].as_py(), whole)])])

    schema = "block long, items array<int>, bits binary"
    blocks = written(tids.select("tid", "labels").mapInArrow(pack, schema).groupBy("block").applyInArrow(merge, schema), "blocks")
    return Store(n, s_min, items, long, blocks, labels)


def packed_rows(parts: list[tuple[int, np.ndarray]]) -> pa.RecordBatch:
    """Rows (block, items, bits) of the bitmaps of all items of blocks; items without a transaction are left out."""
    names = [np.nonzero(bits.any(1))[0] for _, bits in parts]
    return pa.RecordBatch.from_arrays(
        [pa.array([b for b, _ in parts], pa.int64()), pa.array([x.tolist() for x in names], pa.list_(pa.int32())), pa.array([bits[x].tobytes() for x, (_, bits) in zip(names, parts)], pa.binary())],
        names=["block", "items", "bits"],
    )


def block_matrix(items: list[int], bits: bytes, m: int) -> np.ndarray:
    """The packed bitmaps of all m items of a block; rows of absent items are zero."""
    out = np.zeros((m, BLOCK // 8), np.uint8)
    out[items] = np.frombuffer(bits, np.uint8).reshape(len(items), BLOCK // 8)
    return out


def bitmaps(long: DataFrame) -> DataFrame:
    """item, bucket, bits: the same store in Spark's own bitmap encoding."""
    return long.groupBy("item", F.bitmap_bucket_number("tid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("tid")).alias("bits"))


def baskets(long: DataFrame) -> DataFrame:
    """tid, items: the horizontal form."""
    return long.groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))
