"""Support counting: level 1 by aggregation, later levels by one of four plans."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vertical import BLOCK, Store, baskets, bitmaps, block_matrix

#: Candidates of one level that are sent to every task at most; beyond, the distributed bitmap plan counts them.
BROADCAST_CANDIDATES = 400_000
#: Candidates that a task ANDs at once: bounds its memory.
AT_ONCE = 1024


def frequent_items(pairs: DataFrame, least: int) -> DataFrame:
    """label, support of the labels in at least least transactions of distinct rows (key, label)."""
    return pairs.groupBy("label").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)


def conjunction(matrix: np.ndarray, members: np.ndarray) -> np.ndarray:
    """Bitmaps of itemsets, (k, bytes), from those of items and (k, l) item numbers."""
    out = matrix[members[:, 0]]
    for j in range(1, members.shape[1]):
        out &= matrix[members[:, j]]
    return out


def _kernel(members: np.ndarray, store: Store) -> DataFrame:
    spark, m = store.spark, len(store.labels)
    shared = spark.sparkContext.broadcast(members)  # at most BROADCAST_CANDIDATES rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, total = shared.value, np.zeros(len(shared.value), np.int64)
        for batch in batches:
            for items, bits in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                matrix = block_matrix(items, bits, m)
                for lo in range(0, len(x), AT_ONCE):
                    both = conjunction(matrix, x[lo : lo + AT_ONCE]).view(np.uint64)
                    total[lo : lo + AT_ONCE] += np.bitwise_count(both).sum(1, dtype=np.int64)
        at = np.nonzero(total)[0]
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["cid", "support"])

    counted = store.blocks.select("items", "bits").mapInArrow(run, "cid long, support long").groupBy("cid").agg(F.sum("support").alias("support"))
    names = spark.createDataFrame(pa.table({"cid": pa.array(np.arange(len(members))), "items": pa.array(members.tolist(), pa.list_(pa.int32()))}))
    return names.join(counted, "cid", "left").select("items", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def count(candidates: DataFrame, store: Store, mode: str = "kernel", bound: int = BROADCAST_CANDIDATES) -> DataFrame:
    """items, support of every distinct candidate, those in no transaction with 0.

    kernel: candidates go to the blocks, which AND and count; bitmap: Spark's bitmap functions after an equi-join;
    tidlist: intersection of lists, for small n; horizontal: containment in baskets that hold the first item.
    """
    each = candidates.select("items").distinct()
    if mode == "kernel":
        rows = each.limit(bound + 1).collect()
        if not rows:
            return each.withColumn("support", F.lit(0).cast("long"))
        if len(rows) <= bound and len({len(r[0]) for r in rows}) == 1:
            return _kernel(np.array(sorted(r[0] for r in rows), np.int32), store)
        mode = "bitmap"
    members = each.select("items", F.explode("items").alias("item"))
    if mode == "bitmap":
        met = members.join(bitmaps(store.long), "item").groupBy("items", "bucket").agg(F.bitmap_and_agg("bits").alias("bits"), F.count(F.lit(1)).alias("k"))
        found = met.where(F.col("k") == F.size("items")).groupBy("items").agg(F.sum(F.bitmap_count("bits")).alias("support"))
    elif mode == "tidlist":
        lists = store.long.groupBy("item").agg(F.collect_list("tid").alias("tids"))
        both = members.join(lists, "item").groupBy("items").agg(F.collect_list("tids").alias("lists"))
        common = F.aggregate(F.slice("lists", 2, 1_000), F.col("lists")[0], lambda acc, x: F.array_intersect(acc, x))
        found = both.where(F.size("lists") == F.size("items")).select("items", F.size(common).cast("long").alias("support"))
    elif mode == "horizontal":
        held = baskets(store.long).select("tid", F.col("items").alias("basket"), F.explode("items").alias("first"))
        named = each.select("items", F.col("items")[0].alias("first"))
        found = held.join(named, "first").where(F.size(F.array_except("items", "basket")) == 0).groupBy("items").agg(F.count(F.lit(1)).alias("support"))
    else:
        raise ValueError(mode)
    return each.join(found, "items", "left").select("items", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


__all__ = ["BLOCK", "conjunction", "count", "frequent_items"]
