"""Functions for SQL users; register(spark) makes them known."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def itemset_key(items: Column) -> Column:
    """A 64-bit key of a sorted itemset, for joins; the array itself decides between equal keys."""
    return F.xxhash64(items)


def hamming(a: Column, b: Column) -> Column:
    """Hamming distance of two sets given as arrays."""
    return F.size(F.array_except(a, b)) + F.size(F.array_except(b, a))


def jaccard(a: Column, b: Column) -> Column:
    """Jaccard similarity of two sets given as arrays; null for two empty ones."""
    union = F.size(F.array_union(a, b))
    return F.when(union > 0, F.size(F.array_intersect(a, b)) / union)


def md5_rank(seed: int, pos: Column) -> Column:
    """A 60-bit pseudo-random number of a position, the same in every engine that has md5."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), pos.cast("string"))), 1, 15), 16, 10).cast("long")


SQL_FUNCTIONS = {
    "itemset_key": "itemset_key(items ARRAY<INT>) RETURNS BIGINT RETURN xxhash64(items)",
    "itemset_union": "itemset_union(a ARRAY<INT>, b ARRAY<INT>) RETURNS ARRAY<INT> RETURN array_sort(array_union(a, b))",
    "is_compatible": "is_compatible(a ARRAY<INT>, b ARRAY<INT>) RETURNS BOOLEAN RETURN size(a) = size(b) AND size(array_union(a, b)) = size(a) + 1",
    "padded_hamming": "padded_hamming(ip BIGINT, most BIGINT) RETURNS BIGINT RETURN 2 * (most - ip)",
    "padded_jaccard": "padded_jaccard(ip BIGINT, most BIGINT) RETURNS DOUBLE RETURN ip / (2 * most - ip)",
    "bands_collision_prob": "bands_collision_prob(s DOUBLE, b INT, r INT) RETURNS DOUBLE RETURN 1 - power(1 - power(s, r), b)",
}


class KSubsets:
    """Rows of all subsets of k items of an array."""

    def eval(self, items: list, k: int) -> Iterator[tuple]:
        for sub in combinations(sorted(items or []), k):
            yield (list(sub),)


class LeaveOneOut:
    """Rows of an array without each of its items in turn."""

    def eval(self, items: list) -> Iterator[tuple]:
        for i in range(len(items or [])):
            yield (items[:i] + items[i + 1 :],)


class CoveringKeys:
    """Rows (block, v) of the masks of a block design with b blocks of radius r_b."""

    def eval(self, blocks: int, radius: int) -> Iterator[tuple]:
        for b in range(blocks):
            for v in range(1, 2 ** (radius + 1)):
                yield (b, v)


def bitmap_jaccard():  # noqa: ANN201
    """A vectorised function: Jaccard similarity of two bitmaps given as binary, null for two empty ones."""

    def one(x: bytes | None, y: bytes | None) -> float | None:
        if x is None or y is None:
            return None
        p, q = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
        union = int(np.bitwise_count(p | q).sum())
        return int(np.bitwise_count(p & q).sum()) / union if union else None

    def both(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="float64")

    return F.pandas_udf(both, "double")


def register(spark: SparkSession) -> None:
    """Temporary SQL functions, table functions and the bitmap similarity."""
    for text in SQL_FUNCTIONS.values():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    ints = T.ArrayType(T.IntegerType())
    spark.udtf.register("k_subsets", F.udtf(KSubsets, returnType=T.StructType([T.StructField("subset", ints)])))
    spark.udtf.register("leave_one_out", F.udtf(LeaveOneOut, returnType=T.StructType([T.StructField("subset", ints)])))
    spark.udtf.register("covering_keys", F.udtf(CoveringKeys, returnType="block int, v int"))
    spark.udf.register("bitmap_jaccard", bitmap_jaccard())


def mine_itemsets(spark: SparkSession, table: str, theta: float | str, method: str = "exact", view: str = "frequent_itemsets", **options: object) -> DataFrame:
    """Mines a table or view of rows (key, label) and leaves the result as a temporary view."""
    from ..plans.miner import mine

    found = mine(spark.table(table).select("key", "label").distinct(), theta, method, **options).labelled()
    found.createOrReplaceTempView(view)
    return found
