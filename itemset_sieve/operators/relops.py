"""Relational operators around mining, each a plain plan of joins, windows and aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def constrained(itemsets: DataFrame, include: list[int] = (), exclude: list[int] = (), sizes: tuple[int, int] = (1, 1 << 30)) -> DataFrame:
    """Itemsets that hold all of include, none of exclude, and have a size in range."""
    out = itemsets.where(F.size("items").between(*sizes))
    for i in include:
        out = out.where(F.array_contains("items", i))
    return out.where(~F.arrays_overlap("items", F.array(*[F.lit(i).cast("int") for i in exclude]))) if exclude else out


def top_k(itemsets: DataFrame, k: int, by: str | None = "level") -> DataFrame:
    """The k most frequent itemsets, of each level or overall; ties by name."""
    if by is None:
        return itemsets.orderBy(F.col("support").desc(), "itemset").limit(k).withColumn("rn", F.row_number().over(Window.orderBy(F.col("support").desc(), "itemset")))
    order = Window.partitionBy(by).orderBy(F.col("support").desc(), "itemset")
    return itemsets.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= k)


def ranked(itemsets: DataFrame) -> DataFrame:
    """Rank, dense rank, share below, quarter, and the support before, by falling support within a level."""
    w = Window.partitionBy("level").orderBy(F.col("support").desc(), "itemset")
    s = Window.partitionBy("level").orderBy(F.col("support").desc())
    return itemsets.select("*", F.rank().over(s).alias("rk"), F.dense_rank().over(s).alias("drk"), F.ntile(4).over(w).alias("quarter"), F.lag("support").over(w).alias("before"), F.first("support").over(w).alias("most"))


def rollup_levels(itemsets: DataFrame) -> DataFrame:
    """Number and sum of supports by level, and in all (level null)."""
    return itemsets.rollup("level").agg(F.count(F.lit(1)).alias("n"), F.sum("support").alias("support"), F.grouping("level").cast("int").alias("total"))


def cube(df: DataFrame, *cols: str) -> DataFrame:
    """Counts of all combinations of the columns' values: a cell is the support of an attribute itemset."""
    return df.cube(*cols).agg(F.count(F.lit(1)).alias("n"))


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: Column, name: str) -> DataFrame:
    """left with the value of the last right row of the same key at or before it; null if there is none.

    Both sides go through one window by key: a single sort, no join. Of right rows at the same time the
    largest value counts.
    """
    r = right.groupBy(key, at).agg(F.max(value).alias("_v")).withColumn("_side", F.lit(0))
    cols = [c for c in left.columns if c not in (key, at)]
    both = left.withColumn("_side", F.lit(1)).unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(name, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select(key, at, *cols, name)


def within(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int, right_as: str) -> DataFrame:
    """Pairs of rows of the same key with 0 < right time - left time <= seconds: an equi-join on time slots of that
    width, each left row put into its own and the next."""
    slot = F.floor(F.unix_seconds(F.col(at).cast("timestamp")) / seconds)
    a = left.withColumn("_slot", F.explode(F.array(slot, slot + 1)))
    b = right.select(F.col(key).alias("_k"), *[F.col(c).alias(f"{right_as}_{c}") for c in right.columns if c != key], slot.alias("_s"))
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    gap = micros(f"{right_as}_{at}") - micros(at)
    return a.join(b, (F.col(key) == F.col("_k")) & (F.col("_slot") == F.col("_s"))).where((gap > 0) & (gap <= seconds * 1_000_000)).drop("_k", "_s", "_slot")


def set_ops(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows by where they are: both, only a, only b."""
    return a.intersect(b).withColumn("side", F.lit("both")).union(a.subtract(b).withColumn("side", F.lit("a"))).union(b.subtract(a).withColumn("side", F.lit("b")))


def one_hot(long: DataFrame, items: list[int]) -> DataFrame:
    """tid and a 0/1 column for each of a few items; and back with unpivot."""
    return long.where(F.col("item").isin(items)).groupBy("tid").pivot("item", items).agg(F.lit(1)).na.fill(0)


def from_one_hot(wide: DataFrame, items: list[int]) -> DataFrame:
    return wide.unpivot("tid", [str(i) for i in items], "item", "v").where("v = 1").select("tid", F.col("item").cast("int").alias("item"))


def itemset_counts_preview(long: DataFrame, k: int) -> DataFrame:
    """Approximate number of distinct items and median item frequency, before mining."""
    freq = long.groupBy("item").agg(F.count(F.lit(1)).alias("f"))
    return freq.agg(F.approx_count_distinct("item").alias("items"), F.percentile_approx("f", 0.5).alias("median_freq"), F.max_by("item", "f").alias("top")).limit(k)
