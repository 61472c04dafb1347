"""Readers, writers and a generator for transactions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A table's named columns, so that the scan reads no others."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_transactions(spark: SparkSession, path: str, fmt: str = "parquet", layout: str = "long", sep: str = " ") -> DataFrame:
    """Rows (key, label) from a file of transactions.

    layout long: columns key and label; array: columns key and items; line (fmt text): one transaction a line,
    items between sep. An empty item is dropped.
    """
    if fmt == "text":
        lines = spark.read.text(path).select(F.xxhash64("value", F.monotonically_increasing_id()).alias("key"), F.split("value", sep, -1).alias("items"))
    elif fmt == "csv":
        lines = spark.read.csv(path, header=True, schema="key string, label string")
    elif fmt == "json":
        lines = spark.read.json(path, schema="key string, label string" if layout == "long" else "key string, items array<string>")
    else:
        lines = spark.read.format(fmt).load(path)
    if layout == "long" and fmt != "text":
        return lines.select(F.col("key").cast("string"), F.col("label").cast("string")).where("label <> ''")
    return lines.select(F.col("key").cast("string"), F.explode("items").alias("label")).where("label <> ''")


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    w = df.write.mode(mode).format(fmt)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def synthetic(spark: SparkSession, n: int, m: int, density: float, planted: dict[tuple[int, ...], float] | None = None, seed: int = 0) -> DataFrame:
    """Rows (key, label): n transactions over m items, each present with the given density, plus itemsets that
    are put into a share of the transactions. A function of the seed and the transaction alone."""
    share = lambda *c: F.pmod(F.xxhash64(F.lit(seed), *c), F.lit(1 << 40)) / F.lit(float(1 << 40))
    rows = spark.range(n).select(F.col("id").alias("key"), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("label"))
    out = rows.where(share("key", "label") < density)
    for k, (items, part) in enumerate((planted or {}).items()):
        extra = spark.range(n).where(share("id", F.lit(-1 - k)) < part).select(F.col("id").alias("key"), F.explode(F.array(*map(F.lit, items))).alias("label"))
        out = out.union(extra)
    return out.select(F.col("key").cast("string").alias("key"), F.col("label").cast("string").alias("label")).distinct()
