"""What several operators share: reading, ASCII lower-casing, word patterns, shared scratch tables, components."""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..scratch import forget, scratch_dir
from ..scratch import written as materialize

__all__ = ["ascii_lower", "components", "fold", "forget", "materialize", "scratch_dir", "table", "trim", "trimmed"]

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: A word, for Python's re and for Java's and DuckDB's regular expressions alike.
WORD = r"[^\x20\x09-\x0D]+"
#: str.translate table that lower-cases A-Z and nothing else.
ASCII_LOWER = {ord(a): b for a, b in zip(UPPER, LOWER)}


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """The named columns of a Parquet table, and no others, so that extra columns never clash."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*cols)


def ascii_lower(c: Column) -> Column:
    """A-Z lower-cased, null read as empty."""
    return F.translate(F.coalesce(c, F.lit("")), UPPER, LOWER)


def fold(c: Column) -> Column:
    """crc32 of the id's decimal text, as the held-out rules define it."""
    return F.crc32(c.cast("string").cast("binary"))


def trim() -> None:
    """Gives memory that a task has freed back to the system: workers are kept, and wait beside those of other stages."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        ctypes.CDLL(None).malloc_trim(0)


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run for mapInArrow, with memory given back before it starts and when it ends."""

    def outer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()
        yield from run(batches)
        trim()

    return outer


def components(edges: DataFrame) -> DataFrame:
    """Smallest reachable id of every node of edges(a, b): rows (node, component).

    Alternates min-label steps with pointer jumping; every round is a written table. An empty edge
    table gives an empty result; repeated and reversed edges and loops change nothing.
    """
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = materialize(both, "edges")
    label = materialize(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("c")).select(F.col("a").alias("node"), "c"), "labels")
    written = label
    while True:
        near = both.join(label, both["b"] == label["node"]).groupBy("a").agg(F.min("c").alias("n"))
        step = label.join(near, label["node"] == near["a"]).select("node", F.col("c").alias("old"), F.least("c", "n").alias("c"))
        up = label.select(F.col("node").alias("p"), F.col("c").alias("pc"))
        step = step.join(up, step["c"] == up["p"], "left").select("node", "old", F.least("c", F.coalesce("pc", "c")).alias("c"))
        step = materialize(step, "labels")
        forget(written)
        if step.where("old <> c").limit(1).count() == 0:
            forget(both)
            return step.select("node", F.col("c").alias("component"))
        written, label = step, step.select("node", "c")
