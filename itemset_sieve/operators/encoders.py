"""Tables turned into transactions: rows (key, label), distinct, without nulls."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import load


def pairs(df: DataFrame, key: Column, label: Column) -> DataFrame:
    return df.select(key.cast("string").alias("key"), label.cast("string").alias("label")).where("key is not null and label is not null").distinct()


def wide_columns(df: DataFrame, key: Column, cols: dict[str, Column]) -> DataFrame:
    """Rows (key, labels) with one item name=value of each column, none twice; a key may have several rows."""
    items = F.array_distinct(F.array_compact(F.array(*[F.concat(F.lit(f"{name}="), c.cast("string")) for name, c in cols.items()])))
    return df.select(key.cast("string").alias("key"), items.alias("labels")).where("key is not null and size(labels) > 0")


def from_columns(df: DataFrame, key: Column, cols: dict[str, Column]) -> DataFrame:
    """One item name=value of each column."""
    return pairs(wide_columns(df, key, cols).select("key", F.explode("labels").alias("label")), F.col("key"), F.col("label"))


def from_text(df: DataFrame, key: str, text: str) -> DataFrame:
    """Distinct lower-cased letter runs."""
    runs = F.array_distinct(F.split(F.lower(text), r"[^\p{L}]+"))
    return pairs(df.select(F.col(key).alias("k"), F.explode(runs).alias("i")).where("i <> ''"), F.col("k"), F.col("i"))


def from_vector(df: DataFrame, key: str, vector: str) -> DataFrame:
    """The dimensions with positive values."""
    return pairs(df.select(F.col(key).alias("k"), F.posexplode(vector).alias("i", "x")).where("x > 0"), F.col("k"), F.col("i"))


def from_html(df: DataFrame, key: str, html: str) -> DataFrame:
    """Names of the tags."""
    tags = F.array_distinct(F.regexp_extract_all(F.lower(html), F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1)))
    return pairs(df.select(F.col(key).alias("k"), F.explode(tags).alias("i")), F.col("k"), F.col("i"))


def from_json(df: DataFrame, key: str, props: str, name: str) -> DataFrame:
    """One item from a key of a JSON text."""
    return pairs(df, F.col(key), F.concat(F.lit(f"{name}="), F.get_json_object(props, f"$.{name}")))


def from_events(df: DataFrame, unit: str = "day") -> DataFrame:
    """Event types of each user and unit of time."""
    return pairs(df, F.concat_ws("|", F.col("user_id"), F.date_format(F.date_trunc(unit, "ts"), "yyyy-MM-dd HH:mm")), F.col("event_type"))


def _lines(spark: SparkSession, d: str, key: str, label: str) -> DataFrame:
    lines = load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    if label.startswith("p_"):
        lines = lines.join(load(spark, d, "part", "p_partkey", label), F.col("l_partkey") == F.col("p_partkey"))
    if key == "o_custkey":
        lines = lines.join(load(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return pairs(lines, F.col(key), F.col(label))


def _attributes(spark: SparkSession, d: str, of: Callable[..., DataFrame] = from_columns) -> DataFrame:
    cols = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_quantity", "l_discount", "l_tax", "l_shipdate")
    lines = load(spark, d, "lineitem", *cols)
    hundredth = lambda c: F.round(F.col(c) * 100).cast("int")
    values = {
        "rf": F.col("l_returnflag"), "ls": F.col("l_linestatus"), "ln": F.col("l_linenumber"), "q": F.floor(F.col("l_quantity") / 10),
        "d": hundredth("l_discount"), "tx": hundredth("l_tax"), "y": F.year("l_shipdate"),
    }
    return of(lines, F.concat_ws("|", *cols[:4]), values)


def _labels(spark: SparkSession, d: str) -> DataFrame:
    df = load(spark, d, "labels").join(load(spark, d, "documents", "doc_id", "lang", "source"), "doc_id")
    return from_columns(df, F.col("doc_id"), {c: F.col(c) for c in ("quality", "toxic", "lang", "source")})


ENCODINGS = {
    "e1": lambda s, d: _lines(s, d, "l_orderkey", "l_partkey"),
    "e2": lambda s, d: _lines(s, d, "l_orderkey", "p_brand"),
    "e2b": lambda s, d: _lines(s, d, "l_orderkey", "p_type"),
    "e2c": lambda s, d: _lines(s, d, "o_custkey", "p_brand"),
    "e3": _attributes,
    "e4": lambda s, d: from_text(load(s, d, "documents", "doc_id", "text"), "doc_id", "text"),
    "e5": lambda s, d: from_events(load(s, d, "events", "user_id", "ts", "event_type")),
    "e6": lambda s, d: from_vector(load(s, d, "embeddings", "vec_id", "embedding"), "vec_id", "embedding"),
    "e7": lambda s, d: _lines(s, d, "o_custkey", "l_suppkey"),
    "e8": lambda s, d: from_html(load(s, d, "pages", "page_id", "html"), "page_id", "html"),
    "e9": lambda s, d: from_text(load(s, d, "conversations", "conv_id", "text"), "conv_id", "text"),
    "e10": _labels,
}


def encode(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The transactions of a named encoding of the given tables."""
    return ENCODINGS[name](spark, sf_dir)


#: Encodings of which every row of a table has all items of a key, as rows (key, labels): a store is built of these without a row for each item.
WIDE = {"e3": lambda s, d: _attributes(s, d, wide_columns)}


def encode_wide(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The same transactions for build(): rows (key, labels) where the encoding has them, else rows (key, label)."""
    return WIDE[name](spark, sf_dir) if name in WIDE else encode(spark, sf_dir, name)
