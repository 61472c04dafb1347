"""Exact deduplication by content-defined chunk recipes, with built-in functions only.

A text is cut where its content says so, each chunk gets an identifier that is checked to stand for one
chunk text only, and texts are equal when their ordered identifier lists are. Chunk texts cross the network
once, as keys of a distinct; afterwards only identifier lists move.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

#: Characters that every chunk has at least, and at most before a cut is forced.
CHUNK_MIN, CHUNK_MAX = 1024, 8192
#: A cut follows such content: about once in a few hundred characters of words, so that forced cuts are rare and
#: cuts fall into step again behind an insertion.
CUT = r"(?:\n|[aeiou]\s[b-f][aeiou]|\.\s[A-M])"


def chunks(text: Column, low: int = CHUNK_MIN, high: int = CHUNK_MAX) -> Column:
    """Content-defined chunks in order; joined they give the text again. An empty text has none."""
    pattern = rf"(?s).{{{low}}}.{{0,{high - low}}}?{CUT}|.{{1,{high}}}"
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def sha(c: Column) -> Column:
    return F.sha2(c, 256)


def clashes(texts: DataFrame, digest: Callable[[Column], Column] = sha) -> DataFrame:
    """Digests that stand for two or more different chunk texts of texts(norm): expected to be none."""
    distinct = texts.select(F.explode(chunks(F.col("norm"))).alias("chunk")).select(digest(F.col("chunk")).alias("id"), "chunk").distinct()
    return distinct.groupBy("id").count().where("count > 1").select("id")


def recipes(docs: DataFrame, digest: Callable[[Column], Column] = sha) -> DataFrame:
    """Adds recipe: the ordered, verified chunk identifiers of norm, as one string."""
    bad = clashes(docs, digest)
    listed = docs.withColumn("ids", F.transform(chunks(F.col("norm")), digest))
    if bad.limit(1).count() == 0:
        return listed.withColumn("recipe", F.array_join("ids", " ")).drop("ids")
    # Where a digest clashes, the length and text of the chunk itself are its identifier.
    each = docs.dropDuplicates(["row"]).select("row", F.posexplode(chunks(F.col("norm"))).alias("at", "chunk")).withColumn("id", digest(F.col("chunk")))
    each = each.join(bad.withColumn("bad", F.lit(True)), "id", "left")
    each = each.select("row", "at", F.when(F.col("bad"), F.concat_ws(":", "id", F.length("chunk"), "chunk")).otherwise(F.col("id")).alias("id"))
    made = each.groupBy("row").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "id"))), lambda x: x["id"]), " ").alias("recipe"))
    return listed.drop("ids").join(made, "row", "left").withColumn("recipe", F.coalesce("recipe", F.lit("")))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest: Callable[[Column], Column] = sha) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after lower-casing A-Z; null counts as empty; the largest id of a group
    stays. Of rows that repeat the same id, every one is returned with the same decision. An empty table
    gives an empty result. A null id is never kept before a real one. Texts of any length are read whole; other columns
    than the two are not read. Very many copies make one recipe's rows many: the join by recipe is left to adaptive skew handling.
    """
    base = docs.select(F.col(id_col).alias("doc_id"), ascii_lower(F.col(text_col)).alias("norm"))
    base = base.withColumn("row", F.struct(F.col("doc_id"), F.sha2("norm", 256)))
    r = recipes(base, digest).select("doc_id", "recipe", F.sha2("norm", 256).alias("text_sha256"))
    groups = r.groupBy("recipe").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    out = r.join(groups, "recipe")
    return out.select("doc_id", "keep_id", "group_size", F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull()).alias("kept"), "text_sha256")


SQL = """
WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS n FROM documents)
SELECT doc_id, max(doc_id) OVER (PARTITION BY n) AS keep_id, count(*) OVER (PARTITION BY n) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY n) AS kept, sha256(n) AS text_sha256
FROM t
"""
