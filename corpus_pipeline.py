"""A corpus from raw documents: quality filter, exact and near deduplication, source mixing, tokens.

Each stage gets what its predecessor kept, as a written table, and all but the last return the columns of
documents. run() applies them in order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from itemset_sieve.llm import bpe, exact_dedup, mix, ngram_join, quality_cnn
from itemset_sieve.llm.common import ascii_lower, forget, materialize, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier, learnt from the labels, doesn't reject. A null text is judged as an empty one;
    repeated rows fare alike; other columns pass through; no rows give no rows."""
    rows = quality_cnn.training_rows(docs.select("doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality_cnn.scored(docs, quality_cnn.fit(*rows), "_score").where("_score >= 0.5").drop("_score")


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the largest id; of rows that repeat its id and text, one. Rows with one id and
    different texts are judged each. Null texts are equal to empty ones; a null id stays only where no other has the text."""
    groups = exact_dedup.exact_groups(docs).where("kept").select(F.col("doc_id").alias("_id"), F.col("text_sha256").alias("_kept")).distinct()
    named = docs.withColumn("_sha", F.sha2(ascii_lower(F.col("text")), 256))
    return named.join(groups, F.expr("doc_id <=> _id and _sha = _kept"), "left_semi").dropDuplicates(["doc_id", "_sha"]).select(docs.columns)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest document of each component of near duplicates. Null and empty texts link with nothing and stay; rows that
    repeat an id count as one document; a null id stays unless its text is that of another document."""
    first = ngram_join.near_duplicates(docs).where("doc_id <=> component_id").select(F.col("doc_id").alias("_id")).distinct()
    return docs.join(first, F.expr("doc_id <=> _id"), "left_semi").select(docs.columns)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it. Null texts have no words; a null source is one of its own; columns named
    like the mix's results are kept as they are."""
    drawn = mix.mix(docs, prefix="_mix_").where("_mix_copies > 0")
    return drawn.select(*docs.columns, F.explode(F.sequence(F.lit(1), F.col("_mix_copies").cast("int"))).alias("_copy")).drop("_copy")


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts, and digests of ids and decoded bytes, of every copy. A null text has no tokens; no rows give no rows."""
    import public_tokenizers

    return bpe.encoded(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, digests=True)


STAGES = [("quality classifier", quality), ("exact dedup", exact), ("n-gram Jaccard join", near), ("mixing sources", mixed), ("byte-level BPE", tokens)]

#: The classifier is learnt and the tokenizer is a table of merges, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source", "n_chars")
    before = None
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.replace(" ", "-"))
        if before is not None:
            forget(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
