"""The pipeline's stages, each against its operator, and the registered queries."""

import corpus_pipeline
import __spark_entry__ as entry

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_keep_the_columns_and_take_effect(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    seen, kept = docs, []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        seen = spark.createDataFrame(stage(spark, seen, sf).collect(), docs.schema)
        assert seen.columns == COLUMNS
        kept.append((name, seen.count()))
    counts = dict(kept)
    assert docs.count() >= counts["quality classifier"] >= counts["exact dedup"] >= counts["n-gram Jaccard join"] > 0
    last = corpus_pipeline.STAGES[-1][1](spark, seen, sf)
    assert last.count() == counts["mixing sources"]
    ids = {r.doc_id for r in seen.collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert not [i for i in ids if labels.get(i) == 0]


def test_run_and_registration(spark, sf):
    assert corpus_pipeline.run(spark, sf).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    names = list(entry.queries())
    assert "pipeline" in names and all(sum(n.startswith(f"op{k}_") for n in names) == 1 for k in range(1, 11))


def test_stages_take_repeats_nulls_clashing_columns_and_no_rows(spark, sf):
    rows = [(1, "one two three", "en", "s", 3, 9), (1, "one two three", "en", "s", 3, 9), (1, "another text of id one", "en", "s", 3, 9), (2, "ONE two three", "en", "s", 3, 9), (None, "alone", "en", None, 3, 9), (3, None, None, "s", 3, 9), (4, "", "en", "s", 3, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size long")
    kept = corpus_pipeline.exact(spark, docs, sf)
    assert kept.columns == docs.columns
    assert sorted((r.doc_id or 0, r.text) for r in kept.collect()) == [(0, "alone"), (1, "another text of id one"), (2, "ONE two three"), (4, "")]
    near = corpus_pipeline.near(spark, kept, sf)
    assert near.columns == docs.columns and near.count() == 4
    mixed = corpus_pipeline.mixed(spark, docs, sf)
    assert mixed.columns == docs.columns and {r["size"] for r in mixed.collect()} == {9}
    none = docs.where("doc_id < 0")
    assert [f(spark, none, sf).count() for f in (corpus_pipeline.exact, corpus_pipeline.near, corpus_pipeline.mixed, corpus_pipeline.tokens)] == [0] * 4
