"""Readers, writers, SQL functions, relational operators and streams."""

import pytest
from pyspark.sql import functions as F

from itemset_sieve import functions as fn
from itemset_sieve import streaming
from itemset_sieve.operators import encoders, relops
from itemset_sieve.sources import load, read_transactions, write


def test_formats_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([("t1", "a"), ("t1", "b"), ("t2", "a")], "key string, label string")
    want = sorted(map(tuple, rows.collect()))
    for fmt in ("parquet", "json", "orc"):
        write(rows, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, read_transactions(spark, str(tmp_path / fmt), fmt).collect())) == want
    rows.write.csv(str(tmp_path / "csv"), header=True)
    assert sorted(map(tuple, read_transactions(spark, str(tmp_path / "csv"), "csv").collect())) == want
    (tmp_path / "lines.txt").write_text("a b\nb  c\n")
    lines = read_transactions(spark, str(tmp_path / "lines.txt"), "text").groupBy("key").agg(F.array_sort(F.collect_list("label")).alias("x"))
    assert sorted(r["x"] for r in lines.collect()) == [["a", "b"], ["b", "c"]]


def test_scan_reads_only_named_columns(spark, sf):
    plan = load(spark, sf, "documents", "doc_id", "lang").where("lang = 'en'")._jdf.queryExecution().executedPlan().toString()
    assert "text" not in plan.split("ReadSchema")[1] and "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in plan


def test_encoders_on_nulls_and_blanks(spark):
    df = spark.createDataFrame([(1, "A b, a"), (2, ""), (3, None)], "k int, t string")
    assert sorted(map(tuple, encoders.from_text(df, "k", "t").collect())) == [("1", "a"), ("1", "b")]
    v = spark.createDataFrame([(1, [0.5, -1.0, None]), (2, None)], "k int, v array<double>")
    assert list(map(tuple, encoders.from_vector(v, "k", "v").collect())) == [("1", "0")]
    j = spark.createDataFrame([(1, '{"k": 3}'), (2, "broken")], "k int, p string")
    assert list(map(tuple, encoders.from_json(j, "k", "p", "k").collect())) == [("1", "k=3")]


def test_sql_functions(spark):
    fn.register(spark)
    r = spark.sql("SELECT itemset_union(array(1, 3), array(2, 3)) u, is_compatible(array(1, 3), array(2, 3)) c, padded_hamming(3, 5) h, padded_jaccard(3, 5) j, bands_collision_prob(0.5, 2, 1) p").first()
    assert (r.u, r.c, r.h, round(r.j, 6), r.p) == ([1, 2, 3], True, 4, round(3 / 7, 6), 0.75)
    assert spark.sql("SELECT * FROM k_subsets(array(1, 2, 3), 2)").count() == 3
    assert spark.sql("SELECT * FROM covering_keys(3, 2)").count() == 21
    a, b = F.array(F.lit(1), F.lit(2)), F.array(F.lit(2), F.lit(3))
    assert spark.range(1).select(fn.hamming(a, b), fn.jaccard(a, b)).first()[:] == (2, 1 / 3)


def test_mine_from_a_view(spark):
    spark.createDataFrame([("1", "a"), ("1", "b"), ("2", "a")], "key string, label string").createOrReplaceTempView("rows_to_mine")
    fn.mine_itemsets(spark, "rows_to_mine", "0.5")
    assert {(r.itemset, r.support) for r in spark.sql("SELECT * FROM frequent_itemsets").collect()} == {("a", 2), ("b", 1), ("a,b", 1)}


def test_as_of_and_interval_joins(spark):
    left = spark.createDataFrame([(1, 10, "x"), (1, 3, "y"), (2, 5, "z")], "k int, t int, v string")
    right = spark.createDataFrame([(1, 4, 40), (1, 10, 100), (1, 10, 90)], "k int, t int, w int")
    got = {r["v"]: r["found"] for r in relops.as_of(left, right, "k", "t", F.col("w"), "found").collect()}
    assert got == {"x": 100, "y": None, "z": None}


def test_set_operations_and_pivot(spark):
    a, b = spark.createDataFrame([(1,), (2,)], "x int"), spark.createDataFrame([(2,), (3,)], "x int")
    assert {(r.x, r.side) for r in relops.set_ops(a, b).collect()} == {(2, "both"), (1, "a"), (3, "b")}
    long = spark.createDataFrame([(1, 0), (1, 2), (2, 2)], "tid long, item int")
    assert sorted(map(tuple, relops.from_one_hot(relops.one_hot(long, [0, 2]), [0, 2]).collect())) == [(1, 0), (1, 2), (2, 2)]


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "session"])
def test_windows_close_behind_the_watermark(spark, sf, tmp_path, kind):
    how = {"tumbling": {}, "sliding": {"width": "2 days", "slide": "1 day"}, "session": {"gap": "6 hours"}}[kind]
    streaming.run_once(streaming.windows(streaming.read_events(spark, sf), **how), str(tmp_path / "out"), str(tmp_path / "state"))
    out = spark.read.parquet(str(tmp_path / "out"))
    assert out.count() > 0 and out.where("size(items) = 0").count() == 0


def test_stream_deduplicates_and_joins(spark, sf, tmp_path):
    e = streaming.read_events(spark, sf)
    streaming.run_once(streaming.deduplicated(e), str(tmp_path / "a"), str(tmp_path / "b"))
    assert spark.read.parquet(str(tmp_path / "a")).select("event_id").distinct().count() == load(spark, sf, "events", "event_id").distinct().count()
    e2 = streaming.read_events(spark, sf)
    j = streaming.followed(e.where("event_type = 'signup'"), e2.where("event_type = 'purchase'"), "1 day")
    streaming.run_once(j, str(tmp_path / "c"), str(tmp_path / "d"))
    assert spark.read.parquet(str(tmp_path / "c")).where("rts <= lts").count() == 0


def events_in_batches(spark, folder, batches):
    """A stream that reads one file of (event_id, minute, user_id, event_type) a micro-batch, in order, and how to add one."""
    kind = "event_id long, ts timestamp, user_id long, event_type string"

    def add(rows):
        rows = [(i, None if m is None else f"2024-01-01 {m // 60:02}:{m % 60:02}:00", u, e) for i, m, u, e in rows]
        df = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string")
        df.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(folder)

    for rows in batches:
        add(rows)
    return spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(folder), add


def test_late_rows_go_aside(spark, tmp_path):
    at = [str(tmp_path / x) for x in ("in", "out", "state")]
    stream, add = events_in_batches(spark, at[0], [[(1, 100, 1, "a"), (2, 10, 1, "a")]])  # one batch: nothing is late in it
    streaming.split_late(stream, at[1], at[2])
    for rows in ([(3, 39, 1, "a"), (4, 40, 1, "b"), (5, None, 1, "c")], [(6, 39, 2, "a")], [(7, 300, 2, "a")], [(8, 239, 2, "a"), (9, 240, 2, "a")]):
        add(rows)
        streaming.split_late(stream, at[1], at[2])
    ids = {side: sorted(r.event_id for r in spark.read.schema("event_id long").parquet(f"{at[1]}/{side}").collect()) for side in ("rows", "late")}
    assert ids == {"rows": [1, 2, 4, 5, 7, 9], "late": [3, 6, 8]}


@pytest.mark.parametrize("mode", ["update", "complete"])
def test_counts_in_update_and_complete_mode(spark, tmp_path, mode):
    at = [str(tmp_path / x) for x in ("in", "out", "state")]
    stream, add = events_in_batches(spark, at[0], [[(1, 10, 1, "a"), (2, 20, 2, "a"), (3, 30, 1, "b")]])
    counts = streaming.item_counts(stream, "1 hour")
    for rows in ([(4, 40, 1, "a"), (5, 70, 1, "c")], [(6, 50, 1, "b")]):
        streaming.run_changes(counts, at[1], at[2], mode)
        add(rows)
    streaming.run_changes(counts, at[1], at[2], mode)
    got = streaming.current(spark, at[1], "starts timestamp, event_type string, n long", ["starts", "event_type"], mode)
    assert sorted((r.starts.hour, r.event_type, r.n) for r in got.collect()) == [(0, "a", 3), (0, "b", 2), (1, "c", 1)]


def test_summaries_merge_to_those_of_all_rows(spark, tmp_path):
    at = [str(tmp_path / x) for x in ("in", "out", "state")]
    parts = [[(i, i, i % 7 + 10 * k, "ab"[i % 2]) for i in range(9)] for k in range(4)] + [[(0, 0, 3, "a"), (1, 1, None, "b"), (2, 2, 4, None)]]
    stream, add = events_in_batches(spark, at[0], parts[:1])
    pairs = stream.select(F.col("user_id").cast("string").alias("key"), F.col("event_type").alias("label"))
    streaming.summaries(pairs, at[1], at[2], 5)
    for rows in parts[1:]:
        add(rows)
        streaming.summaries(pairs, at[1], at[2], 5)
    got = streaming.current(spark, at[1], streaming.SUMMARY, ["label", "slot"], "complete")
    whole = spark.read.parquet(at[0]).select(F.col("user_id").cast("string").alias("key"), F.col("event_type").alias("label"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, streaming.minima(whole, 5).collect())) and got.count() == 10
