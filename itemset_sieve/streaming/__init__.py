"""Streams of events to baskets, incremental supports, and mining of closed windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.miner import mine
from ..scratch import remove

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """A stream of the events file. Its times have no zone: they are read as the session's, which should be UTC."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def windows(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour", gap: str | None = None) -> DataFrame:
    """window, user_id, items: the event types of each user in tumbling, sliding or session windows."""
    w = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.collect_set("event_type").alias("items"))


def item_counts(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Incremental level-1 supports: starts, event_type, n of each window."""
    counted = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("starts"), "event_type", "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def followed(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: right events of the same user up to `within` after a left one."""
    a = left.withWatermark("ts", late).select("user_id", F.col("ts").alias("lts"), F.col("event_id").alias("lid"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("ruser"), F.col("ts").alias("rts"), F.col("event_id").alias("rid"))
    return a.join(b, F.expr(f"user_id = ruser AND rts > lts AND rts <= lts + interval {within}"))


def run_once(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Everything that is there now, into a Parquet sink, once."""
    q = stream.writeStream.outputMode(mode).format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def mine_windows(baskets: DataFrame, theta: float | str, out: str, checkpoint: str, method: str = "exact", **options: object) -> None:
    """Mines every micro-batch of closed windows. A batch is written under its number, so a repeat replaces it."""
    def each(batch: DataFrame, number: int) -> None:
        rows = batch.select(F.concat_ws("|", F.col("w.start").cast("string"), F.col("user_id").cast("string")).alias("key"), F.explode("items").alias("label"))
        found = mine(rows, theta, method, **options).labelled() if not rows.isEmpty() else None
        if found is not None:
            found.write.mode("overwrite").parquet(f"{out}/batch={number}")

    q = baskets.writeStream.foreachBatch(each).outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def late_rows(events: DataFrame, newest: object, late_seconds: int) -> DataFrame:
    """Rows of a batch that are older than the watermark which the newest time so far gives: the side output."""
    return events.where(F.unix_seconds("ts") < F.unix_seconds(F.lit(newest)) - late_seconds)


def _batch(spark: SparkSession, out: str, number: int, schema: str) -> DataFrame:
    return spark.read.schema(schema).parquet(f"{out}/batch={number}")


def split_late(events: DataFrame, out: str, checkpoint: str, late_seconds: int = 3600) -> None:
    """Writes rows in time to out/rows and late ones to out/late, each micro-batch under its number, so a repeat replaces it.

    Late is what is older than late_seconds before the newest time of all batches before; a null time is in time. That newest
    time is one row a batch in out/newest.
    """
    def each(batch: DataFrame, number: int) -> None:
        spark, kind = batch.sparkSession, "newest long"
        batch = batch.persist()
        try:
            before = _batch(spark, f"{out}/newest", number - 1, kind) if number else spark.createDataFrame([], kind)
            newest = before.first()
            limit = newest[0] - late_seconds * 1_000_000 if newest and newest[0] is not None else None
            late = F.coalesce(F.unix_micros("ts") < F.lit(limit).cast("long"), F.lit(False))
            batch.where(~late).write.mode("overwrite").parquet(f"{out}/rows/batch={number}")
            batch.where(late).write.mode("overwrite").parquet(f"{out}/late/batch={number}")
            before.union(batch.select(F.unix_micros("ts"))).agg(F.max("newest").alias("newest")).write.mode("overwrite").parquet(f"{out}/newest/batch={number}")
            if number > 1:
                remove(spark, f"{out}/newest/batch={number - 2}")
        finally:
            batch.unpersist()

    q = events.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def run_changes(counts: DataFrame, out: str, checkpoint: str, mode: str) -> None:
    """Update and complete mode, which files as a sink don't have: each micro-batch's rows under its number. Of complete
    results the last two batches stay, of updates all."""
    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        if mode == "complete" and number > 1:
            remove(batch.sparkSession, f"{out}/batch={number - 2}")

    q = counts.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def current(spark: SparkSession, out: str, schema: str, keys: list[str], mode: str) -> DataFrame:
    """What run_changes has come to: in complete mode the last batch, in update mode the last row of every key."""
    rows = spark.read.schema(f"{schema}, batch int").parquet(out)
    if mode == "complete":
        return rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0]).drop("batch")
    rest = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(*[F.max_by(c, "batch").alias(c) for c in rest])


SUMMARY = "label string, slot int, h long"


def minima(pairs: DataFrame, slots: int) -> DataFrame:
    """label, slot, h: the smallest rank of the label's keys in each slot. Ranks depend on slot and key alone, and a minimum
    of minima is one of all, so summaries of parts can be merged; pairs that repeat change nothing."""
    rows = pairs.where("key is not null and label is not null").withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(slots - 1))))
    rank = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("slot").cast("string"), "key")), 1, 15), 16, 10).cast("long")
    return rows.groupBy("label", "slot").agg(F.min(rank).alias("h"))


def summaries(pairs: DataFrame, out: str, checkpoint: str, slots: int = 64) -> None:
    """Minwise summaries kept up to date: each micro-batch (key, label) merges its minima with those of the batch before, and
    reads no older row again. out/batch=<last> has all; a repeated batch starts from the one before and replaces itself."""
    def each(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = minima(batch, slots)
        if number:
            new = _batch(spark, out, number - 1, SUMMARY).union(new).groupBy("label", "slot").agg(F.min("h").alias("h"))
        new.write.mode("overwrite").parquet(f"{out}/batch={number}")
        if number > 1:
            remove(spark, f"{out}/batch={number - 2}")

    q = pairs.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def episodes(events: DataFrame, theta: float | str, width: str = "1 hour", slide: str | None = None, **options: object):  # noqa: ANN201
    """Event types that occur together within a window of time: windows are the transactions."""
    w = F.window(F.col("ts").cast("timestamp"), width, slide) if slide else F.window(F.col("ts").cast("timestamp"), width)
    rows = events.select(F.col("event_type").alias("label"), w.alias("w")).select(F.col("w.start").cast("string").alias("key"), "label").distinct()
    return mine(rows, theta, **options)
