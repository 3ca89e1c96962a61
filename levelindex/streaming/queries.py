"""Streaming queries over `events`: windowed load, late rows, sessions, inserts into an index."""

from __future__ import annotations

from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.operators.build import RootBudget, build_index, verify_index
from levelindex.sources.tables import event_vectors, table
from levelindex.streaming.upserts import changes_of, replay, run_to_table, windowed_load


STAMP = "yyyy-MM-dd HH:mm:ss"


def folder(spark, d: str, name: str) -> str:
    """A table copied to a folder, which is what a file stream reads."""
    where = scratch.path(spark, name)
    rows = table(spark, d, name)
    rows.withColumn("ts", rows.ts.cast("timestamp")).write.parquet(where)
    return where


def loads(stream, watermark: str = "2 hours"):
    """One row for each window and type."""
    return windowed_load(stream, watermark=watermark).select(F.date_format("w.start", STAMP).alias("start"), "event_type", "n", F.round("total", 2).alias("total"))


def events_windowed_load(spark, d):
    where = folder(spark, d, "events")
    stream = spark.readStream.schema(spark.read.parquet(where).schema).parquet(where)
    return run_to_table(loads(stream), ["start", "event_type"])


def late_updates_dropped(spark, d):
    """Events in three batches: the third meets the watermark that the first one set, so its rows in closed windows are dropped."""
    rows = table(spark, d, "events")
    rows = rows.withColumn("ts", rows.ts.cast("timestamp"))
    where = scratch.path(spark, "late")
    for i, part in enumerate(("event_id % 10 != 3", "event_id % 20 = 3", "event_id % 20 = 13")):
        rows.where(part).coalesce(1).write.parquet(f"{where}/part{i}")
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{where}/*")
    kept = run_to_table(loads(stream), ["start", "event_type"]).agg(F.sum("n").alias("kept"))
    return kept.select("kept", (F.lit(rows.count()) - F.col("kept")).alias("dropped"))


def event_sessions(spark, d):
    """Sessions of a user: events less than six hours apart."""
    where = folder(spark, d, "events")
    stream = spark.readStream.schema(spark.read.parquet(where).schema).parquet(where)
    found = stream.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    out, check = scratch.path(spark, "sessions"), scratch.path(spark, "sessions-state")
    found = found.select(F.date_format("w.start", STAMP).alias("start"), "user_id", "n")
    found.writeStream.foreachBatch(lambda batch, i: batch.write.mode("overwrite").parquet(f"{out}/batch={i}")).option("checkpointLocation", check).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    last = spark.read.parquet(out)
    return last.join(last.agg(F.max("batch").alias("batch")), "batch").select("start", "user_id", "n")


def events_stream_insert(spark, d):
    """Events after the first tenth arrive as a stream of inserts into an index: what is missing, left over or out of order afterwards."""
    rows = scratch.save(event_vectors(spark, d), "events")
    start = build_index(rows.where("vec_id % 10 = 0"), RootBudget(vectors=1), density=0.1, levels=2)
    where = scratch.path(spark, "arriving")
    rows.where("vec_id % 10 != 0").repartition(4).write.parquet(where)
    stream = changes_of(spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 2).parquet(where), "3650 days")
    index = replay(stream, start, scratch.path(spark, "versions"), scratch.path(spark, "versions-state"))
    whole = index.members(0).select("vec_id")
    missing, extra = rows.select("vec_id").exceptAll(whole).count(), whole.exceptAll(rows.select("vec_id")).count()
    found = verify_index(index).agg(F.sum("headless").alias("headless"), F.sum("unlisted").alias("unlisted"), F.sum("stale").alias("stale"))
    return found.select("headless", "unlisted", "stale", F.lit(missing).cast("long").alias("missing"), F.lit(extra).cast("long").alias("extra"))


QUERIES = {f.__name__: f for f in (events_windowed_load, late_updates_dropped, event_sessions, events_stream_insert)}

WALL = "'%Y-%m-%d %H:%M:%S'"
ORACLE = {
    "events_windowed_load": f"SELECT strftime(date_trunc('hour', ts), {WALL}) AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1, 2",
    "late_updates_dropped": "SELECT kept, (SELECT count(*) FROM events) - kept AS dropped FROM (SELECT count(*) AS kept FROM events WHERE event_id % 20 <> 13 OR date_trunc('hour', ts) + INTERVAL 1 HOUR > (SELECT max(ts) - INTERVAL 2 HOUR FROM events WHERE event_id % 10 <> 3))",
    "event_sessions": f"""SELECT strftime(min(ts), {WALL}) AS start, user_id, count(*) AS n FROM (
  SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM (
    SELECT *, coalesce((ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR)::INT, 1) AS fresh FROM events))
GROUP BY user_id, session""",
    "events_stream_insert": "SELECT 0::BIGINT AS headless, 0::BIGINT AS unlisted, 0::BIGINT AS stale, 0::BIGINT AS missing, 0::BIGINT AS extra",
}
