"""Streams of inserts and deletes into a leveled index, and windowed load of the stream."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.operators import updates
from levelindex.operators.build import LeveledIndex


def changes_of(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Rows of vec_id, vec, ts, user_id become one change for each event; late repeats fall to the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["vec_id"]).select(F.lit("insert").alias("op"), "vec_id", "vec", "ts")


def replay(stream: DataFrame, start: LeveledIndex, where: str, checkpoint: str, most: int = 40, least: int = 2) -> LeveledIndex:
    """Apply a stream to an index: each batch writes a version with the partitions it touched, in a folder
    named by its id, so a repeated batch writes the same version again."""
    spark = start.spark
    done = {-1: start}

    def apply(batch: DataFrame, batch_id: int) -> None:
        before = done.get(batch_id - 1) or LeveledIndex.load(spark, f"{where}/batch={batch_id - 1}")
        path = f"{where}/batch={batch_id}"
        latest = scratch.save(updates.last_change(batch.select("op", "vec_id", "vec", "ts")), "latest")
        adds = latest.where("op = 'insert'").select("vec_id", "vec")
        done[batch_id] = updates.maintain(before, adds, latest.where("op = 'delete'").select("vec_id"), most, least, path=path)

    query = stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return done[max(done)]


def windowed_load(events: DataFrame, size: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Events and summed value by tumbling window and type."""
    w = F.window("ts", size)
    return events.withWatermark("ts", watermark).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def run_to_table(stream: DataFrame, keys: list[str]) -> DataFrame:
    """Run an aggregating stream over what is there; the last state of each key, windows still open included."""
    spark = stream.sparkSession
    out, check = scratch.path(spark, "stream"), scratch.path(spark, "stream-state")

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", check).outputMode("update").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(out)
    rest = [c for c in rows.columns if c not in (*keys, "batch")]
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last"))
    return last.select(*keys, *[F.col("last").getField(c).alias(c) for c in rest])
