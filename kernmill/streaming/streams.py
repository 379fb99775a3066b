"""Streams: scoring with a frozen model, windowed features, late data, repeats, drift, refresh."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import materialize, shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, schema: str = EVENTS, files_per_trigger: int = 1) -> DataFrame:
    """A file stream; event time becomes a timestamp, as watermarks need one."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in raw.columns else raw


def score(points: DataFrame, model, id_col: str = "idx") -> DataFrame:
    """Labels of an unbounded stream of points."""
    return model.assign(points, id_col)


def windowed(events: DataFrame, kind: str = "tumbling", late: str = "2 hours") -> DataFrame:
    """(start, end, event_type, n, total) by tumbling or sliding hours, or by sessions of a user: (start, end, user_id, n, total)."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    frame = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "30 minutes")}[kind]
    by = "user_id" if kind == "session" else "event_type"
    got = marked.groupBy(frame.alias("w"), by).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n", "total")


def without_repeats(events: DataFrame, late: str = "2 hours") -> DataFrame:
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drift(scored: DataFrame, far: float, late: str = "2 hours", every: str = "1 hour") -> DataFrame:
    """Per window and cluster: members, mean distance and the share beyond ``far``; ``scored`` has ts, cl, sq_distance."""
    marked = scored.withWatermark("ts", late) if scored.isStreaming else scored
    got = marked.groupBy(F.window("ts", every).alias("w"), "cl").agg(F.count("*").alias("n"), F.avg("sq_distance").alias("mean_sq"), F.avg(F.when(F.col("sq_distance") > far, 1.0).otherwise(0.0)).alias("far_share"))
    return got.select(F.col("w.start").alias("start"), "cl", "n", "mean_sq", "far_share")


def with_dimension(events: DataFrame, dimension: DataFrame, on: str) -> DataFrame:
    """Stream-static join."""
    return events.join(dimension, on, "left")


def paired(left: DataFrame, right: DataFrame, on: str, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: ``right`` up to ``within`` after ``left``; both need ts."""
    a = left.withWatermark("ts", late).select(F.col(on).alias("a_key"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = right.withWatermark("ts", late).select(F.col(on).alias("b_key"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return a.join(b, F.expr(f"a_key = b_key AND b_ts >= a_ts AND b_ts <= a_ts + interval {within}"))


def refresh(points: DataFrame, refit, buffer_rows: int, path: str, checkpoint: str):
    """Refit on each batch's newest ``buffer_rows`` points and publish the model under ``path``; the returned query runs until stopped."""

    def publish(batch: DataFrame, epoch: int) -> None:
        newest = batch.orderBy(F.desc("idx")).limit(buffer_rows)
        if newest.limit(1).count():
            refit(newest).save(path)

    return points.writeStream.foreachBatch(publish).option("checkpointLocation", checkpoint).start()


def run_available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return its rows as a staged table; the last window closes only once the watermark passes it."""
    import uuid

    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode("append").start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")
    held: list[DataFrame] = []

    def last(batch: DataFrame, epoch: int) -> None:
        held[:] = [materialize(batch)]

    query = stream.writeStream.foreachBatch(last).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode(mode).start()
    query.awaitTermination()
    return held[0] if held else spark.createDataFrame([], stream.schema)
