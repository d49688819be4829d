"""Transactions and joins over event streams, as functions from streaming to streaming DataFrames."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.sources.files import save_results

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, folder: str, pattern: str = "events*.parquet") -> DataFrame:
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).parquet(folder)


def points(events: DataFrame, watermark: str = "1 day") -> DataFrame:
    """ts, event_id, user_id, feature, gi, gj, p: events as unit buffers seen from their own nearest grid point."""
    k = F.get_json_object("props", "$.k").cast("double")
    rows = events.withWatermark("ts", watermark).where("value < 100")
    gi = F.round("value").cast("long")
    d = F.abs(F.col("value") - gi)
    return rows.select("ts", "event_id", "user_id", F.col("event_type").alias("feature"), gi.alias("gi"), k.cast("long").alias("gj"), (F.cos(F.pi() * d) / 2 + 0.5).alias("p"))


def tumbling(pts: DataFrame, size: str = "1 day") -> DataFrame:
    """Largest probability per window, point and feature."""
    return pts.groupBy(F.window("ts", size).alias("w"), "gi", "gj", "feature").agg(F.max("p").alias("p"))


def sliding(pts: DataFrame, size: str = "7 days", step: str = "1 day") -> DataFrame:
    return pts.groupBy(F.window("ts", size, step).alias("w"), "feature").agg(F.count(F.lit(1)).alias("n"), F.sum("p").alias("sum_p"))


def sessions(pts: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Bursts of a user, the raw material of line objects."""
    return pts.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def with_radii(pts: DataFrame, radii: DataFrame) -> DataFrame:
    """Stream-static join: a bounded table of radii by feature."""
    return pts.join(F.broadcast(radii), "feature")


def close_pairs(pts: DataFrame, one: str, two: str, within: str = "6 hours") -> DataFrame:
    """Stream-stream join: events of two types at one user within a time of each other; state is bounded by both watermarks."""
    a = pts.where(F.col("feature") == one).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"))
    b = pts.where(F.col("feature") == two).select(F.col("event_id").alias("b"), F.col("user_id").alias("user_b"), F.col("ts").alias("tb"))
    return a.join(b, (F.col("user_id") == F.col("user_b")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"INTERVAL {within}"))).select("a", "b")


def deduplicated(pts: DataFrame) -> DataFrame:
    return pts.dropDuplicatesWithinWatermark(["event_id"])


def drained(stream: DataFrame, mode: str, checkpoint: str) -> DataFrame:
    """All that the source has now, through the stream into a table beside the checkpoint: each batch its own folder, so a repeated one
    replaces itself; in mode complete the last one only."""
    spark, path = stream.sparkSession, f"{checkpoint}-rows"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={0 if mode == 'complete' else number}")

    spark.createDataFrame([], stream.schema).write.mode("overwrite").parquet(f"{path}/batch=0")
    stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(f"{_ddl(stream)}, batch int").parquet(path).drop("batch")


def late_rows(run) -> int:
    """Rows that a stream's query has dropped behind its watermark so far."""
    return sum(op["numRowsDroppedByWatermark"] for p in run.recentProgress for op in p["stateOperators"])


def retested(objects: DataFrame, mine: Callable[[DataFrame], DataFrame], folder: str, results: str, checkpoint: str):
    """Query that adds each batch's objects to a table in `folder` and mines all of them again; a batch that is repeated replaces itself, in
    the objects and in the results, which are kept by batch."""

    def again(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(folder)
        held = batch.sparkSession.read.schema(f"{_ddl(objects)}, batch int").parquet(folder)
        save_results(mine(held.where(F.col("batch") <= number).drop("batch")), results, str(number))

    return objects.writeStream.foreachBatch(again).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
