"""Source lists as a stream: file batches matched against the catalogue, and windows over live events."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from stripmatch.operators import match


def list_stream(spark: SparkSession, folder: str, schema: StructType, per_batch: int = 1) -> DataFrame:
    """New Parquet files of a folder, some per micro-batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(folder)


def match_stream(stream: DataFrame, objects: Callable[[], DataFrame], target: str, checkpoint: str, r: float = 1.0):
    """Match each micro-batch with the catalogue as it is then, and append the pairs; a replayed batch overwrites its own."""

    def each(batch: DataFrame, batch_id: int) -> None:
        match.match_zones(batch, objects(), r, 1 / 60, 1.0).write.mode("overwrite").parquet(f"{target}/batch={batch_id}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stream_static_match(stream: DataFrame, objects: DataFrame, r: float = 1.0, width: float = 1 / 60) -> DataFrame:
    """The same as one streaming plan: zones of the stream joined with a static catalogue."""
    left = match.prepared(stream, r).withColumn("zone", F.explode(match.sky.strips_touched("s_dec", F.col("r_deg"), width)))
    right = objects.select("object_id", "ra_deg", "dec_deg", "x", "y", "z").withColumn("zone", match.sky.strip_of("dec_deg", width))
    return match._pairs(left.join(right, "zone").where(match.in_box() & match._close("chord2")))


def timed(events: DataFrame, ts: str) -> DataFrame:
    """A stream's event time must be an instant; a table may keep its local timestamps."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")) if events.isStreaming else events


def counts_per_window(events: DataFrame, length: str = "1 hour", late: str = "1 hour", ts: str = "ts", slide: str | None = None) -> DataFrame:
    """Events per window; those later than the watermark are dropped. Works on streams and on tables alike."""
    events = timed(events, ts)
    return events.withWatermark(ts, late).groupBy(F.window(ts, length, slide)).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Runs of a user's events without a longer gap."""
    return timed(events, "ts").withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return timed(events, "ts").withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def split_late(events: DataFrame, late: str = "1 hour", ts: str = "ts", newest: str = "newest") -> tuple[DataFrame, DataFrame]:
    """(in time, late): by the newest event time that had come before each; the late ones are for a side table."""
    behind = F.col(ts) < F.col(newest) - F.expr(f"INTERVAL {late}")
    return events.where(~behind), events.where(behind)


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return what it wrote."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
