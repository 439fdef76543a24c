"""Run logs and the measures over them. A log has run_id, image_id, step, query, seconds, rows_out, rows_scanned, n_database."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stripmatch.schema import QUERY_LOG


class QueryLog:
    """Wall time per query per image, held by the driver (a row per query)."""

    def __init__(self, run_id: str, count: bool = True):
        self.run_id, self.rows, self.count = run_id, [], count

    def record(self, step: str, query: str, image_id: int, seconds: float, rows_out: int = 0, rows_scanned: int = 0, n_database: int = 0) -> None:
        self.rows.append((self.run_id, image_id, step, query, float(seconds), int(rows_out), int(rows_scanned), int(n_database)))

    def timed(self, step: str, query: str, image_id: int, call, **more):
        began = time.perf_counter()
        out = call()
        seconds = time.perf_counter() - began
        rows = out if isinstance(out, int) else out.count() if self.count and isinstance(out, DataFrame) else 0  # a written table's: from its footers
        self.record(step, query, image_id, seconds, rows_out=rows, **more)
        return out

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, QUERY_LOG)


def per_image(log: DataFrame) -> DataFrame:
    """Summed time of a module per image."""
    return log.groupBy("run_id", "image_id").agg(F.sum("seconds").alias("seconds"), F.max("n_database").alias("n_database"))


def accumulated(log: DataFrame) -> DataFrame:
    """Running sum of time over the image sequence, per query."""
    one = log.groupBy("run_id", "query", "image_id").agg(F.sum("seconds").alias("seconds"))
    return one.withColumn("accumulated", F.sum("seconds").over(Window.partitionBy("run_id", "query").orderBy("image_id").rowsBetween(Window.unboundedPreceding, 0)))


def instantaneous(log: DataFrame) -> DataFrame:
    """Time against database size, per query and image."""
    return log.groupBy("run_id", "query", "image_id").agg(F.sum("seconds").alias("seconds"), F.max("n_database").alias("n_database"))


def banded(log: DataFrame, edges: list[int]) -> DataFrame:
    """Mean time and rows in bands of the image sequence."""
    band = F.lit(0)
    for e in edges:
        band = band + F.when(F.col("image_id") >= e, 1).otherwise(0)
    return log.groupBy("run_id", "query", band.alias("band")).agg(F.avg("seconds").alias("seconds"), F.avg("rows_out").alias("rows_out"), F.count(F.lit(1)).alias("n"))


def growth(log: DataFrame) -> DataFrame:
    return log.groupBy("run_id", "image_id").agg(F.max("n_database").alias("n_database"))


def _power(y: Column, x: Column) -> Column:
    return F.regr_slope(F.ln(y), F.ln(x))


def scaling_class(log: DataFrame, flat: float = 0.2, linear: float = 0.8) -> DataFrame:
    """Per query: log-log slopes of time on database size and on result rows, the linear fit, and the class they mean."""
    good = log.where("seconds > 0 AND n_database > 0")
    rows = F.greatest(F.col("rows_out"), F.lit(1)).cast("double")
    s = good.groupBy("run_id", "query").agg(
        _power(F.col("seconds"), F.col("n_database").cast("double")).alias("slope_n"), _power(F.col("seconds"), rows).alias("slope_rows"), F.regr_slope("seconds", F.col("n_database").cast("double")).alias("per_row"),
        F.regr_intercept("seconds", F.col("n_database").cast("double")).alias("intercept"), F.regr_r2("seconds", F.col("n_database").cast("double")).alias("r2"), F.regr_r2("seconds", rows).alias("r2_rows"))
    kind = F.when(F.col("slope_n") < flat, F.when((F.coalesce("slope_rows", F.lit(0.0)) > linear) & (F.col("r2_rows") > 0.5), "linear in rows").otherwise("constant")).when(F.col("slope_n") < linear, "sublinear").when(F.col("slope_n") <= 1.25, "linear in N").otherwise("N times M")
    return s.withColumn("class", kind)


def linear_share(classes: DataFrame) -> DataFrame:
    """Share of the queries that are linear in the database or worse."""
    return classes.groupBy("run_id").agg(F.avg(F.when(F.col("class").isin("linear in N", "N times M"), 1.0).otherwise(0.0)).alias("linear_share"))


def totals(log: DataFrame, pipeline_seconds: float) -> DataFrame:
    """Pipeline time, query time and their difference (commits and other overhead)."""
    return log.groupBy("run_id").agg(F.sum("seconds").alias("query_seconds")).withColumn("pipeline_seconds", F.lit(float(pipeline_seconds))).withColumn("overhead_seconds", F.col("pipeline_seconds") - F.col("query_seconds"))


def speedup(log: DataFrame, slow: str, fast: str) -> DataFrame:
    """Per step, how many times faster one run is than another."""
    p = log.groupBy("step").pivot("run_id", [slow, fast]).agg(F.sum("seconds"))
    return p.select("step", F.col(f"`{slow}`").alias("slow"), F.col(f"`{fast}`").alias("fast"), F.try_divide(F.col(f"`{slow}`"), F.col(f"`{fast}`")).alias("speedup"))


def cadence_report(log: DataFrame, cadence: float) -> DataFrame:
    """Slowest and mean seconds per image, and whether each keeps up with the cadence."""
    return per_image(log).groupBy("run_id").agg(F.max("seconds").alias("limiting_cadence"), F.avg("seconds").alias("mean_seconds")).withColumn("keeps_up", F.col("limiting_cadence") <= cadence).withColumn("average_keeps_up", F.col("mean_seconds") <= cadence)


def backlog(log: DataFrame, cadence: float) -> DataFrame:
    """Waiting time after each image if images come every `cadence` seconds: S minus the running minimum of S and 0."""
    w = Window.partitionBy("run_id").orderBy("image_id").rowsBetween(Window.unboundedPreceding, 0)
    s = per_image(log).withColumn("s", F.sum(F.col("seconds") - cadence).over(w))
    return s.withColumn("waiting", F.col("s") - F.least(F.min("s").over(w), F.lit(0.0))).drop("s")


def spread(log: DataFrame) -> DataFrame:
    """Scatter of a query's time."""
    return log.groupBy("run_id", "query").agg(F.avg("seconds").alias("mean"), F.stddev_samp("seconds").alias("sd"), F.percentile("seconds", F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9))).alias("p10_p50_p90"))


def time_to_cadence(classes: DataFrame, cadence: float) -> DataFrame:
    """Database size at which a growing query's linear fit reaches the cadence."""
    return classes.select("run_id", "query", F.when(F.col("per_row") > 0, (F.lit(float(cadence)) - F.col("intercept")) / F.col("per_row")).alias("rows_at_cadence"))


def capacity(spark: SparkSession, bytes_per_source: int = 402, sources_per_image: int = 170_000, modes=(("nominal", 120), ("fast", 600))) -> DataFrame:
    """Sources and GB a night of each observing mode."""
    rows = spark.createDataFrame(list(modes), "mode string, images_per_night long")
    n = F.col("images_per_night") * sources_per_image
    return rows.select("mode", "images_per_night", n.alias("sources_per_night"), (n * bytes_per_source / F.lit(1e9)).alias("gb_per_night"))
