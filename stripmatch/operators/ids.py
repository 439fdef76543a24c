"""Dense, deterministic ids, and the ways to know the largest one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def assign_ids(df: DataFrame, start: int, order: list[str], name: str = "object_id", block: int = 65536) -> DataFrame:
    """Add ids start, start + 1, ... in the order of some columns, the first a number: by its blocks, offsets over their counts, a row number within.

    The same rows get the same ids on every run, what sorts first has the smaller id, and no task sees all rows.
    """
    b = df.withColumn("_b", F.floor(F.col(order[0]) / block))
    running = Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offset = b.groupBy("_b").agg(F.count(F.lit(1)).alias("_n")).withColumn("_o", F.coalesce(F.sum("_n").over(running), F.lit(0))).drop("_n")
    nth = F.row_number().over(Window.partitionBy("_b").orderBy(*order))
    return b.join(F.broadcast(offset), "_b").withColumn(name, (F.lit(start) + F.col("_o") + nth - 1).cast("long")).drop("_b", "_o")


def max_id_scan(df: DataFrame, column: str) -> DataFrame:
    """The largest id by reading the column: linear in the table."""
    return df.agg(F.max(column).alias("max_id"))


def max_id_footer(spark: SparkSession, path: str, column: str) -> DataFrame:
    """The largest id from the files' footers (aggregate push-down of the v2 reader): linear in files, not rows.

    The v2 reader is chosen per session, so a child session with its own settings reads here.
    """
    own = spark.newSession()
    own.conf.set("spark.sql.sources.useV1SourceList", "")
    own.conf.set("spark.sql.parquet.aggregatePushdown", "true")
    return own.read.parquet(path).agg(F.max(column).alias("max_id"))


class IdCounter:
    """The application's own counter, kept in the catalogue's manifest: no table is read."""

    def __init__(self, value: int = 0):
        self.value = value

    def take(self, n: int) -> int:
        first, self.value = self.value, self.value + n
        return first
