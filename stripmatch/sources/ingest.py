"""Attach, validate, load, header rows, clean-up; a row-wise loader as the comparator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import clean
from stripmatch.functions.sky import with_position
from stripmatch.schema import DETECTION, EXPOSURE, conform
from stripmatch.sources.fits_table import FitsTableSource


def attach(spark: SparkSession, path: str, format: str = "parquet", extensions: list[int] | None = None, **options) -> DataFrame:
    """A table that can be queried before it is loaded. Formats: fits_table, parquet, orc, csv, json, text, jdbc."""
    if format == "fits_table":
        spark.dataSource.register(FitsTableSource)
        options |= {"extensions": ",".join(map(str, extensions))} if extensions else {}
    return spark.read.format(format).options(**options).load(path)


def validate(rows: DataFrame, loaded: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(good, quarantine): positions in range and not null; ids present; not loaded already; one row per id."""
    fine = F.col("ra_deg").between(0.0, 360.0) & F.col("dec_deg").between(-90.0, 90.0) & F.col("image_id").isNotNull() & F.col("source_id").isNotNull()
    fine = F.coalesce(fine & ~F.isnan("ra_deg") & ~F.isnan("dec_deg"), F.lit(False))
    good = rows.where(fine).dropDuplicates(["image_id", "source_id"])
    if loaded is not None:
        good = good.join(loaded.select("image_id", "source_id"), ["image_id", "source_id"], "left_anti")
    return good, rows.where(~fine)


def append_detections(rows: DataFrame, target: str, width: float = 1.0) -> None:
    """Bulk append with derived columns, partitioned by strip and image, sorted by declination: one commit."""
    ready = with_position(conform(rows, DETECTION), width)
    ready.repartition("strip", "image_id").sortWithinPartitions("strip", "image_id", "dec_deg").write.mode("append").partitionBy("strip", "image_id").parquet(target)


def load_rowwise(rows: DataFrame, target: str) -> None:
    """Comparator only: every row goes through the driver."""
    rows.sparkSession.createDataFrame([tuple(x) for x in rows.collect()], rows.schema).write.mode("append").parquet(target)


def register_exposures(headers: DataFrame, target: str) -> None:
    """Many headers in one write, checked against the schema: a file per image would be as dear as a statement per image."""
    conform(headers, EXPOSURE).write.mode("append").parquet(target)


def cleanup(spark: SparkSession, views: list[str] = (), frames: list[DataFrame] = (), written: bool = False) -> None:
    """Drop the views and cached frames of a load, and all that operators have written to the shared folder if asked."""
    for v in views:
        spark.catalog.dropTempView(v)
    for f in frames:
        f.unpersist()
    if written:
        clean(spark)
