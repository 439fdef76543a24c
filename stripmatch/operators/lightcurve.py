"""Light curves: appending, reading, statistics and simple variability indices."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType
from pyspark.sql.window import Window

from stripmatch.functions import sky
from stripmatch.operators import match

from stripmatch.schema import LIGHTCURVE, conform


def points(resolved: DataFrame, sources: DataFrame) -> DataFrame:
    """Light-curve rows of resolved pairs."""
    return conform(resolved.select("object_id", "source_id", "sep_arcsec", "topology").join(sources.select("source_id", "image_id", "mjd", "flux", "flux_err"), "source_id"), LIGHTCURVE)


def with_strip(curve: DataFrame, sources: DataFrame, width: float = 1.0) -> DataFrame:
    """curve with the strip of each row's source."""
    return curve.join(sources.select("source_id", sky.strip_of("dec_deg", width).alias("strip")), "source_id").select(*curve.columns, "strip")


def append(curve: DataFrame, target: str, image_id: int) -> None:
    """Write the rows that an image adds to the light-curve table, by image and strip; a replay replaces its own rows."""
    curve.repartition("strip").sortWithinPartitions("strip", "object_id").write.mode("overwrite").partitionBy("strip").parquet(f"{target}/added={image_id}")


def table(spark: SparkSession, target: str) -> DataFrame:
    """The light-curve table: its partition columns are the image that added a row and the strip of the row's source."""
    return spark.read.schema(StructType([*LIGHTCURVE.fields, StructField("added", IntegerType()), StructField("strip", IntegerType())])).parquet(target)


def compact(spark: SparkSession, target: str, to: str) -> None:
    """Rewrite the table without its many small files, sorted by object within each strip."""
    table(spark, target).repartition("strip").sortWithinPartitions("strip", "object_id", "mjd").write.mode("overwrite").partitionBy("strip").parquet(to)


def of_cone(curve: DataFrame, objects: DataFrame, ra: float, dec: float, r_deg: float, width: float = 1.0) -> DataFrame:
    """The light curves of objects within r of a centre; the table's strips next to the cone are read (a source may lie in the strip beside its object's)."""
    found = match.cone_search(objects, ra, dec, r_deg).select("object_id")
    low, high = math.floor((dec - r_deg) / width) - 1, math.floor((dec + r_deg) / width) + 1
    near = curve.where(F.col("strip").between(low, high)) if "strip" in curve.columns else curve
    return near.join(found, "object_id", "left_semi")


def of_box(curve: DataFrame, objects: DataFrame, ra: tuple[float, float], dec: tuple[float, float], width: float = 1.0) -> DataFrame:
    """The light curves of objects in a box; ra goes east from its first value, through 0 if need be."""
    inside = (F.pmod(F.col("ra_deg") - ra[0], F.lit(360.0)) <= (ra[1] - ra[0]) % 360.0) & F.col("dec_deg").between(*dec)
    near = curve.where(F.col("strip").between(math.floor(dec[0] / width) - 1, math.floor(dec[1] / width) + 1)) if "strip" in curve.columns else curve
    return near.join(objects.where(inside).select("object_id"), "object_id", "left_semi")


def lightcurve_of(curve: DataFrame, ids: list[int]) -> DataFrame:
    """The light curves of some objects, in time order."""
    return curve.where(F.col("object_id").isin(ids)).orderBy("object_id", "mjd", "source_id")


def folded(curve: DataFrame) -> DataFrame:
    """One row per object: its points, in time order, as an array."""
    return curve.groupBy("object_id").agg(F.array_sort(F.collect_list(F.struct("mjd", "flux"))).alias("points"))


def statistics(curve: DataFrame) -> DataFrame:
    """n, span, mean, scatter, scatter over mean, and weighted reduced chi-square of each object."""
    w = 1 / (F.col("flux_err") * F.col("flux_err"))
    agg = curve.groupBy("object_id").agg(
        F.count(F.lit(1)).alias("n"), F.min("mjd").alias("mjd_min"), F.max("mjd").alias("mjd_max"), F.avg("flux").alias("mean_flux"), F.stddev_samp("flux").alias("sd_flux"),
        F.sum(w).alias("sw"), F.sum(w * F.col("flux")).alias("swf"), F.sum(w * F.col("flux") * F.col("flux")).alias("swff"))
    chi = F.when(F.col("n") > 1, (F.col("swff") - F.col("swf") * F.col("swf") / F.col("sw")) / (F.col("n") - 1))
    return agg.select("object_id", "n", "mjd_min", "mjd_max", "mean_flux", "sd_flux", (F.col("sd_flux") / F.col("mean_flux")).alias("scatter"), chi.alias("chi2"))


def variability(curve: DataFrame, scatter: float = 0.5, least: int = 5) -> DataFrame:
    """Objects whose scatter over mean flux is beyond a bound, with enough points."""
    return statistics(curve).where((F.col("n") >= least) & (F.col("scatter") > scatter))


def previous(curve: DataFrame) -> DataFrame:
    """As-of: each point with the object's detection before it, the gap, and the change of flux."""
    w = Window.partitionBy("object_id").orderBy("mjd", "source_id")
    return curve.withColumn("prev_source_id", F.lag("source_id").over(w)).withColumn("gap_days", F.col("mjd") - F.lag("mjd").over(w)).withColumn("flux_change", F.col("flux") - F.lag("flux").over(w))
