"""Sky objects, detections and exposures on the given star-schema tables (integer milliarcseconds until the last step)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stripmatch.cluster import read_table, shuffle_parts
from stripmatch.functions.sky import with_position

DETECTION_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]


def position_mas(k: Column) -> tuple[Column, Column, Column]:
    """(ra, dec, amp) of a key, in milliarcseconds."""
    k = k.cast("long")
    b = F.when(k % 10 == 1, k - 1).otherwise(k)
    polar, origin, edge = b % 40 == 7, b % 20 == 3, b % 20 == 13
    ra = F.when(polar, (b * 7919) % 1_296_000 * 1000).when(origin, F.lit(0)).otherwise((((b * 7919) % 7200) * 1000 + 1_292_400_000) % 1_296_000_000)
    dec = F.when(polar, 324_000_000 - (1 + (b * 104_729) % 3600) * 1000).when(edge, ((b * 7) % 5 - 2) * 3_600_000).otherwise((b * 104_729) % 21_600 * 1000 - 10_800_000)
    return ra.cast("long"), (dec + F.when(k % 10 == 1, 1200).otherwise(0)).cast("long"), F.when(polar, 50).otherwise(1).cast("long")


def degrees_of(mas: Column) -> Column:
    return mas.cast("double") / F.lit(3.6e6)


def objects(spark: SparkSession, sf_dir: str, table: str = "part", key: str = "p_partkey", shift_mas: int = 0, holes: bool = False) -> DataFrame:
    """The static catalogue: object_id, ra_deg, dec_deg, x, y, z, strip."""
    df = read_table(spark, sf_dir, table).select(F.col(key).alias("object_id"))
    df = df.where("object_id % 7 <> 0") if holes else df
    ra, dec, _ = position_mas(F.col("object_id"))
    return with_position(df.select("object_id", degrees_of(ra).alias("ra_deg"), degrees_of(F.least(dec + shift_mas, F.lit(324_000_000))).alias("dec_deg")), libm=True)


def image_of(ts: Column) -> Column:
    return ((F.year(ts) - 1995) * 12 + F.month(ts) - 1).cast("int")


def detections(spark: SparkSession, sf_dir: str, image: int | None = None) -> DataFrame:
    """All detections, or one image's, with dense ids: an offset per day plus the order within it."""
    li = read_table(spark, sf_dir, "lineitem").withColumn("image_id", image_of(F.col("l_shipdate"))).withColumn("_day", F.to_date("l_shipdate"))
    first = li.groupBy("_day").agg(F.count(F.lit(1)).alias("n")).where("_day IS NOT NULL").withColumn("offset", F.coalesce(F.sum("n").over(Window.orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))  # a row per day
    if image is not None:
        li = li.where(F.col("image_id") == image)
    li = li.join(F.broadcast(first.select("_day", "offset")), "_day")
    nth = F.row_number().over(Window.partitionBy("_day", "image_id").orderBy(*DETECTION_ORDER))  # a day has one image: choosing images later passes through
    ra, dec, amp = position_mas(F.col("l_partkey"))
    key, line = F.col("l_orderkey").cast("long"), F.col("l_linenumber").cast("long")
    ra = (ra + amp * ((key * 37 + line * 101) % 1201 - 600) + 1_296_000_000) % 1_296_000_000
    dec = F.least(dec + (key * 53 + line * 211) % 1201 - 600, F.lit(324_000_000))
    out = li.select(
        "image_id", (F.col("offset") + nth - 1).cast("long").alias("source_id"), degrees_of(ra).alias("ra_deg"), degrees_of(dec).alias("dec_deg"),
        (F.lit(49718.0) + F.datediff(F.col("l_shipdate"), F.lit("1995-01-01").cast("date"))).alias("mjd"), F.col("l_extendedprice").alias("flux"), (1 + F.lit(0.01) * F.col("l_extendedprice")).alias("flux_err"),
        F.col("l_discount").alias("ellipticity"), F.col("l_quantity").alias("area"), F.col("l_linestatus").alias("band"), F.col("l_returnflag").alias("quality"), F.col("l_partkey").alias("true_object"), (F.lit(0.5) + F.col("l_quantity") / F.lit(50.0)).alias("r_arcsec"))
    if image is not None:  # numbered by few tasks, used by all
        out = out.repartition(max(shuffle_parts(spark), spark.sparkContext.defaultParallelism), "source_id")
    return with_position(out, libm=True)


def known_objects(spark: SparkSession, sf_dir: str, last: int) -> DataFrame:
    """The static catalogue of those objects that images up to last have seen: what is first seen later is missing from it."""
    seen = read_table(spark, sf_dir, "lineitem").where(image_of(F.col("l_shipdate")) <= last).select(F.col("l_partkey").alias("object_id")).distinct()
    return objects(spark, sf_dir).join(seen, "object_id", "left_semi")


def exposures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One header row of fifteen fields per image, with attributes of the month's orders."""
    li = read_table(spark, sf_dir, "lineitem").select(image_of(F.col("l_shipdate")).alias("image_id"), "l_partkey", "l_linestatus", "l_returnflag", "l_quantity", "l_extendedprice", "l_discount", (F.lit(49718.0) + F.datediff(F.col("l_shipdate"), F.lit("1995-01-01").cast("date"))).alias("mjd"))
    o = read_table(spark, sf_dir, "orders").select(image_of(F.col("o_orderdate")).alias("image_id"), "o_orderkey", "o_orderpriority", "o_totalprice")
    seen = li.groupBy("image_id").agg(F.min("mjd").alias("mjd_min"), F.max("mjd").alias("mjd_max"), F.count(F.lit(1)).alias("n_sources"),
        F.count_distinct("l_partkey").alias("n_objects"), F.count_if(F.col("l_linestatus") == "F").alias("n_finished"), F.min("l_extendedprice").alias("flux_min"), F.max("l_extendedprice").alias("flux_max"),
        F.sum("l_quantity").alias("area_sum"), F.max("l_discount").alias("ellipticity_max"), F.min("l_returnflag").alias("first_quality"))
    told = o.groupBy("image_id").agg(F.min("o_orderpriority").alias("band"), F.round(F.avg("o_totalprice"), 2).alias("exptime"), F.count(F.lit(1)).alias("order_count"), F.max("o_orderkey").alias("last_order"))
    return seen.join(told, "image_id", "left")
