"""Association by place. Objects of one position have the same pairs, so lists against crowded catalogues are classified and
resolved on (place, source) pairs that weigh n objects each; ids come in at the end. A place goes by its smallest object.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stripmatch.functions import sky
from stripmatch.operators import associate, match


def pairs(sources: DataFrame, objects: DataFrame, keep: tuple[str, ...] = ("image_id",), r: float | str = 1.0) -> DataFrame:
    """keep, place, n, source_id, sep_arcsec."""
    return match.zone_join(sources, objects, r, match.FINE, match.CELL, keep=keep, by_place=True).select(*keep, "place", "n", "source_id", match.separation())


def count(sources: DataFrame, objects: DataFrame, r: float | str = 1.0, threshold: str = "chord2") -> int:
    """How many pairs of objects and sources there are."""
    return match.zone_join(sources, objects, r, match.FINE, match.CELL, threshold, by_place=True).agg(F.sum("n")).first()[0] or 0


def expand(found: DataFrame, objects: DataFrame) -> DataFrame:
    """found with object_id for place and n: a row for each object of a place, or for the place's first alone where n is 1."""
    several = match.places(objects).where("n > 1").select(F.col("place").alias("_p"), "held")
    size = objects.count()
    several = F.broadcast(several) if size <= 8 * match.SMALL_LIST else several
    joined = found.join(several, (F.col("place") == F.col("_p")) & (F.col("n") > 1), "left")
    return joined.withColumn("object_id", F.explode(F.coalesce("held", F.array("place")))).select(*["object_id" if c == "place" else c for c in found.columns if c != "n"])


def classify(found: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """As associate.classify: the degrees of both sides, counted in objects, and the topology."""
    d = found.withColumn("objects", F.sum("n").over(Window.partitionBy(*by, "source_id"))).withColumn("sources", F.count(F.lit(1)).over(Window.partitionBy(*by, "place")))
    return d.withColumn("topology", associate.topology())


def resolve(found: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """As associate.resolve by the nearest: in many-to-many groups a source keeps one object, the smallest of the nearest place.

    A place's pairs within a list are all reduced or, if it has one source only, all whole; so its objects stay alike.
    """
    nth = F.row_number().over(Window.partitionBy(*by, "source_id").orderBy("sep_arcsec", "place"))
    many = F.col("topology") == "many-to-many"
    kept = classify(found, by).withColumn("_nth", nth).where(~many | (F.col("_nth") == 1))
    return classify(kept.withColumn("n", F.when(many, F.lit(1).cast("long")).otherwise(F.col("n"))).select(found.columns), by)


def accuracy(sources: DataFrame, objects: DataFrame, truth: str, r: float | str = 1.0) -> DataFrame:
    """recall and purity of a list whose column truth names each source's object: as match.match_accuracy, in one pass."""
    joined = match.zone_join(sources, objects, r, match.FINE, match.CELL, keep=(truth,), by_place=True)
    found = joined.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_pairs"), F.count_if(F.array_contains("held", F.col(truth))).alias("n_hit"))
    both = found.crossJoin(sources.agg(F.count(F.lit(1)).alias("n_true")))
    return both.select("n_pairs", "n_true", "n_hit", (F.col("n_hit") / F.col("n_true")).alias("recall"), (F.col("n_hit") / F.col("n_pairs")).alias("purity"))


def topology_groups(found: DataFrame, by: str) -> DataFrame:
    """As associate.topology_groups: a group's smallest object is that of its smallest place."""
    return associate.topology_groups(found.withColumnRenamed("place", "object_id"), by).withColumnRenamed("object_id", "place")


def candidates(objects: DataFrame, found: DataFrame, sources: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """As associate.candidates; what is gone is found by place."""
    new = associate.unmatched_sources(sources, found.select("source_id")).select(*by, F.lit("new").alias("kind"), "source_id", F.lit(None).cast("long").alias("object_id"))
    as_object = lambda df: df.withColumnRenamed("place", "object_id")
    held = as_object(match.places(objects).select("place", "n", "ra_deg", "dec_deg"))
    gone = associate.missed_objects(held, as_object(found.select(*by, "place").distinct()), sources, by=by)
    gone = expand(gone.withColumnRenamed("object_id", "place").select(*by, "place", "n"), objects)
    return new.unionByName(gone.select(*by, F.lit("gone").alias("kind"), F.lit(None).cast("long").alias("source_id"), "object_id"))


def distance_forms(sources: DataFrame, objects: DataFrame) -> DataFrame:
    """n pairs, and whether the dot product errs by more than a thousandth of an arcsecond in one of them."""
    chord, dot = sky.sep_arcsec(sky.chord2("x", "y", "z", "sx", "sy", "sz")), sky.sep_dot("x", "y", "z", "sx", "sy", "sz")
    joined = match.zone_join(sources, objects, 1.0, match.FINE, match.CELL, by_place=True)
    return joined.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), (F.sum(F.when(F.abs(chord - dot) > 1e-3, 1).otherwise(0)) > 0).alias("dot_is_worse"))
