"""Association: topologies of candidate pairs, and how they are resolved. The first word is the catalogue's side."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stripmatch.operators.components import connected_components
from stripmatch.operators.ids import assign_ids


def topology() -> Column:
    """The name of what the degrees say."""
    return F.when((F.col("objects") == 1) & (F.col("sources") == 1), "one-to-one").when(F.col("objects") == 1, "one-to-many").when(F.col("sources") == 1, "many-to-one").otherwise("many-to-many")


def classify(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """pairs with the degrees of both sides and the topology. by: columns that tell lists apart (image_id) where pairs has several."""
    d = pairs.withColumn("sources", F.count(F.lit(1)).over(Window.partitionBy(*by, "object_id")))  # first, so that what resolve does by source needs no third shuffle
    d = d.withColumn("objects", F.count(F.lit(1)).over(Window.partitionBy(*by, "source_id"))).select(*pairs.columns, "objects", "sources")
    return d.withColumn("topology", topology())


def nearest(pairs: DataFrame, k: int = 1) -> DataFrame:
    """Each source's k nearest objects; ties by the smaller id."""
    w = Window.partitionBy("source_id").orderBy("sep_arcsec", "object_id")
    return pairs.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= k).drop("_n")


def mutual_nearest(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Pairs that are nearest from both sides."""
    other = Window.partitionBy(*by, "object_id").orderBy("sep_arcsec", "source_id")
    own = Window.partitionBy(*by, "source_id").orderBy("sep_arcsec", "object_id")
    return pairs.withColumn("_a", F.row_number().over(own)).withColumn("_b", F.row_number().over(other)).where("_a = 1 AND _b = 1").drop("_a", "_b")


def resolve(pairs: DataFrame, policy: str = "nearest", by: tuple[str, ...] = ()) -> DataFrame:
    """What is appended to light curves, with the final topology.

    nearest: in many-to-many groups each source keeps its nearest object, then all is classified again. mutual_nearest:
    only mutually nearest pairs. all: nothing is reduced.
    """
    if policy == "all":
        return classify(pairs, by)
    if policy == "mutual_nearest":
        return classify(mutual_nearest(pairs, by).select(*by, "object_id", "source_id", "sep_arcsec"), by)
    if policy != "nearest":
        raise ValueError(policy)
    c = classify(pairs, by)
    w = Window.partitionBy(*by, "source_id").orderBy("sep_arcsec", "object_id")
    kept = c.withColumn("_n", F.row_number().over(w)).where("topology <> 'many-to-many' OR _n = 1")
    return classify(kept.select(*by, "object_id", "source_id", "sep_arcsec"), by)


def fork(resolved: DataFrame, start: int) -> DataFrame:
    """The children that one-to-many pairs found instead of being merged: object_id (dense from start), parent_id, source_id, sep_arcsec."""
    many = resolved.where("topology = 'one-to-many'").select(F.col("object_id").alias("parent_id"), "source_id", "sep_arcsec")
    return assign_ids(many, start, ["parent_id", "source_id"])


def fork_objects(objects: DataFrame, children: DataFrame) -> DataFrame:
    """objects with parents set inactive, and a copy of its parent's row for each child."""
    parents = children.select(F.col("parent_id").alias("_p")).distinct()
    old = objects.join(parents, objects["object_id"] == F.col("_p"), "left").withColumn("active", F.col("active") & F.col("_p").isNull()).select(*objects.columns)
    own = objects.withColumnRenamed("object_id", "parent_id").where("active").join(children.select("object_id", "parent_id"), "parent_id")
    return old.unionByName(own.select(*objects.columns))


def fork_history(curve: DataFrame, children: DataFrame) -> DataFrame:
    """The light-curve rows that children inherit: each one a copy of its parent's history."""
    return curve.withColumnRenamed("object_id", "parent_id").join(children.select("object_id", "parent_id"), "parent_id").select(*curve.columns)


def unmatched_sources(sources: DataFrame, pairs: DataFrame) -> DataFrame:
    """Sources without a counterpart: they become objects."""
    return sources.join(pairs, "source_id", "left_anti")


def missed_objects(objects: DataFrame, pairs: DataFrame, sources: DataFrame, width: float = 1.0, cell: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """Objects in the image's footprint (the zone cells that hold its sources) that were not seen."""
    at = lambda df: df.withColumn("zone", F.floor(F.col("dec_deg") / width)).withColumn("cell", F.floor(F.pmod(F.col("ra_deg"), F.lit(360.0)) / cell))
    footprint = at(sources).select(*by, "zone", "cell").distinct()
    return at(objects).join(footprint, ["zone", "cell"], "inner" if by else "left_semi").drop("zone", "cell").join(pairs, [*by, "object_id"], "left_anti")


def candidates(objects: DataFrame, pairs: DataFrame, sources: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """What may be new or gone: kind, and the source or the object."""
    new = unmatched_sources(sources, pairs.drop(*by)).select(*by, F.lit("new").alias("kind"), "source_id", F.lit(None).cast("long").alias("object_id"))
    gone = missed_objects(objects, pairs, sources, by=by).select(*by, F.lit("gone").alias("kind"), F.lit(None).cast("long").alias("source_id"), "object_id")
    return new.unionByName(gone)


def topology_groups(pairs: DataFrame, by: str | None = None) -> DataFrame:
    """pairs with the connected group that they belong to (objects and sources are nodes of one graph), named by its smallest object.

    by: the column that tells lists apart; an object is then a node of each list's graph, and a group is named by list and smallest object.
    """
    if by:
        ends = pairs.groupBy(by, "object_id").agg(F.min("source_id").alias("own"))  # source ids are unique over lists
        edges = pairs.join(ends, [by, "object_id"]).select(F.col("own").alias("a"), F.col("source_id").alias("b"))
        labels = connected_components(edges).withColumnRenamed("node", "source_id")
        named = pairs.join(labels, "source_id", "left").withColumn("component", F.coalesce("component", "source_id"))
        return named.withColumn("group_id", F.min("object_id").over(Window.partitionBy(by, "component"))).select(*pairs.columns, "group_id")
    nodes = pairs.select((F.col("object_id") * 2).alias("a"), (F.col("source_id") * 2 + 1).alias("b"))
    labels = connected_components(nodes)
    known = labels.withColumn("object_id", F.expr("node div 2")).where("node % 2 = 0")
    named = known.join(known.groupBy("component").agg(F.min("object_id").alias("group_id")), "component")
    return pairs.join(named.select("object_id", "group_id"), "object_id")
