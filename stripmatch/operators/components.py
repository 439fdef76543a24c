"""Connected components of an edge table, by hooking to the smallest neighbour and contracting."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import written


def _flat(hook: DataFrame) -> DataFrame:
    """hook (b, to) with every `to` a node that hooks nowhere: doubling steps."""
    while True:
        onward = hook.select(F.col("b").alias("via"), F.col("to").alias("end"))
        if hook.join(onward, hook["to"] == onward["via"], "left_semi").isEmpty():
            return hook
        hook = written(hook.join(onward, hook["to"] == onward["via"], "left").select("b", F.coalesce("end", "to").alias("to")), "hooks")


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest node that each node of an edge table can reach.

    Every round, each node with a smaller neighbour hooks to the smallest one (a minimum, combined before the shuffle,
    so that a hub is no hot key), chains of hooks are cut short by pointer jumping, edges are rewritten between their
    ends and those inside one node go. So a chain takes logarithmically many steps. Nulls and loops
    are left out; an empty table gives an empty one. Nothing but counts comes to the driver.
    """
    pair = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    live = written(pair.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).distinct(), "edges")
    labels = live.select(F.col("a").alias("node")).union(live.select("b")).distinct().withColumn("component", F.col("node"))
    for _ in range(most_rounds):
        if live.isEmpty():
            return labels
        hook = _flat(written(live.groupBy("b").agg(F.min("a").alias("to")), "hooks"))
        labels = written(labels.join(hook, labels["component"] == hook["b"], "left").select("node", F.coalesce("to", "component").alias("component")), "labels")
        left = hook.select(F.col("b").alias("ka"), F.col("to").alias("ta"))
        right = hook.select(F.col("b").alias("kb"), F.col("to").alias("tb"))
        moved = live.join(left, live["a"] == left["ka"], "left").join(right, F.col("b") == right["kb"]).select(F.coalesce("ta", "a").alias("x"), F.col("tb").alias("y"))
        live = written(moved.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "edges")
    raise RuntimeError("components did not settle")
