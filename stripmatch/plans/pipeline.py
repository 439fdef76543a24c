"""The image loop: ingest, match, resolve, append, update, commit; and waves of images that don't touch one another."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import note, scratch, shared_dir, shuffle_parts, written
from stripmatch.functions import sky
from stripmatch.operators import associate, catalog, lightcurve, match, replay
from stripmatch.operators.ids import assign_ids
from stripmatch.plans.metrics import QueryLog

LONG_LIST = 20_000  # sources that one task still matches

def step_image(cat: catalog.Catalog, sources: DataFrame, image_id: int, r: float = 1.0, mode: str = "strips", policy: str = "nearest", mean_mode: str = "vector", one_to_many: str = "merge", target: str | None = None, log: QueryLog | None = None) -> DataFrame:
    """One image against the catalogue, committed as its next version. Returns the image's light-curve rows, appended to target if named.

    mode strips reads only the cells that the list touches; baseline compares with the whole catalogue. one_to_many:
    merge gives all sources of an object to its light curve; fork founds an object for each, with the parent's history
    (read from target) and statistics, and sets the parent inactive.
    """
    log, ids = log or QueryLog("run", count=False), cat.ids
    size = ids.value
    near, listed = cat.touched(sources, r), sources.count()
    held = (cat.all() if mode == "baseline" else cat.cells(near)).where("active")
    held = held.withColumnsRenamed({"mean_ra_deg": "ra_deg", "mean_dec_deg": "dec_deg"})
    spread = sources.repartition(max(shuffle_parts(cat.spark), cat.spark.sparkContext.defaultParallelism), "source_id") if listed > LONG_LIST else sources  # a list is one file
    if mode == "baseline":
        find = lambda: match.match_baseline(spread, held, r, zones=listed * size > match.SCAN)
    else:
        find = lambda: match.match_zones(spread, held, r, match.FINE, match.CELL)
    pairs = log.timed("associate", "match", image_id, lambda: written(find(), "pairs"), n_database=size)
    resolved = log.timed("associate", "resolve", image_id, lambda: written(associate.resolve(pairs, policy), "resolved"), n_database=size)
    fresh = associate.unmatched_sources(sources, pairs if policy == "mutual_nearest" else resolved)  # the other policies keep a pair of every source that has one
    new = log.timed("associate", "new objects", image_id, lambda: written(catalog.new_objects(fresh, size, cat.width), "new"), n_database=size)
    ids.take(new.count())
    old, kept, inherited = cat.cells(near), resolved, None
    if one_to_many == "fork":
        children = written(associate.fork(resolved, ids.value), "children")
        ids.take(children.count())
        old = written(associate.fork_objects(old, children), "forked")
        moved_to = children.select(F.col("object_id").alias("child"), F.col("parent_id").alias("_p"), F.col("source_id").alias("_s"))
        kept = resolved.join(moved_to, (resolved["object_id"] == F.col("_p")) & (resolved["source_id"] == F.col("_s")), "left").withColumn("object_id", F.coalesce("child", "object_id")).select(resolved.columns)
        if target is not None and size:
            inherited = associate.fork_history(lightcurve.table(cat.spark, target).drop("added"), children)
    elif one_to_many != "merge":
        raise ValueError(one_to_many)
    founding = new.select("object_id", F.col("first_source_id").alias("source_id"), F.lit(0.0).alias("sep_arcsec"), F.lit("none").alias("topology"))
    curve = lightcurve.with_strip(lightcurve.points(kept.select("object_id", "source_id", "sep_arcsec", "topology").union(founding), sources), sources, cat.width)
    curve = curve if inherited is None else curve.unionByName(inherited)
    if target is not None:
        log.timed("associate", "light curves", image_id, lambda: lightcurve.append(curve, target, image_id), n_database=size)
    moved = kept.select("object_id", "source_id").join(sources.select("source_id", "ra_deg", "dec_deg", "x", "y", "z"), "source_id")

    def update():
        cat.commit(catalog.update_stats(old, moved, cat.width, mean_mode).unionByName(new), near, ids.value)
        return ids.value - size

    log.timed("associate", "update and commit", image_id, update, n_database=size)
    return curve


def build_up(spark: SparkSession, detections: DataFrame, images: list[int], r: float = 1.0, mode: str = "strips", root: str | None = None, log: QueryLog | None = None, policy: str = "nearest", one_to_many: str = "merge", by_groups: bool = False, stored: bool = False) -> tuple[catalog.Catalog, DataFrame]:
    """A cold start over images in order: the catalogue and the light-curve table, to which each image appends.

    The lists are written once, a directory an image, so that no image reads another's rows. stored: they are already. by_groups: the same objects, ids and
    light curves without a job per image, committed as one version; see build_up_by_groups.
    """
    root = root or f"{shared_dir(spark)}/stripmatch/catalog-{uuid.uuid4().hex}"
    cat, target = catalog.Catalog(spark, root), f"{root}-lightcurve"
    if by_groups:
        if (policy, one_to_many, log) != ("nearest", "merge", None) or len(set(images)) < len(images):
            raise ValueError("groups are replayed by the nearest, merged, each image once, without a log by image")
        build_up_by_groups(cat, detections, images, r, target)
        return cat, lightcurve.table(spark, target)
    lists = detections if stored else written_lists(detections, images)
    for i in images:
        step_image(cat, lists.where(F.col("image_id") == i), i, r, mode, policy, one_to_many=one_to_many, target=target, log=log)
    return cat, lightcurve.table(spark, target)


def written_lists(detections: DataFrame, images: list[int]) -> DataFrame:
    return written(detections.where(F.col("image_id").isin(images)), "lists", by="image_id")


def build_up_by_groups(cat: catalog.Catalog, detections: DataFrame, images: list[int], r: float, target: str) -> None:
    """A cold start of an empty catalogue, group by group of sources that can meet. Groups too large for a task go through the image loop.

    Ids are given in the end, by the image and the number of the founding source, which is the order in which the loop gives them.
    """
    spark = cat.spark
    with scratch(spark):
        order = F.broadcast(spark.createDataFrame(list(zip(images, range(len(images)))), "image_id int, pos int"))
        lists = written(detections.join(order, "image_id"), "lists").withColumn("cell", replay.cell_of(replay.side(3 * r)))
        of = replay.groups(lists, r)
        fits = (F.col("group_size") <= replay.MOST) & (F.col("most_pairs") <= replay.PAIRS)
        found = replay.replayed(lists.join(of.where(fits), "cell"), r)
        rest = lists.join(of.where(fits).select("cell"), "cell", "left_anti")  # those without a position, too
        if not rest.isEmpty():
            found = found.unionByName(_looped(spark, rest, images, r))
        found = written(found, "found")
        objects = written(assign_ids(found.where("datapoints > 0"), 0, ["pos", "first_source_id"], block=1), "objects")
        points = found.join(objects.select("first_source_id", "object_id"), "first_source_id").select("object_id", "source_id", "sep_arcsec", "topology")
        curve = lightcurve.with_strip(lightcurve.points(points, lists), lists, cat.width).withColumn("added", F.col("image_id"))
        curve.repartition("added", "strip").sortWithinPartitions("added", "strip", "object_id").write.partitionBy("added", "strip").parquet(target)
        cat.commit(objects.withColumn("active", F.lit(True)).withColumn("strip", sky.strip_of("mean_dec_deg", cat.width)), [], objects.count())


def _looped(spark: SparkSession, sources: DataFrame, images: list[int], r: float) -> DataFrame:
    """What replay.replayed gives, by the image loop."""
    own_images = {x["image_id"] for x in sources.select("image_id").distinct().collect()}
    part, curve = build_up(spark, sources.drop("pos", "cell"), [i for i in images if i in own_images], r, root=note(f"{shared_dir(spark)}/stripmatch/part-{uuid.uuid4().hex}"))
    note(f"{part.root}-lightcurve")
    held = part.all().select("object_id", "first_source_id", "datapoints", "mean_ra_deg", "mean_dec_deg", "x", "y", "z")
    points = curve.select("object_id", "source_id", "sep_arcsec", "topology").join(sources.select("source_id", "pos"), "source_id").join(held, "object_id")
    own = F.col("source_id") == F.col("first_source_id")
    state = [F.when(own, F.col(c)).alias(c) for c in ("mean_ra_deg", "mean_dec_deg", "x", "y", "z")]
    return points.select("first_source_id", "pos", "source_id", "sep_arcsec", "topology", F.when(own, F.col("datapoints")).otherwise(0).alias("datapoints"), *state)


def waves(footprints: dict[int, set]) -> list[list[int]]:
    """Images in order, grouped so that those of a wave share no cell; a conflicting image comes after the earlier one."""
    level: dict[int, int] = {}
    last: dict = {}
    for i in sorted(footprints):
        level[i] = 1 + max((last.get(c, 0) for c in footprints[i]), default=0)
        for c in footprints[i]:
            last[c] = level[i]
    return [[i for i in sorted(level) if level[i] == w] for w in range(1, max(level.values(), default=0) + 1)]


def footprints(detections: DataFrame, r: float = 1.0, width: float = 1.0) -> DataFrame:
    """image_id and the strips that it touches."""
    return detections.select("image_id", F.explode(sky.strips_touched("dec_deg", r / 3600, width)).alias("strip")).distinct()


def in_waves(detections: DataFrame, objects: DataFrame, r: float = 1.0) -> DataFrame:
    """Images matched wave by wave: those of a wave touch no common strip. The same pairs as one by one.

    A catalogue that no image changes needs no wave to wait for another: all are one join, and each pair names its wave.
    """
    touched: dict[int, set] = {}
    for x in footprints(detections, r).collect():  # at most images times strips
        touched.setdefault(x["image_id"], set()).add(x["strip"])
    of = [(i, k) for k, wave in enumerate(waves(touched)) for i in wave]
    lists = detections.join(F.broadcast(detections.sparkSession.createDataFrame(of, "image_id int, wave int")), "image_id")
    return match.match_zones(lists, objects, r, match.FINE, match.CELL, keep=("wave",))


def parallel_fields(detections: DataFrame, objects: DataFrame, bands: list[tuple[float, float]], r: float = 1.0) -> DataFrame:
    """Disjoint declination bands matched in one job; the same as one by one."""
    out = None
    for k, (lo, hi) in enumerate(bands):
        part = match.match_zones(detections.where((F.col("dec_deg") >= lo) & (F.col("dec_deg") < hi)), objects, r, 1 / 60, 1.0).withColumn("field", F.lit(k))
        out = part if out is None else out.unionByName(part)
    return out
