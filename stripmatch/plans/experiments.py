"""Comparisons of layouts, modules, loaders and trees. `python -m stripmatch.plans.experiments SF_DIR` prints the timed ones."""

from __future__ import annotations

import subprocess
import sys
import time
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import shared_dir, ship, written
from stripmatch.functions import sky
from stripmatch.operators import catalog, match, places
from stripmatch.plans import metrics, pipeline
from stripmatch.sources import fixtures, ingest

WIDTHS = (0.1, 0.25, 1.0, 5.0, 180.0)


def _folder(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/stripmatch/{what}-{uuid.uuid4().hex}"


def layouts(sources: DataFrame, objects: DataFrame, widths=WIDTHS, r: float = 1.0, log: metrics.QueryLog | None = None) -> DataFrame:
    """Pairs of a list against catalogues of each strip width, sorted or not, by each threshold. All must agree.

    A width is one of storage: the join within what is read goes by the fine key, as in match_strips, and pairs are counted by place.
    """
    spark, log, rows = objects.sparkSession, log or metrics.QueryLog("layouts"), []
    sources = written(sources.select("source_id", "ra_deg", "dec_deg", "x", "y", "z"), "list")
    kept = objects.select("object_id", F.lit(-1).cast("long").alias("first_source_id"), F.lit(1).alias("datapoints"), F.lit(True).alias("active"), F.col("ra_deg").alias("mean_ra_deg"), F.col("dec_deg").alias("mean_dec_deg"), "x", "y", "z")
    for width in widths:
        strips = match.touched_strips(sources, r, width)
        for dense in (True, False):
            cat = catalog.Catalog(spark, _folder(spark, "layout"), width, sort=dense)
            cat.commit(kept.withColumn("strip", sky.strip_of("mean_dec_deg", width)), [])
            for threshold in ("chord2", "angle"):
                part = match.strips_of(cat, strips)
                n = log.timed(f"width {width}", f"{'sorted' if dense else 'unsorted'} {threshold}", 0, lambda: places.count(sources, part, r, threshold))
                rows.append((width, dense, threshold, n))
    return spark.createDataFrame(rows, "width double, dense boolean, threshold string, n_pairs long")


def module_logs(spark: SparkSession, detections: DataFrame, images: list[int]) -> tuple[DataFrame, dict[str, float]]:
    """A cold start by either module: (the log of both, seconds of each as a whole)."""
    logs, took, lists = None, {}, pipeline.written_lists(detections, images)
    for mode in ("baseline", "strips"):
        log, began = metrics.QueryLog(mode), time.perf_counter()
        pipeline.build_up(spark, lists, images, mode=mode, log=log, stored=True)
        took[mode] = time.perf_counter() - began
        frame = log.frame(spark)
        logs = frame if logs is None else logs.union(frame)
    return logs, took


def modules(spark: SparkSession, detections: DataFrame, images: list[int]) -> tuple[DataFrame, DataFrame]:
    """A cold start by either module: (speed-up per query, totals with the overhead)."""
    logs, took = module_logs(spark, detections, images)
    totals = None
    for mode, seconds in took.items():
        one = metrics.totals(logs.where(F.col("run_id") == mode), seconds)
        totals = one if totals is None else totals.union(one)
    return metrics.speedup(logs.withColumn("step", F.col("query")), "baseline", "strips"), totals


def module_counts(spark: SparkSession, detections: DataFrame, images: list[int]) -> DataFrame:
    """What both modules log, image by image, but for the seconds: they must agree."""
    logs, _ = module_logs(spark, detections, images)
    of = lambda q: F.max(F.when(F.col("query") == q, F.col("rows_out")))
    return logs.groupBy("run_id", "image_id").agg(F.max("n_database").alias("n_database"), of("match").alias("n_pairs"), of("resolve").alias("n_kept"), of("new objects").alias("n_new"))


def large_match(spark: SparkSession, n_objects: int, n_sources: int, r: float = 1.0) -> dict[str, float]:
    """Seconds of the baseline and of the partitioned match of a list against a catalogue of n_objects even on the sky, as stored."""
    u = lambda seed: F.rand(seed)
    place = spark.range(0, n_objects, 1, 64).select(F.col("id").alias("object_id"), (u(1) * 360).alias("ra_deg"), F.degrees(F.asin(2 * u(2) - 1)).alias("dec_deg"))
    objects = place.select("*", *sky.unit_vector("ra_deg", "dec_deg"), sky.strip_of("dec_deg").alias("strip"))
    cat = catalog.Catalog(spark, _folder(spark, "catalog-large"))
    cat.commit(objects.select("object_id", F.lit(-1).cast("long").alias("first_source_id"), F.lit(1).alias("datapoints"), F.lit(True).alias("active"), F.col("ra_deg").alias("mean_ra_deg"), F.col("dec_deg").alias("mean_dec_deg"), "x", "y", "z", "strip"), [])
    field = cat.all().where("mean_dec_deg BETWEEN 10.1 AND 10.9").orderBy("object_id").limit(n_sources)
    source = field.select(F.col("object_id").alias("source_id"), F.col("mean_ra_deg").alias("ra_deg"), (F.col("mean_dec_deg") + 0.2 / 3600).alias("dec_deg"))
    source = written(source.select("*", *sky.unit_vector("ra_deg", "dec_deg")), "list")
    whole = cat.all().withColumnsRenamed({"mean_ra_deg": "ra_deg", "mean_dec_deg": "dec_deg"})
    ways = {"probe": lambda: match.match_probe(source, cat, r), "strips": lambda: match.match_strips(source, cat, r), "baseline": lambda: match.match_baseline(source, whole, r)}
    took, found = {}, {}
    for name, way in ways.items():
        for _ in range(1 if name == "baseline" else 3):  # the first compiles
            began = time.perf_counter()
            found[name] = way().count()
            took[name] = min(took.get(name, 1e9), time.perf_counter() - began)
    if len(set(found.values())) != 1:
        raise AssertionError(found)
    return {k: round(v, 3) for k, v in took.items()} | {"speedup": round(took["baseline"] / min(took["strips"], took["probe"]), 1)}


def resources(sf: str, cores=(1, 2, 4), memory=("1g", "2g", "4g"), query: str = "match_all_images") -> list[tuple[int, str, float, int]]:
    """(cores, driver memory, seconds, rows) of a query in sessions of its own: the classes of nodes."""
    code = "import sys, time; from pyspark.sql import SparkSession; from stripmatch import workloads; s = SparkSession.builder.master(f'local[{sys.argv[1]}]').config('spark.driver.memory', sys.argv[2]).config('spark.ui.enabled', 'false').getOrCreate(); b = time.perf_counter(); n = workloads.queries()[sys.argv[4]](s, sys.argv[3]).count(); print('took', time.perf_counter() - b, n)"
    out = []
    for c in cores:
        for m in memory:
            ran = subprocess.run([sys.executable, "-c", code, str(c), m, sf, query], capture_output=True, text=True, check=True)
            seconds, n = next(x.split()[1:] for x in ran.stdout.splitlines() if x.startswith("took"))
            out.append((c, m, float(seconds), int(n)))
    return out


def loading(spark: SparkSession, detections: DataFrame, images: list[int]) -> DataFrame:
    """Seconds of a bulk and of a row-wise load against the size of the table that they grow."""
    log, size = metrics.QueryLog("loading"), 0
    bulk, rowwise = _folder(spark, "bulk"), _folder(spark, "rowwise")
    for i in images:
        rows = written(detections.where(F.col("image_id") == i), "list")
        n = rows.count()
        size += n
        log.timed("load", "bulk", i, lambda: ingest.append_detections(rows, bulk), n_database=size)
        log.timed("load", "rowwise", i, lambda: ingest.load_rowwise(rows, rowwise), n_database=size)
    return log.frame(spark)


def tree_growth(objects: DataFrame, batches: int = 8) -> DataFrame:
    """Per strip, depth and rebuilt points of a tree that is rebuilt at every batch, and of a forest."""
    ship(objects.sparkSession)

    def grow(pdf: pd.DataFrame) -> pd.DataFrame:
        t = match.tree_stats(pdf.sort_values("object_id")[["x", "y", "z"]].to_numpy(), batches)
        t.insert(0, "strip", pdf["strip"].iloc[0])
        return t

    return objects.select("strip", "object_id", "x", "y", "z").groupBy("strip").applyInPandas(grow, "strip int, points long, tree_depth long, tree_rebuilt long, forest_depth long, forest_trees long, forest_rebuilt long")


def rows_touched(detections: DataFrame, objects: DataFrame, r: float = 1.0) -> DataFrame:
    """Per image, the catalogue rows in the strips that its list touches, beside all rows."""
    held = objects.groupBy("strip").agg(F.count(F.lit(1)).alias("n"))
    size = objects.count()
    return pipeline.footprints(detections, r).join(held, "strip", "left").groupBy("image_id").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("rows_touched")).withColumn("n_database", F.lit(size).cast("long"))


def main(sf: str) -> None:
    spark = SparkSession.builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    detections, objects = fixtures.detections(spark, sf), fixtures.objects(spark, sf)
    log = metrics.QueryLog("layouts")
    layouts(fixtures.detections(spark, sf, 40), objects, log=log)
    log.frame(spark).select("step", "query", "seconds", "rows_out").show(40, False)
    for frame in modules(spark, detections, [0, 1, 2]):
        frame.show(40, False)
    print(large_match(spark, 2_000_000, 7_000))
    metrics.scaling_class(loading(spark, detections, list(range(12)))).select("query", "slope_n", "per_row", "class").show(40, False)
    spark.stop()
    for row in resources(sf):
        print(*row)


if __name__ == "__main__":
    main(sys.argv[1])
