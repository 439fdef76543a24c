"""Round 3, F15: a cold start over all images without jobs for each image."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from stripmatch import workloads
from stripmatch.functions import sky
from stripmatch.operators import catalog, replay
from stripmatch.plans import pipeline
from stripmatch.sources import fixtures

SF = "/root/testdata/sf0.001"


def crowd(spark):
    """Four lists of 60 in a field of 20 arcseconds across 0/360, beside 40 around the pole; numbered against the order of images 3, 1, 0, 2."""
    rng, rows = np.random.default_rng(4), []
    for k, image in enumerate([3, 1, 0, 2]):
        for n in range(100):
            ra, dec = ((rng.random() - 0.5) / 180 % 360, (rng.random() - 0.5) / 180) if n < 60 else (rng.random() * 360, 90 - rng.random() / 600)
            rows.append((image, (3 - k) * 100 + n, ra, dec, 50000.0 + k, 1.0 + n, 0.1))
    frame = spark.createDataFrame(rows, "image_id int, source_id long, ra_deg double, dec_deg double, mjd double, flux double, flux_err double")
    return sky.with_position(frame, libm=True)


def told(cat, curve):
    o = cat.all().select("object_id", "first_source_id", "datapoints", "active", "strip", *[F.round(c, 9).alias(c) for c in ("mean_ra_deg", "mean_dec_deg", "x", "y", "z")])
    return sorted(map(tuple, o.collect())), sorted(map(tuple, curve.collect()))


@pytest.fixture(scope="module")
def looped(spark):
    d, c = fixtures.detections(spark, SF), crowd(spark)
    return {"given": (d, [0, 1, 2, 3], told(*pipeline.build_up(spark, d, [0, 1, 2, 3]))), "crowd": (c, [3, 1, 0, 2], told(*pipeline.build_up(spark, c, [3, 1, 0, 2])))}


@pytest.mark.parametrize("which", ["given", "crowd"])
@pytest.mark.parametrize("most", [500_000, 8])
def test_groups_are_as_the_loop(spark, looped, monkeypatch, which, most):
    """Objects, ids and light curves, also where groups of more than 8 sources are left to the loop."""
    monkeypatch.setattr(replay, "MOST", most)
    monkeypatch.setattr(replay, "CHUNK", 50)
    d, images, (objects, curve) = looped[which]
    cat, points = pipeline.build_up(spark, d, images, by_groups=True)
    got = told(cat, points)
    assert got[0] == objects and got[1] == curve
    assert catalog.Catalog(spark, cat.root).ids.value == len(objects) and {x[-1] for x in curve} and {x[7] for x in curve} >= {"none", "one-to-one"}


def test_sources_that_meet_share_a_group(spark):
    c = crowd(spark).withColumn("cell", replay.cell_of(replay.side(3.0)))
    p = c.join(replay.groups(c, 1.0), "cell").select("x", "y", "z", "group", "group_size").toPandas()
    x = p[["x", "y", "z"]].to_numpy()
    near = np.sqrt(((x[:, None] - x) ** 2).sum(axis=2)) < 2 * np.sin(np.radians(3 / 3600) / 2)
    assert len(p) == 400 and (p.group.to_numpy()[:, None] == p.group.to_numpy())[near].all()
    assert (p.groupby("group").size() == p.groupby("group").group_size.first()).all()


def test_empty(spark):
    cat, curve = pipeline.build_up(spark, fixtures.detections(spark, SF), [500], by_groups=True)
    assert cat.ids.value == 0 and cat.all().count() == 0 and curve.count() == 0


def test_full_build_up_has_no_jobs_for_each_image(spark):
    spark.sparkContext.setJobGroup("full", "catalog_buildup_full")
    o = workloads.queries()["catalog_buildup_full"](spark, SF).toPandas()
    jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("full")
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    d = pd.DataFrame(fixtures.detections(spark, SF).select("image_id", "source_id").collect(), columns=["image_id", "source_id"])
    assert d.image_id.nunique() > 80 and len(jobs) < 83
    assert o.datapoints.sum() >= len(d) and set(o.first_source_id) <= set(d.source_id)
    assert o.sort_values("first_source_id").object_id.tolist() == list(range(len(o)))


def test_a_crowded_group_is_not_left_to_the_loop(spark):
    """A group's sources are many if its images are: what one image can pair is what counts."""
    c = spark.range(0, 12_000).select((F.col("id") % 80).cast("int").alias("image_id"), F.lit(0.001).alias("ra_deg"), (F.col("id") % 7 * 1e-6).alias("dec_deg"))
    got = replay.groups(sky.with_position(c), 1.0).select("group_size", "most_pairs").distinct().collect()
    assert [tuple(x) for x in got] == [(12_000, 150 * 12_000)] and 12_000 <= replay.MOST and 150 * 12_000 <= replay.PAIRS
