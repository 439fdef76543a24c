import math

import pytest
from pyspark.sql import functions as F

from stripmatch.functions import sky
from stripmatch.operators import match

POINTS = [(0.0, 90.0), (10.0, -90.0), (0.0, 0.0), (359.9999999, 0.0), (360.0, 0.0), (120.0, 1.0), (120.0, 0.99999999), (120.0, 1.00000001), (5.0, 89.9999), (185.0, 89.9999), (200.0, -5.0), (200.0, -5.0)]


def frame(spark, points, name):
    df = spark.createDataFrame([(i, float(a), float(d)) for i, (a, d) in enumerate(points)], f"{name} long, ra_deg double, dec_deg double")
    return sky.with_position(df)


@pytest.mark.parametrize("r", [0.0, 1.0, 30.0, 3600.0, 7200.0])
def test_variants_equal_brute_force(spark, r):
    jitter = [((a + da / max(1e-3, math.cos(math.radians(d)))) % 360, max(-90, min(90, d + dd))) for a, d in POINTS for da, dd in ((0, 0), (2e-4, 0), (0, -2e-4), (0.9, 0.3))]
    s, o = frame(spark, jitter, "source_id"), frame(spark, POINTS, "object_id")
    want = {(x.object_id, x.source_id) for x in match.match_bruteforce(s, o, r).collect()}
    for found in (match.match_baseline(s, o, r), match.match_strips(s, o, r), match.match_zones(s, o, r, 0.25, 1.0), match.match_zones(s, o, r, 5.0, 10.0), match.match_tree(s, o, r), match.match_tree(s, o, r, forest=True)):
        assert {(x.object_id, x.source_id) for x in found.collect()} == want
    assert r == 0 or len(want) > len(POINTS)


def test_threshold_is_strict_and_empty_inputs(spark):
    o = frame(spark, [(0.0, 0.0)], "object_id")
    s = frame(spark, [(0.0, 1 / 3600 - 1e-9), (0.0, 1 / 3600 + 1e-9)], "source_id")
    assert [x.source_id for x in match.match_zones(s, o, 1.0).collect()] == [0]
    assert match.match_strips(s.limit(0), o, 1.0).count() == 0
    assert match.match_zones(s, o.limit(0), 1.0).count() == 0


def test_round_trip_and_halfwidth(spark):
    df = frame(spark, POINTS, "k")
    ra, dec = sky.radec("x", "y", "z")
    for x in df.select("dec_deg", "ra_deg", ra.alias("a"), dec.alias("d"), (F.col("x") ** 2 + F.col("y") ** 2 + F.col("z") ** 2).alias("n"), sky.ra_halfwidth("dec_deg", F.lit(0.1)).alias("h")).collect():
        assert abs(x.n - 1) < 1e-12 and abs(x.d - x.dec_deg) < 1e-7 and x.h >= 0.1 - 1e-12
        assert abs(x.dec_deg) == 90 or abs((x.a - x.ra_deg + 540) % 360 - 180) < 1e-7
        assert x.h == 180 if abs(x.dec_deg) > 89.95 else x.h < 180


def test_no_nested_loop_and_no_python_in_match(spark):
    s, o = frame(spark, POINTS, "source_id"), frame(spark, POINTS, "object_id")
    plan = match.match_zones(s, o, 1.0, 1 / 60, 1.0)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan and "Python" not in plan
    plan = match.match_baseline(s, o, 1.0)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" in plan or "Cartesian" in plan  # the comparator stays a scan


def test_sql_functions(spark):
    sky.register(spark)
    x = spark.sql("SELECT sky_ra_halfwidth(60D, 1D) h, sky_strip(-0.5D, 1D) s, sky_ra_gap(359.5D, 0.5D) g, sky_sep_arcsec(sky_chord2(0D, 0D, 0D, 1D)) a").first()
    assert abs(x.h - math.degrees(math.asin(math.sin(math.radians(1)) / 0.5))) < 1e-9 and x.s == -1 and abs(x.g - 1) < 1e-9 and abs(x.a - 3600) < 1e-6
