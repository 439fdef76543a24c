"""Round 3, F14: both modules over lists that one task, or one scan, would take too long for."""

from pathlib import Path

import pytest
from test_findings_r03 import SF, against_sql

from stripmatch.operators import associate, match
from stripmatch.plans import pipeline
from stripmatch.sources import fixtures


def test_modules_agree_with_sql_by_zones_and_spread_lists(spark, monkeypatch):
    monkeypatch.setattr(match, "SCAN", 0)
    monkeypatch.setattr(pipeline, "LONG_LIST", 0)
    stored, find, zones = [], match.match_baseline, []
    monkeypatch.setattr(pipeline, "written_lists", lambda *a, write=pipeline.written_lists: stored.append(a) or write(*a))
    monkeypatch.setattr(match, "match_baseline", lambda *a, **k: zones.append(k["zones"]) or find(*a, **k))
    got = against_sql(spark, "bench_modules", Path(SF), ["part", "lineitem"])
    assert len(got) == 6 and len(stored) == 1 and zones == [False, True, True]


def test_baseline_by_zones_finds_the_same(spark):
    s, o = fixtures.detections(spark, SF, 40), fixtures.objects(spark, SF)
    scan, zones = match.match_baseline(s, o), match.match_baseline(s, o, zones=True)
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(scan) == key(zones) and scan.count()
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" in plan(scan) and "NestedLoop" not in plan(zones)


def test_only_the_chosen_images_are_numbered(spark):
    plan = fixtures.detections(spark, SF).where("image_id IN (0, 1, 2)")._jdf.queryExecution().optimizedPlan().toString()
    below = plan[plan.index("Window [row_number") :]
    assert " IN (0,1,2)" in below or "INSET 0, 1, 2" in below


def test_resolution_shuffles_its_pairs_twice(spark):
    pairs = spark.createDataFrame([(1, 10, 0.1)], "object_id long, source_id long, sep_arcsec double")
    assert associate.classify(pairs).columns == ["object_id", "source_id", "sep_arcsec", "objects", "sources", "topology"]
    assert associate.resolve(pairs)._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") <= 4


@pytest.mark.parametrize("policy", ["nearest", "all"])
def test_every_matched_source_stays_resolved(spark, policy):
    rows = [(1, 10, 0.1), (1, 11, 0.2), (2, 10, 0.3), (2, 11, 0.1), (3, 12, 0.1), (4, 13, 0.1), (4, 14, 0.2), (5, 15, 0.1), (6, 15, 0.2)]
    pairs = spark.createDataFrame(rows, "object_id long, source_id long, sep_arcsec double")
    assert {x.source_id for x in associate.resolve(pairs, policy).collect()} == {x[1] for x in rows}
