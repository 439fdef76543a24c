"""Round 3: what larger tables showed."""

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

from stripmatch import workloads
from stripmatch.functions import sky
from stripmatch.operators import ids, match
from stripmatch.sources import fixtures

SF = "/root/testdata/sf0.001"


def against_sql(spark, name, folder, tables):
    c = duckdb.connect()
    for t in tables:
        c.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    want = c.execute(workloads.oracle_sql()[name]).df()
    got = workloads.queries()[name](spark, str(folder)).toPandas()[list(want.columns)]
    rows = lambda d: sorted(map(tuple, d.itertuples(index=False)), key=str)
    assert str(rows(got)) == str(rows(want.astype(got.dtypes.to_dict())))
    return got


def test_pairs_on_the_radius_go_as_in_sql(spark, tmp_path):
    pd.DataFrame({"p_partkey": [10823, 10824, 32423]}).to_parquet(tmp_path / "part.parquet")
    pd.DataFrame({"s_suppkey": [5243]}).to_parquet(tmp_path / "supplier.parquet")
    against_sql(spark, "cone_search_bulk", tmp_path, ["part", "supplier"])


def test_ids_follow_their_order(spark):
    df = spark.range(0, 300_000, 3).select(F.col("id").alias("source_id")).repartition(7)
    got = ids.assign_ids(df, 5, ["source_id"]).toPandas().sort_values("source_id")
    assert got.object_id.tolist() == list(range(5, 100_005))


def test_means_on_half_a_last_place_round_as_c_does(spark):
    got = spark.createDataFrame([(2.5,), (-2.5,), (0.25,), (1.0000000499999998,)], "v double").select(sky.rounded("v", 0).alias("a"), sky.rounded("v", 7).alias("b")).toPandas()
    assert got.a.tolist() == [3.0, -3.0, 0.0, 1.0] and got.b.tolist() == [2.5, -2.5, 0.25, 1.0]


CROWDED = ["match_strip_key_image", "match_baseline_image", "match_accuracy_all_images", "topology_counts_all_images", "topology_groups_all_images", "resolve_nearest_all_images", "transient_candidates", "distance_forms_all_images", "lightcurve_points_all_images", "match_in_waves", "bench_layouts"]


@pytest.fixture(scope="module")
def crowded(tmp_path_factory):
    """Objects that share positions (keys repeat on the sky after 21,600) with some that don't, and a list for each of five images."""
    at = tmp_path_factory.mktemp("crowded")
    c = duckdb.connect()
    c.execute(f"copy (select p.* replace (p_partkey + 21600 * i as p_partkey) from '{SF}/part.parquet' p, range(4) g(i) where i = 0 or p_partkey % 3 = 0) to '{at}/part.parquet'")
    c.execute(f"copy (select l.* replace (l_partkey + 21600 * (l_orderkey % 4) * CAST(l_partkey % 3 = 0 AS BIGINT) as l_partkey) from '{SF}/lineitem.parquet' l where year(l_shipdate) * 12 + month(l_shipdate) between 1995 * 12 + 1 and 1995 * 12 + 4 or (year(l_shipdate) = 1998 and month(l_shipdate) = 5)) to '{at}/lineitem.parquet'")
    return at


@pytest.mark.parametrize("name", CROWDED)
def test_crowded_positions(spark, crowded, name):
    assert len(against_sql(spark, name, crowded, ["part", "lineitem"]))


def test_positions_are_compared_once(spark, crowded):
    s, o = fixtures.detections(spark, str(crowded), 3), fixtures.objects(spark, str(crowded))
    joined = match.zone_join(s, o)
    n = joined.agg(F.count(F.lit(1)), F.sum("n")).first()
    assert n[1] == match.match_zones(s, o).count() > n[0]


def test_numbering_is_not_one_task_an_image(spark, crowded):
    d = fixtures.detections(spark, str(crowded))
    assert "windowspecdefinition(_day" in d._jdf.queryExecution().analyzed().toString()
