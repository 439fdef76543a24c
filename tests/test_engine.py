import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from stripmatch import workloads
from stripmatch.operators import associate, catalog, ids
from stripmatch.plans import experiments, metrics, pipeline
from stripmatch.sources import fits_table, fixtures, ingest

SF = "/root/testdata/sf0.001"
CHECKED = ["match_probe_image", "match_strip_key_image", "match_tree_ratio_rebuilt_image", "match_tree_never_rebuilt_image", "match_split_catalog_all_images", "match_in_waves", "catalogue_statistics", "exposure_headers", "topology_groups", "topology_groups_all_images", "catalog_buildup_3", "bench_modules", "bench_loading", "bench_tree", "stream_ingest", "transient_candidates", "lightcurves_of_cone", "lightcurves_of_box", "match_strips_image", "match_cells_image", "match_strip_catalog_image", "resolve_nearest", "unmatched_sources", "missed_objects", "catalog_update_one_image", "lightcurve_points", "max_id_footer", "cone_search", "measure_backlog", "customer_supplier_match", "rows_touched", "bench_layouts"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in ("lineitem", "part", "orders", "customer", "supplier", "nation", "region", "embeddings", "events"):
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", CHECKED)
def test_against_sql(spark, duck, name):
    got = workloads.queries()[name](spark, SF).toPandas()
    want = duck.sql(workloads.oracle_sql()[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    key = lambda d: sorted(map(tuple, d[cols].itertuples(index=False)), key=str)
    assert str(key(got)) == str(key(want.astype({c: got[c].dtype for c in cols})))


ALL_IMAGES = ["ingest_all_lists", "match_accuracy_all_images", "match_variable_radius_all_images", "topology_counts_all_images", "topology_pairs_all_images", "resolve_nearest_all_images", "resolve_mutual_nearest_all_images", "resolve_all_all_images",
              "unmatched_sources_all_images", "missed_objects_all_images", "distance_forms_all_images", "lightcurve_points_all_images"]


@pytest.mark.parametrize("name", ALL_IMAGES)
def test_all_images_against_sql(spark, duck, name):
    test_against_sql(spark, duck, name)


def test_all_images_are_there(spark):
    groups = workloads.queries()["topology_groups_all_images"](spark, SF).toPandas()
    pairs = workloads.queries()["topology_pairs_all_images"](spark, SF).toPandas()
    assert pairs.image_id.nunique() == fixtures.detections(spark, SF).select("image_id").distinct().count() > 80 and len(groups) == len(pairs)
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for x in pairs.itertuples():
        a, b = find((x.image_id, "o", x.object_id)), find((x.image_id, "s", x.source_id))
        root[max(a, b)] = min(a, b)
    assert all(find((x.image_id, "s", x.source_id)) == (x.image_id, "o", x.group_id) for x in groups.itertuples())


def test_build_up_invariants(spark, tmp_path):
    d = fixtures.detections(spark, SF)
    cat, curve = pipeline.build_up(spark, d, [0, 1, 2], root=f"file://{tmp_path}/cat")
    o, c = cat.all().toPandas(), curve.toPandas()
    assert o.object_id.is_unique and sorted(o.object_id) == list(range(len(o)))
    n = c.groupby("object_id").size()
    assert o.set_index("object_id").datapoints.sort_index().to_dict() == n.to_dict()
    assert set(c.source_id) == {x.source_id for x in d.where("image_id < 3").select("source_id").collect()}
    assert (np.floor(o.mean_dec_deg) == o.strip).all()
    pos = {x.source_id: (x.x, x.y, x.z) for x in d.where("image_id < 3").collect()}
    for x in o.itertuples():
        m = np.mean([pos[s] for s in c.source_id[c.object_id == x.object_id]], axis=0)
        assert np.abs(m / np.linalg.norm(m) - (x.x, x.y, x.z)).max() < 1e-8
    before = catalog.Catalog(spark, f"file://{tmp_path}/cat")
    assert before.state == cat.state and cat.ids.value == len(o)
    cut = cat.split(4)  # growth control: the same rows in smaller cells, and the next image goes on from there
    assert cut and cat.all().toPandas().sort_values("object_id").object_id.tolist() == sorted(o.object_id)
    sizes = cat.all().withColumn("cell", cat.cell_of(F.col("mean_ra_deg"), F.col("strip"))).groupBy("strip", "cell").count().toPandas()
    assert len(sizes) > o.strip.nunique()
    sources = d.where("image_id = 3")
    pipeline.step_image(cat, sources, 3, target=f"file://{tmp_path}/cat-lightcurve")
    one, _ = pipeline.build_up(spark, d, [0, 1, 2, 3], root=f"file://{tmp_path}/one")
    key = lambda c: sorted((x.first_source_id, x.datapoints, x.strip) for x in c.all().collect())
    assert key(cat) == key(one) and set(cat.touched(sources)) != {(s, 0) for s, _ in cat.touched(sources)}


def test_commit_beyond_the_cells_read(spark, tmp_path):
    """Rows that moved into a cell that was not read join those that it holds; a failed attempt's files are never read."""
    cat = catalog.Catalog(spark, f"file://{tmp_path}/moved")
    at = lambda k, dec: (k, k, 1, True, 10.0, dec, 0.0, 0.0, 1.0, int(dec))
    rows = lambda *r: spark.createDataFrame(list(r), "object_id long, first_source_id long, datapoints int, active boolean, mean_ra_deg double, mean_dec_deg double, x double, y double, z double, strip int")
    cat.commit(rows(at(0, 1.5), at(1, 1.6), at(2, 2.5), at(3, 3.5)), [], 4)
    (tmp_path / "moved" / "v=2-dead" / "strip=1" / "cell=0").mkdir(parents=True)
    (tmp_path / "moved" / "v=2-dead" / "strip=1" / "cell=0" / "part.parquet").write_bytes(b"cut short")
    cat.commit(rows(at(0, 1.5), at(1, 2.1)), [(1, 0)], 4)
    got = {(x.object_id, x.strip) for x in catalog.Catalog(spark, cat.root).all().collect()}
    assert got == {(0, 1), (1, 2), (2, 2), (3, 3)} and cat.state["version"] == 2


def test_forking_loop(spark, tmp_path):
    """Each source of a one-to-many pair founds an object with its parent's history; the parent goes inactive."""
    d = fixtures.detections(spark, SF)
    cat, curve = pipeline.build_up(spark, d, [0, 1], root=f"file://{tmp_path}/fork", one_to_many="fork")
    o, c = cat.all().toPandas(), curve.toPandas()
    n = c.groupby("object_id").size()
    assert o.object_id.is_unique and (~o.active).any() and cat.ids.value == len(o)
    assert o.set_index("object_id").datapoints.sort_index().to_dict() == n.to_dict()


def test_forest_updates():
    from stripmatch.operators.match import Forest, GrowingTree

    rng = np.random.default_rng(5)
    x = rng.normal(size=(900, 3))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    f = Forest()
    for i in range(0, 900, 100):
        f.insert(x[i : i + 100], np.arange(i, i + 100))
    f.remove(np.arange(0, 900, 7))
    moved = x[1:900:7][:, [1, 2, 0]]
    f.update(moved, np.arange(1, 900, 7))
    now = x.copy()
    now[1:900:7] = moved
    left = np.setdiff1d(np.arange(900), np.arange(0, 900, 7))
    for p in now[:40]:
        want = left[((now[left] - p) ** 2).sum(axis=1) < 0.09]
        assert sorted(f.near(p, 0.3)) == want.tolist()
    for rebuild in ("never", "every", "ratio"):
        t = GrowingTree(rebuild)
        for i in range(0, 900, 100):
            t.insert(x[i : i + 100], np.arange(i, i + 100))
        assert sorted(t.near(x[0], 0.3)) == np.flatnonzero(((x - x[0]) ** 2).sum(axis=1) < 0.09).tolist()
        assert t.rebuilt == {"never": 100, "every": 4500}.get(rebuild, t.rebuilt) and 100 <= t.rebuilt <= 4500


def test_strips_are_joined_by_a_fine_key(spark, tmp_path):
    cat = workloads._static_catalog(spark, SF)
    plan = workloads.match.match_strips(fixtures.detections(spark, SF, 40), cat)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "zone" in plan and "cell" in plan and "NestedLoop" not in plan


def test_clean(spark):
    from stripmatch import cluster

    kept = cluster.written(spark.range(3), "left-over")
    assert kept.count() == 3 and cluster.clean(spark, keep=("catalog", "other")) >= 1
    with pytest.raises(Exception):
        spark.read.parquet(*kept.inputFiles()).count()
    with cluster.scratch(spark):
        inner = cluster.written(spark.range(4), "inner")
        assert inner.count() == 4
    outer = cluster.written(spark.range(5), "outer")
    with pytest.raises(Exception):
        spark.read.parquet(*inner.inputFiles()).count()
    assert outer.count() == 5


def test_full_build_up_takes_every_image(spark, monkeypatch):
    taken = []
    monkeypatch.setattr(pipeline, "build_up", lambda spark, d, images, **_: (taken.extend(images), (catalog.Catalog(spark, f"{workloads.shared_dir(spark)}/stripmatch/none-{workloads.uuid.uuid4().hex}"), None))[1])
    workloads.queries()["catalog_buildup_full"](spark, SF)
    assert taken == sorted(x.image_id for x in fixtures.detections(spark, SF).select("image_id").distinct().collect()) and len(taken) > 80


def test_resolution_policies(spark):
    p = spark.createDataFrame([(1, 10, 0.1), (1, 11, 0.2), (2, 10, 0.3), (2, 11, 0.1), (3, 12, 0.1), (4, 13, 0.1), (4, 14, 0.2), (5, 15, 0.1), (6, 15, 0.2)], "object_id long, source_id long, sep_arcsec double")
    kinds = {(x.object_id, x.source_id): x.topology for x in associate.classify(p).collect()}
    assert kinds[1, 10] == kinds[2, 11] == "many-to-many" and kinds[3, 12] == "one-to-one" and kinds[4, 13] == "one-to-many" and kinds[5, 15] == "many-to-one"
    assert {(x.object_id, x.source_id) for x in associate.resolve(p).collect()} == {(1, 10), (2, 11), (3, 12), (4, 13), (4, 14), (5, 15), (6, 15)}
    assert {(x.object_id, x.source_id) for x in associate.resolve(p, "mutual_nearest").collect()} == {(1, 10), (2, 11), (3, 12), (4, 13), (5, 15)}
    g = {x.object_id: x.group_id for x in associate.topology_groups(p).collect()}
    assert g[1] == g[2] and g[5] == g[6] and len(set(g.values())) == 4


def test_fork_inherits_history(spark):
    p = spark.createDataFrame([(1, 10, 0.1), (1, 11, 0.2), (3, 12, 0.1)], "object_id long, source_id long, sep_arcsec double")
    kids = associate.fork(associate.resolve(p), 100)
    assert sorted((x.object_id, x.parent_id, x.source_id) for x in kids.collect()) == [(100, 1, 10), (101, 1, 11)]
    o = spark.createDataFrame([(1, True, 5), (3, True, 6), (4, False, 7)], "object_id long, active boolean, datapoints int")
    assert sorted(tuple(x) for x in associate.fork_objects(o, kids).collect()) == [(1, False, 5), (3, True, 6), (4, False, 7), (100, True, 5), (101, True, 5)]
    c = spark.createDataFrame([(1, 7, 1.5), (3, 8, 2.5)], "object_id long, source_id long, flux double")
    assert sorted(tuple(x) for x in associate.fork_history(c, kids).collect()) == [(100, 7, 1.5), (101, 7, 1.5)]


def test_ids_are_dense_and_repeatable(spark):
    df = spark.range(1000).withColumnRenamed("id", "source_id")
    a = sorted(x.object_id for x in ids.assign_ids(df, 7, ["source_id"]).collect())
    assert a == list(range(7, 1007))
    assert {tuple(x) for x in ids.assign_ids(df, 7, ["source_id"]).collect()} == {tuple(x) for x in ids.assign_ids(df.repartition(5), 7, ["source_id"]).collect()}


def test_waves_keep_order():
    assert pipeline.waves({0: {1}, 1: {2}, 2: {1, 2}, 3: {3}}) == [[0, 1, 3], [2]]


def test_fits_round_trip(spark, tmp_path):
    n = 1000
    a = {"id": np.arange(n), "ra": np.linspace(0, 360, n), "flag": (np.arange(n) % 5).astype("i2"), "mag": np.arange(n).astype("f4"), "tag": np.array([b"ab", b"c"] * (n // 2))}
    fits_table.write_table(f"{tmp_path}/t.fits", [a, {k: v[:10] for k, v in a.items()}])
    df = ingest.attach(spark, f"{tmp_path}/t.fits", "fits_table")
    assert df.count() == n + 10
    x = ingest.attach(spark, f"{tmp_path}/t.fits", "fits_table", extensions=[1]).toPandas().sort_values("id")
    assert len(x) == n and (x.ra.to_numpy() == a["ra"]).all() and (x.mag.to_numpy() == a["mag"]).all() and x.tag.tolist() == [b.decode() for b in a["tag"].tolist()]


def test_validate_and_replay(spark):
    rows = spark.createDataFrame([(1, 1, 10.0, 5.0), (1, 1, 10.0, 5.0), (1, 2, 400.0, 5.0), (1, 3, float("nan"), 5.0), (1, 4, None, 5.0), (1, 5, 0.0, -90.0)], "image_id int, source_id long, ra_deg double, dec_deg double")
    good, bad = ingest.validate(rows)
    assert sorted(x.source_id for x in good.collect()) == [1, 5] and sorted(x.source_id for x in bad.collect()) == [2, 3, 4]
    assert ingest.validate(rows, good)[0].count() == 0


def test_measures(spark):
    log = metrics.QueryLog("a")
    for i in range(1, 40):
        log.record("load", "flat", i, 1.0, n_database=100 * i)
        log.record("associate", "scan", i, 0.01 * i, n_database=100 * i)
    classes = {x["query"]: x["class"] for x in metrics.scaling_class(log.frame(spark)).collect()}
    assert classes == {"flat": "constant", "scan": "linear in N"}
    assert metrics.linear_share(metrics.scaling_class(log.frame(spark))).first().linear_share == 0.5
    waits = [x.waiting for x in metrics.backlog(log.frame(spark), 1.2).orderBy("image_id").collect()]
    assert waits[0] == 0 and waits[-1] > 0


def test_tree_stats_forest_rebuilds_less():
    x = np.random.default_rng(0).normal(size=(4000, 3))
    from stripmatch.operators.match import tree_stats

    t = tree_stats(x, 16)
    assert t.forest_rebuilt.iloc[-1] < t.tree_rebuilt.iloc[-1]


def test_components(spark):
    from stripmatch.operators.components import connected_components

    rng = np.random.default_rng(3)
    e = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1060)] + [(2000, 2001 + i) for i in range(50)] + [(7, None)]
    got = {x.node: x.component for x in connected_components(spark.createDataFrame(e, "a long, b long")).collect()}
    root = {v: v for p in e if None not in p for v in p}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    for a, b in e:
        if b is not None:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    assert got == {v: find(v) for p in e if None not in p and p[0] != p[1] for v in p}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_loading_and_tree_growth(spark):
    d = fixtures.detections(spark, SF)
    log = experiments.loading(spark, d, [0, 1]).collect()
    assert [(x["query"], x.image_id) for x in log] == [("bulk", 0), ("rowwise", 0), ("bulk", 1), ("rowwise", 1)] and log[0].n_database < log[2].n_database
    o = fixtures.objects(spark, SF)
    held = {x.strip: x["count"] for x in o.groupBy("strip").count().collect()}
    top = experiments.tree_growth(o).groupBy("strip").max("points").collect()
    assert {x.strip: x["max(points)"] for x in top} == held
