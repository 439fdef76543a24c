"""The experiments on the given tables as registered queries, with DuckDB SQL where SQL can say the same."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import read_table, shared_dir, written
from stripmatch.functions import sky
from stripmatch.operators import associate, catalog, ids, lightcurve, match, places
from stripmatch.plans import experiments, metrics, pipeline
from stripmatch.schema import EXPOSURE, LIGHTCURVE, conform
from stripmatch.sources import fixtures, ingest
from stripmatch.streaming import lists

IMAGE = 40


def _mas(k: str) -> str:
    """SQL of a key's base columns b, ra, dec, amp."""
    b = f"(CASE WHEN {k} % 10 = 1 THEN {k} - 1 ELSE {k} END)"
    return f"""CASE WHEN {b} % 40 = 7 THEN (({b} * 7919) % 1296000) * 1000 WHEN {b} % 20 = 3 THEN 0 ELSE ((({b} * 7919) % 7200) * 1000 + 1292400000) % 1296000000 END AS ra0,
      CASE WHEN {b} % 40 = 7 THEN 324000000 - (1 + ({b} * 104729) % 3600) * 1000 WHEN {b} % 20 = 13 THEN (({b} * 7) % 5 - 2) * 3600000 ELSE ({b} * 104729) % 21600 * 1000 - 10800000 END
        + CASE WHEN {k} % 10 = 1 THEN 1200 ELSE 0 END AS dec0, CASE WHEN {b} % 40 = 7 THEN 50 ELSE 1 END AS amp"""


def _vector(source: str) -> str:
    return f"""SELECT *, cos(radians(dec_deg)) * cos(radians(ra_deg)) AS x, cos(radians(dec_deg)) * sin(radians(ra_deg)) AS y, sin(radians(dec_deg)) AS z,
      CAST(floor(dec_deg) AS INTEGER) AS strip FROM ({source})"""


def _objects_sql(table: str = "part", key: str = "p_partkey", shift: int = 0, where: str = "TRUE") -> str:
    return _vector(f"SELECT k AS object_id, CAST(ra0 AS DOUBLE) / 3.6e6 AS ra_deg, CAST(least(dec0 + {shift}, 324000000) AS DOUBLE) / 3.6e6 AS dec_deg FROM (SELECT k, {_mas('k')} FROM (SELECT {key} AS k FROM {table}) WHERE {where})")


_DETECTIONS = _vector(f"""
  SELECT image_id, source_id, CAST((ra0 + amp * ((l_orderkey * 37 + l_linenumber * 101) % 1201 - 600) + 1296000000) % 1296000000 AS DOUBLE) / 3.6e6 AS ra_deg,
    CAST(least(dec0 + (l_orderkey * 53 + l_linenumber * 211) % 1201 - 600, 324000000) AS DOUBLE) / 3.6e6 AS dec_deg,
    49718e0 + date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS mjd, l_extendedprice AS flux, 1 + 0.01e0 * l_extendedprice AS flux_err, l_discount AS ellipticity, l_quantity AS area,
    l_linestatus AS band, l_returnflag AS quality, l_partkey AS true_object, 0.5e0 + l_quantity / 50e0 AS r_arcsec
  FROM (SELECT *, {_mas('l_partkey')}, CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS INTEGER) AS image_id,
          row_number() OVER (ORDER BY {', '.join(fixtures.DETECTION_ORDER)}) - 1 AS source_id FROM lineitem)""")
_CHORD = "((o.x - d.x) * (o.x - d.x) + (o.y - d.y) * (o.y - d.y) + (o.z - d.z) * (o.z - d.z))"
_SEP = f"round(degrees(2 * asin(sqrt({_CHORD}) / 2)) * 3600e0, 6)"


def _with(objects: str = "", image: int | None = IMAGE) -> str:
    return f"WITH o AS ({objects or _objects_sql()}), d AS (SELECT * FROM ({_DETECTIONS}) {'' if image is None else f'WHERE image_id = {image}'})"


def _pairs_sql(r: str = "1e0") -> str:
    """All pairs by declination box and chord (the box only spares work)."""
    return f"SELECT o.object_id, d.source_id, {_SEP} AS sep_arcsec FROM o JOIN d ON o.dec_deg BETWEEN d.dec_deg - 0.001 AND d.dec_deg + 0.001 AND {_CHORD} < 4 * power(sin(radians({r} / 3600e0) / 2), 2)"


_CLASS = """SELECT *, CASE WHEN objects = 1 AND sources = 1 THEN 'one-to-one' WHEN objects = 1 THEN 'one-to-many' WHEN sources = 1 THEN 'many-to-one' ELSE 'many-to-many' END AS topology
  FROM (SELECT object_id, source_id, sep_arcsec, count(*) OVER (PARTITION BY source_id) AS objects, count(*) OVER (PARTITION BY object_id) AS sources FROM {})"""
_RESOLVED = f"""p AS ({_pairs_sql()}), c AS ({_CLASS.format('p')}),
  k AS (SELECT object_id, source_id, sep_arcsec FROM (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY sep_arcsec, object_id) AS nth FROM c) WHERE topology <> 'many-to-many' OR nth = 1), res AS ({_CLASS.format('k')})"""

_registered: dict[str, tuple[Callable, str | None]] = {}


def workload(sql: str | None = None):
    def add(f):
        _registered[f.__name__] = (f, sql)
        return f

    return add


def _list(spark, sf, image=IMAGE):
    return fixtures.detections(spark, sf, image)


# ingest


@workload(f"{_with()} SELECT image_id, source_id, round(ra_deg, 9) AS ra_deg, round(dec_deg, 9) AS dec_deg, round(x, 9) AS x, round(y, 9) AS y, round(z, 9) AS z, strip, mjd, flux, band FROM d")
def ingest_source_list(spark, sf):
    """One list with its derived columns, through a written table and back."""
    d = written(_list(spark, sf), "detections")
    return d.select("image_id", "source_id", *[F.round(c, 9).alias(c) for c in ("ra_deg", "dec_deg", "x", "y", "z")], "strip", "mjd", "flux", "band")


@workload("""WITH i AS (SELECT *, CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS INTEGER) AS image_id, 49718e0 + date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS mjd FROM lineitem),
s AS (SELECT image_id, min(mjd) AS mjd_min, max(mjd) AS mjd_max, count(*) AS n_sources, count(DISTINCT l_partkey) AS n_objects, count(*) FILTER (l_linestatus = 'F') AS n_finished,
  min(l_extendedprice) AS flux_min, max(l_extendedprice) AS flux_max, sum(l_quantity) AS area_sum, max(l_discount) AS ellipticity_max, min(l_returnflag) AS first_quality FROM i GROUP BY image_id),
t AS (SELECT CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INTEGER) AS image_id, min(o_orderpriority) AS band, round(avg(o_totalprice), 2) AS exptime, count(*) AS order_count, max(o_orderkey) AS last_order FROM orders GROUP BY 1)
SELECT s.*, t.band, t.exptime, t.order_count, t.last_order FROM s LEFT JOIN t USING (image_id)""")
def exposure_headers(spark, sf):
    """Headers of fifteen typed fields, all written at once and read back."""
    target = f"{shared_dir(spark)}/stripmatch/exposures-{uuid.uuid4().hex}"
    ingest.register_exposures(fixtures.exposures(spark, sf), target)
    return spark.read.schema(EXPOSURE).parquet(target)


_GROWTH = "SELECT CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS INTEGER) AS image_id, count(*) AS n FROM lineitem GROUP BY 1"


def _sizes(spark, sf):
    from pyspark.sql.window import Window

    n = read_table(spark, sf, "lineitem").groupBy(fixtures.image_of(F.col("l_shipdate")).alias("image_id")).agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("n_database", F.sum("n").over(Window.orderBy("image_id").rowsBetween(Window.unboundedPreceding, 0)))  # a row per image


@workload(f"SELECT image_id, n, CAST(sum(n) OVER (ORDER BY image_id) AS BIGINT) AS n_database FROM ({_GROWTH})")
def growth_curve(spark, sf):
    return _sizes(spark, sf)


# match


def _image_match(how):
    return lambda spark, sf: how(_list(spark, sf), fixtures.objects(spark, sf))


for _name, _how in {
    "match_baseline_image": match.match_baseline,
    "match_bruteforce_image": match.match_bruteforce,
    "match_strips_image": match.match_strips,
    "match_strip_key_image": match.match_strip_key,
    "match_probe_image": match.match_probe,
    "match_angle_threshold_image": lambda s, o: match.match_zones(s, o, 1.0, 1.0, threshold="angle"),
    "match_finezones_image": lambda s, o: match.match_zones(s, o, 1.0, 1 / 3600),
    "match_minute_zones_image": lambda s, o: match.match_zones(s, o, 1.0, 1 / 60),
    "match_cells_image": lambda s, o: match.match_zones(s, o, 1.0, 1.0, 1.0),
    "match_tree_image": match.match_tree,
    "match_forest_image": lambda s, o: match.match_tree(s, o, forest=True),
    "match_tree_never_rebuilt_image": lambda s, o: match.match_tree(s, o, rebuild="never"),
    "match_tree_always_rebuilt_image": lambda s, o: match.match_tree(s, o, rebuild="every"),
    "match_tree_ratio_rebuilt_image": lambda s, o: match.match_tree(s, o, rebuild="ratio"),
}.items():
    _registered[_name] = (_image_match(_how), f"{_with()} {_pairs_sql()}")


@workload(f"{_with()} {_pairs_sql()}")
def match_strip_catalog_image(spark, sf):
    """The same over a written catalogue of one directory per strip: only the touched ones are read."""
    cat = _static_catalog(spark, sf)
    return match.match_strips(_list(spark, sf), cat)


@workload(f"{_with(image=None)} {_pairs_sql()}")
def match_split_catalog_all_images(spark, sf):
    """All lists against a written catalogue whose full strips are cut into cells, by range probes of the sorted declination."""
    cat = _static_catalog(spark, sf)
    cat.split(5)
    return match.match_probe(fixtures.detections(spark, sf), cat)


@workload(f"SELECT strip, count(*) AS n, round(avg(dec_deg), 9) AS mean, min(dec_deg) AS low, max(dec_deg) AS high, round(stddev_samp(dec_deg), 9) AS scatter FROM ({_objects_sql()}) GROUP BY strip")
def catalogue_statistics(spark, sf):
    """Storage-kept statistics of a column, strip by strip."""
    return _static_catalog(spark, sf).table_stats().select("strip", "n", F.round("mean", 9).alias("mean"), "low", "high", F.round("scatter", 9).alias("scatter"))


def _static_catalog(spark, sf, holes=False):
    o = fixtures.objects(spark, sf, holes=holes)
    rows = o.select("object_id", F.lit(-1).cast("long").alias("first_source_id"), F.lit(1).alias("datapoints"), F.lit(True).alias("active"), F.col("ra_deg").alias("mean_ra_deg"), F.col("dec_deg").alias("mean_dec_deg"), "x", "y", "z", "strip")
    cat = catalog.Catalog(spark, f"{shared_dir(spark)}/stripmatch/catalog-{uuid.uuid4().hex}")
    top = o.agg(F.max("object_id")).first()[0]
    cat.commit(rows, [], (top or 0) + 1)
    return cat


@workload(f"{_with(image=None)} {_pairs_sql()}")
def match_all_images(spark, sf):
    return match.match_zones(fixtures.detections(spark, sf), fixtures.objects(spark, sf), 1.0, 1 / 60, 1.0)


@workload(f"{_with()} {_pairs_sql('d.r_arcsec')}")
def match_variable_radius(spark, sf):
    return match.match_zones(_list(spark, sf), fixtures.objects(spark, sf), "r_arcsec", 1 / 60, 1.0)


def _edge_match(where_sql, where):
    sql = f"{_with(image=None)} SELECT * FROM ({_pairs_sql()}) WHERE object_id IN (SELECT object_id FROM o WHERE {where_sql})"
    return (lambda spark, sf: match.match_zones(fixtures.detections(spark, sf), fixtures.objects(spark, sf).where(where), 1.0, 1.0, 1.0)), sql


for _name, _w in {"match_polar": "dec_deg > 80", "match_wrap": "ra_deg < 0.001 AND dec_deg < 80", "match_strip_edges": "abs(dec_deg - round(dec_deg)) < 0.001 AND dec_deg < 80"}.items():
    _registered[_name] = _edge_match(_w, _w)


@workload(f"""{_with()} SELECT count(*) AS n, sum(CASE WHEN abs(chord - dot) > 1e-3 THEN 1 ELSE 0 END) > 0 AS dot_is_worse FROM (
SELECT degrees(2 * asin(sqrt({_CHORD}) / 2)) * 3600e0 AS chord, degrees(acos(least(1e0, greatest(-1e0, o.x * d.x + o.y * d.y + o.z * d.z)))) * 3600e0 AS dot
FROM o JOIN d ON o.dec_deg BETWEEN d.dec_deg - 0.001 AND d.dec_deg + 0.001 AND {_CHORD} < 4 * power(sin(radians(1e0 / 3600e0) / 2), 2))""")
def distance_forms(spark, sf):
    """Does the dot product err by more than a thousandth of an arcsecond at small angles?"""
    return _distance_forms(_list(spark, sf), fixtures.objects(spark, sf))


def _distance_forms(s, o):
    p = match.attach_columns(match.match_zones(s, o, 1.0, 1 / 60), s.withColumnsRenamed({"x": "sx", "y": "sy", "z": "sz"}), o, ["sx", "sy", "sz"], ["x", "y", "z"])
    chord, dot = sky.sep_arcsec(sky.chord2("x", "y", "z", "sx", "sy", "sz")), sky.sep_dot("x", "y", "z", "sx", "sy", "sz")
    return p.agg(F.count(F.lit(1)).alias("n"), (F.sum(F.when(F.abs(chord - dot) > 1e-3, 1).otherwise(0)) > 0).alias("dot_is_worse"))


@workload(f"""WITH o AS ({_objects_sql('customer', 'c_custkey')}), d AS (SELECT object_id AS source_id, * EXCLUDE (object_id) FROM ({_objects_sql('supplier', 's_suppkey', 300)})) {_pairs_sql()}""")
def customer_supplier_match(spark, sf):
    o = fixtures.objects(spark, sf, "customer", "c_custkey")
    s = fixtures.objects(spark, sf, "supplier", "s_suppkey", 300).withColumnRenamed("object_id", "source_id")
    return match.match_zones(s, o, 1.0, 1 / 60, 1.0)


_VEC = "SELECT vec_id, a / n AS x, b / n AS y, c / n AS z FROM (SELECT *, sqrt(a * a + b * b + c * c) AS n FROM (SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS a, CAST(embedding[2] AS DOUBLE) AS b, CAST(embedding[3] AS DOUBLE) AS c FROM embeddings))"


@workload(f"""WITH v AS ({_VEC}) SELECT o.vec_id AS object_id, d.vec_id AS source_id, round(degrees(2 * asin(sqrt({_CHORD}) / 2)), 6) AS sep_deg
FROM v o JOIN v d ON o.vec_id < d.vec_id AND {_CHORD} < 4 * power(sin(radians(2e0) / 2), 2)""")
def vector_match_embeddings(spark, sf):
    """Vectors within 2 degrees by chord, as a self-match on zones and cells."""
    e = [F.col("embedding")[i].cast("double") for i in range(3)]
    v = read_table(spark, sf, "embeddings").select(F.col("vec_id").alias("object_id"), *[x.alias(c) for x, c in zip(e, "abc")]).withColumn("n", F.sqrt(F.col("a") * F.col("a") + F.col("b") * F.col("b") + F.col("c") * F.col("c")))
    v = v.select("object_id", *[(F.col(c) / F.col("n")).alias(x) for c, x in zip("abc", "xyz")]).select("*", *sky.radec("x", "y", "z"))
    p = match.match_zones(v.withColumnRenamed("object_id", "source_id"), v, 7200.0, 4.0, 6.0).where("object_id < source_id")
    w = v.select("object_id", "x", "y", "z")
    both = p.join(w, "object_id").join(w.select(F.col("object_id").alias("source_id"), *[F.col(c).alias(f"s{c}") for c in "xyz"]), "source_id")
    return both.select("object_id", "source_id", F.round(F.degrees(2 * F.asin(F.sqrt(sky.chord2("x", "y", "z", "sx", "sy", "sz")) / 2)), 6).alias("sep_deg"))


@workload(f"{_with(image=None)} SELECT *, CASE WHEN source_id IN (SELECT source_id FROM d WHERE dec_deg < 0) THEN 0 WHEN source_id IN (SELECT source_id FROM d WHERE dec_deg < 10) THEN 1 ELSE 2 END AS field FROM ({_pairs_sql()})")
def parallel_fields(spark, sf):
    return pipeline.parallel_fields(fixtures.detections(spark, sf), fixtures.objects(spark, sf), [(-90.0, 0.0), (0.0, 10.0), (10.0, 91.0)])


@workload(f"""{_with()}, p AS ({_pairs_sql()}), t AS (SELECT d.true_object AS object_id, d.source_id FROM d)
SELECT (SELECT count(*) FROM p) AS n_pairs, (SELECT count(*) FROM t) AS n_true, count(*) AS n_hit, count(*) / CAST((SELECT count(*) FROM t) AS DOUBLE) AS recall, count(*) / CAST((SELECT count(*) FROM p) AS DOUBLE) AS purity FROM p JOIN t USING (object_id, source_id)""")
def match_accuracy(spark, sf):
    s = _list(spark, sf)
    return match.match_accuracy(match.match_zones(s, fixtures.objects(spark, sf), 1.0, 1 / 60), s.select(F.col("true_object").alias("object_id"), "source_id"))


# association


def _holes(spark, sf):
    s, o = _list(spark, sf), fixtures.objects(spark, sf, holes=True)
    return s, o, match.match_zones(s, o, 1.0, 1 / 60, 1.0)


def _image_pairs(spark, sf):
    return match.match_zones(_list(spark, sf), fixtures.objects(spark, sf), 1.0, 1 / 60, 1.0)


@workload(f"{_with()}, p AS ({_pairs_sql()}) SELECT topology, count(*) AS n FROM ({_CLASS.format('p')}) GROUP BY topology")
def topology_counts(spark, sf):
    return associate.classify(_image_pairs(spark, sf)).groupBy("topology").agg(F.count(F.lit(1)).alias("n"))


@workload(f"{_with()}, p AS ({_pairs_sql()}) {_CLASS.format('p')}")
def topology_pairs(spark, sf):
    return associate.classify(_image_pairs(spark, sf))


@workload(f"{_with()}, {_RESOLVED} SELECT * FROM res")
def resolve_nearest(spark, sf):
    return associate.resolve(_image_pairs(spark, sf), "nearest")


@workload(f"""{_with()}, p AS ({_pairs_sql()}) SELECT object_id, source_id, sep_arcsec FROM (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY sep_arcsec, object_id) AS a,
row_number() OVER (PARTITION BY object_id ORDER BY sep_arcsec, source_id) AS b FROM p) WHERE a = 1 AND b = 1""")
def resolve_mutual_nearest(spark, sf):
    return associate.mutual_nearest(_image_pairs(spark, sf))


@workload(f"{_with()}, p AS ({_pairs_sql()}) SELECT * FROM p")
def resolve_all(spark, sf):
    return associate.resolve(_image_pairs(spark, sf), "all").select("object_id", "source_id", "sep_arcsec")


@workload(f"{_with(_objects_sql(where='k % 7 <> 0'))} SELECT source_id FROM d WHERE source_id NOT IN (SELECT source_id FROM ({_pairs_sql()}))")
def unmatched_sources(spark, sf):
    s, _, p = _holes(spark, sf)
    return associate.unmatched_sources(s, p).select("source_id")


@workload(f"""{_with(_objects_sql(where='k % 7 <> 0'))} SELECT object_id FROM o WHERE EXISTS (SELECT 1 FROM d WHERE floor(d.dec_deg) = floor(o.dec_deg) AND floor(d.ra_deg) = floor(o.ra_deg))
AND object_id NOT IN (SELECT object_id FROM ({_pairs_sql()}))""")
def missed_objects(spark, sf):
    s, o, p = _holes(spark, sf)
    return associate.missed_objects(o, p, s).select("object_id")


_GROUPS = """e AS (SELECT DISTINCT a.object_id AS a, b.object_id AS b{by} FROM p a JOIN p b USING (source_id)),
r AS (SELECT a AS o, a AS g{by} FROM e UNION SELECT e.b, r.g{by2} FROM r JOIN e ON e.a = r.o{on})"""


@workload(f"{_with().replace('WITH', 'WITH RECURSIVE', 1)}, p AS ({_pairs_sql()}), {_GROUPS.format(by='', by2='', on='')} SELECT p.*, g.group_id FROM p JOIN (SELECT o, min(g) AS group_id FROM r GROUP BY o) g ON g.o = p.object_id")
def topology_groups(spark, sf):
    """Connected groups of candidate pairs."""
    return associate.topology_groups(_image_pairs(spark, sf))


@workload(f"""{_with(_objects_sql(where='k % 7 <> 0'))}, {_RESOLVED},
a AS (SELECT object_id, count(*) AS k, sum(d.x) AS sx, sum(d.y) AS sy, sum(d.z) AS sz FROM res JOIN d USING (source_id) GROUP BY object_id),
u AS (SELECT o.object_id, CAST(1 + coalesce(k, 0) AS INTEGER) AS datapoints, o.x + coalesce((sx - k * o.x) / (1 + k), 0) AS x, o.y + coalesce((sy - k * o.y) / (1 + k), 0) AS y, o.z + coalesce((sz - k * o.z) / (1 + k), 0) AS z FROM o LEFT JOIN a USING (object_id)),
f AS (SELECT x, y, z FROM d WHERE source_id NOT IN (SELECT source_id FROM p))
SELECT datapoints, count(*) AS n, round(sum(z / sqrt(x * x + y * y + z * z)), 6) AS sum_z FROM (SELECT datapoints, x, y, z FROM u UNION ALL SELECT 1, x, y, z FROM f) GROUP BY datapoints""")
def catalog_update_one_image(spark, sf):
    """One image against the catalogue with holes, through a committed version: objects by data points."""
    cat = _static_catalog(spark, sf, holes=True)
    pipeline.step_image(cat, written(_list(spark, sf), "list"), IMAGE)
    return cat.all().groupBy("datapoints").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("z"), 6).alias("sum_z"))


def _buildup(images: int) -> str:
    """SQL of a cold start over the first images, unrolled; an object goes by the source that founded it."""
    parts = [f"d AS MATERIALIZED ({_DETECTIONS})", "o0 AS MATERIALIZED (SELECT source_id AS object_id, 1 AS datapoints, x, y, z, dec_deg FROM d WHERE image_id = 0)"]
    for k in range(1, images):
        pairs = _pairs_sql().replace("FROM o JOIN d ", f"FROM o{k - 1} o JOIN d{k} d ")
        parts += [
            f"d{k} AS MATERIALIZED (SELECT * FROM d WHERE image_id = {k})", f"p{k} AS MATERIALIZED ({pairs})", f"c{k} AS ({_CLASS.format(f'p{k}')})",
            f"k{k} AS MATERIALIZED (SELECT object_id, source_id FROM (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY sep_arcsec, object_id) AS nth FROM c{k}) WHERE topology <> 'many-to-many' OR nth = 1)",
            f"a{k} AS (SELECT object_id, count(*) AS k, sum(x) AS sx, sum(y) AS sy, sum(z) AS sz FROM k{k} JOIN d{k} USING (source_id) GROUP BY object_id)",
            f"u{k} AS (SELECT o.object_id, o.datapoints + k AS datapoints, " + ", ".join(f"o.{c} + (s{c} - k * o.{c}) / (o.datapoints + k) AS {c}" for c in "xyz") + f" FROM o{k - 1} o JOIN a{k} USING (object_id))",
            f"n{k} AS (SELECT object_id, datapoints, " + ", ".join(f"{c} / sqrt(x * x + y * y + z * z) AS {c}" for c in "xyz") + f", degrees(atan2(z, sqrt(x * x + y * y))) AS dec_deg FROM u{k})",
            f"""o{k} AS MATERIALIZED (SELECT * FROM n{k} UNION ALL SELECT * FROM o{k - 1} WHERE object_id NOT IN (SELECT object_id FROM a{k})
              UNION ALL SELECT source_id, 1, x, y, z, dec_deg FROM d{k} WHERE source_id NOT IN (SELECT source_id FROM p{k}))"""]
    return "WITH " + ",\n".join(parts)


_BUILT = f"{_buildup(3)} SELECT object_id AS first_source_id, CAST(datapoints AS INTEGER) AS datapoints, CAST(floor(dec_deg) AS INTEGER) AS strip, round(dec_deg, 7) AS mean_dec_deg FROM o2"
_NONE = "CAST(0 AS BIGINT)"


def _built(cat):
    return cat.all().select("first_source_id", "datapoints", "strip", sky.rounded("mean_dec_deg", 7).alias("mean_dec_deg"))


@workload(_BUILT)
def catalog_buildup_3(spark, sf):
    """A cold start over three images: the catalogue that is left."""
    return _built(pipeline.build_up(spark, fixtures.detections(spark, sf), [0, 1, 2])[0])


@workload(_BUILT)
def catalog_buildup_baseline_3(spark, sf):
    """The same by the baseline module."""
    return _built(pipeline.build_up(spark, fixtures.detections(spark, sf), [0, 1, 2], mode="baseline")[0])


@workload(_buildup(3) + " SELECT run_id, v.* FROM (VALUES ('baseline'), ('strips')) r(run_id), (" + " UNION ALL ".join(
    f"SELECT {k} AS image_id, {f'(SELECT count(*) FROM o{k - 1})' if k else _NONE} AS n_database, {f'(SELECT count(*) FROM p{k})' if k else _NONE} AS n_pairs, {f'(SELECT count(*) FROM k{k})' if k else _NONE} AS n_kept, "
    + (f"(SELECT count(*) FROM o{k}) - (SELECT count(*) FROM o{k - 1})" if k else "(SELECT count(*) FROM o0)") + " AS n_new" for k in range(3)) + ") v")
def bench_modules(spark, sf):
    """Baseline against partitioned module over three images: what each logs but for the seconds (`experiments.modules` has those)."""
    return experiments.module_counts(spark, fixtures.detections(spark, sf), [0, 1, 2])


@workload(f"SELECT query, image_id, n_database FROM (SELECT image_id, CAST(sum(n) OVER (ORDER BY image_id) AS BIGINT) AS n_database FROM ({_GROWTH}) WHERE image_id < 6), (VALUES ('bulk'), ('rowwise')) q(query)")
def bench_loading(spark, sf):
    """Bulk and row-wise loads of six lists into growing tables: the log but for the seconds."""
    return experiments.loading(spark, fixtures.detections(spark, sf), list(range(6))).select("query", "image_id", "n_database")


@workload()
def catalog_buildup_full(spark, sf):
    """A cold start over every image of the table: the catalogue that is left (too long for SQL; invariants, and equality with the loop, are tested)."""
    d = fixtures.detections(spark, sf)
    return pipeline.build_up(spark, d, sorted(r[0] for r in d.select("image_id").distinct().collect()), by_groups=True)[0].all()


@workload(f"SELECT image_id, count(DISTINCT strip) AS strips FROM (SELECT image_id, unnest(generate_series(CAST(floor(dec_deg - 1e0/3600 - 1e-9) AS BIGINT), CAST(floor(least(dec_deg + 1e0/3600 + 1e-9, 90)) AS BIGINT))) AS strip FROM ({_DETECTIONS})) GROUP BY image_id")
def image_footprints(spark, sf):
    return pipeline.footprints(fixtures.detections(spark, sf)).groupBy("image_id").agg(F.count(F.lit(1)).alias("strips"))


_FOOTPRINT = f"SELECT DISTINCT image_id, unnest(generate_series(CAST(floor(dec_deg - 1e0/3600 - 1e-9) AS BIGINT), CAST(floor(least(dec_deg + 1e0/3600 + 1e-9, 90)) AS BIGINT))) AS strip FROM ({_DETECTIONS})"


@workload(f"""WITH o AS ({_objects_sql()}), c AS (SELECT strip, count(*) AS n FROM o GROUP BY strip), f AS ({_FOOTPRINT})
SELECT image_id, CAST(coalesce(sum(n), 0) AS BIGINT) AS rows_touched, (SELECT count(*) FROM o) AS n_database FROM f LEFT JOIN c USING (strip) GROUP BY image_id""")
def rows_touched(spark, sf):
    return experiments.rows_touched(fixtures.detections(spark, sf), fixtures.objects(spark, sf))


@workload(f"""{_with()} SELECT width, dense, threshold, (SELECT count(*) FROM ({_pairs_sql()})) AS n_pairs
FROM (VALUES (0.1e0), (0.25e0), (1e0), (5e0), (180e0)) w(width), (VALUES (TRUE), (FALSE)) s(dense), (VALUES ('chord2'), ('angle')) t(threshold)""")
def bench_layouts(spark, sf):
    """Strip widths, sorted or not, by either threshold: the pairs that each finds."""
    return experiments.layouts(_list(spark, sf), fixtures.objects(spark, sf))


@workload(f"""WITH s AS (SELECT strip, count(*) AS n FROM ({_objects_sql()}) GROUP BY strip), b AS (SELECT strip, n, unnest(generate_series(0, n - 1, greatest(1, n // 8))) AS i FROM s)
SELECT strip, least(i + greatest(1, n // 8), n) AS points, CAST(sum(least(i + greatest(1, n // 8), n)) OVER (PARTITION BY strip ORDER BY i) AS BIGINT) AS tree_rebuilt, TRUE AS forest_rebuilds_less FROM b""")
def bench_tree(spark, sf):
    """Points that a tree rebuilt at every batch has rebuilt as objects come in, and that a forest rebuilds no more."""
    t = experiments.tree_growth(fixtures.objects(spark, sf))
    return t.select("strip", "points", "tree_rebuilt", (F.col("forest_rebuilt") <= F.col("tree_rebuilt")).alias("forest_rebuilds_less"))


@workload(f"{_with(image=None)} {_pairs_sql()}")
def match_in_waves(spark, sf):
    """Images that touch no common strip, matched together."""
    return pipeline.in_waves(fixtures.detections(spark, sf), fixtures.objects(spark, sf)).drop("wave")


# the same over all images: image_id is part of every key, and the catalogue with holes lacks what is first seen after image KNOWN

KNOWN = 2
_BY = ("image_id",)
_ALL = _with(image=None)
_SEEN = _with(_objects_sql(where=f"k IN (SELECT l_partkey FROM lineitem WHERE (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 <= {KNOWN})"), None)
_ALL_PAIRS = f"SELECT image_id, object_id, source_id, sep_arcsec FROM ({_pairs_sql()}) JOIN (SELECT image_id, source_id FROM d) USING (source_id)"
_ALL_CLASS = """SELECT *, CASE WHEN objects = 1 AND sources = 1 THEN 'one-to-one' WHEN objects = 1 THEN 'one-to-many' WHEN sources = 1 THEN 'many-to-one' ELSE 'many-to-many' END AS topology
  FROM (SELECT image_id, object_id, source_id, sep_arcsec, count(*) OVER (PARTITION BY image_id, source_id) AS objects, count(*) OVER (PARTITION BY image_id, object_id) AS sources FROM {})"""
_ALL_RESOLVED = f"""p AS ({_ALL_PAIRS}), c AS ({_ALL_CLASS.format('p')}),
  k AS (SELECT image_id, object_id, source_id, sep_arcsec FROM (SELECT *, row_number() OVER (PARTITION BY image_id, source_id ORDER BY sep_arcsec, object_id) AS nth FROM c) WHERE topology <> 'many-to-many' OR nth = 1), res AS ({_ALL_CLASS.format('k')})"""


def _all_pairs(spark, sf, objects=None):
    s = fixtures.detections(spark, sf)
    found = match.match_zones(s, fixtures.objects(spark, sf) if objects is None else objects, 1.0, 1 / 60, 1.0)
    return s, found.join(s.select("source_id", "image_id"), "source_id").select("image_id", "object_id", "source_id", "sep_arcsec")


def _all_places(spark, sf):
    return places.pairs(fixtures.detections(spark, sf), fixtures.objects(spark, sf))


@workload(_registered["ingest_source_list"][1].replace(f"WHERE image_id = {IMAGE}", ""))
def ingest_all_lists(spark, sf):
    d = written(fixtures.detections(spark, sf), "detections")
    return d.select("image_id", "source_id", *[F.round(c, 9).alias(c) for c in ("ra_deg", "dec_deg", "x", "y", "z")], "strip", "mjd", "flux", "band")


@workload(f"{_ALL} {_pairs_sql('d.r_arcsec')}")
def match_variable_radius_all_images(spark, sf):
    return match.match_zones(fixtures.detections(spark, sf), fixtures.objects(spark, sf), "r_arcsec", 1 / 60, 1.0)


@workload(f"""{_ALL}, p AS ({_pairs_sql()}), t AS (SELECT d.true_object AS object_id, d.source_id FROM d)
SELECT (SELECT count(*) FROM p) AS n_pairs, (SELECT count(*) FROM t) AS n_true, count(*) AS n_hit, count(*) / CAST((SELECT count(*) FROM t) AS DOUBLE) AS recall, count(*) / CAST((SELECT count(*) FROM p) AS DOUBLE) AS purity FROM p JOIN t USING (object_id, source_id)""")
def match_accuracy_all_images(spark, sf):
    return places.accuracy(fixtures.detections(spark, sf), fixtures.objects(spark, sf), "true_object")


@workload(f"{_ALL}, p AS ({_ALL_PAIRS}) SELECT topology, count(*) AS n FROM ({_ALL_CLASS.format('p')}) GROUP BY topology")
def topology_counts_all_images(spark, sf):
    return places.classify(_all_places(spark, sf), _BY).groupBy("topology").agg(F.sum("n").alias("n"))


@workload(f"{_ALL}, p AS ({_ALL_PAIRS}) {_ALL_CLASS.format('p')}")
def topology_pairs_all_images(spark, sf):
    return associate.classify(_all_pairs(spark, sf)[1], _BY)


@workload(f"""{_ALL.replace('WITH', 'WITH RECURSIVE', 1)}, p AS ({_ALL_PAIRS}), {_GROUPS.format(by=', a.image_id', by2=', e.image_id', on=' AND e.image_id = r.image_id').replace('SELECT a AS o, a AS g, a.image_id', 'SELECT a AS o, a AS g, image_id')}
SELECT p.*, g.group_id FROM p JOIN (SELECT image_id, o, min(g) AS group_id FROM r GROUP BY ALL) g ON g.o = p.object_id AND g.image_id = p.image_id""")
def topology_groups_all_images(spark, sf):
    """Connected groups of candidate pairs within each image."""
    return places.expand(places.topology_groups(written(_all_places(spark, sf), "pairs"), "image_id"), fixtures.objects(spark, sf))


@workload(f"{_ALL}, {_ALL_RESOLVED} SELECT * FROM res")
def resolve_nearest_all_images(spark, sf):
    return places.expand(places.resolve(_all_places(spark, sf), _BY), fixtures.objects(spark, sf))


@workload(f"""{_ALL}, p AS ({_ALL_PAIRS}) SELECT image_id, object_id, source_id, sep_arcsec FROM (SELECT *, row_number() OVER (PARTITION BY image_id, source_id ORDER BY sep_arcsec, object_id) AS a,
row_number() OVER (PARTITION BY image_id, object_id ORDER BY sep_arcsec, source_id) AS b FROM p) WHERE a = 1 AND b = 1""")
def resolve_mutual_nearest_all_images(spark, sf):
    return associate.mutual_nearest(_all_pairs(spark, sf)[1], _BY)


@workload(f"{_ALL}, p AS ({_ALL_PAIRS}) SELECT * FROM p")
def resolve_all_all_images(spark, sf):
    return associate.resolve(_all_pairs(spark, sf)[1], "all", _BY).select("image_id", "object_id", "source_id", "sep_arcsec")


@workload(f"{_SEEN}, p AS ({_ALL_PAIRS}) SELECT image_id, source_id FROM d WHERE source_id NOT IN (SELECT source_id FROM p)")
def unmatched_sources_all_images(spark, sf):
    s, p = _all_pairs(spark, sf, fixtures.known_objects(spark, sf, KNOWN))
    return associate.unmatched_sources(s, p.drop("image_id")).select("image_id", "source_id")


@workload(f"""{_SEEN}, p AS ({_ALL_PAIRS}), f AS (SELECT DISTINCT image_id, floor(dec_deg) AS zone, floor(ra_deg) AS cell FROM d)
SELECT f.image_id, o.object_id FROM o JOIN f ON f.zone = floor(o.dec_deg) AND f.cell = floor(o.ra_deg) WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.image_id = f.image_id AND p.object_id = o.object_id)""")
def missed_objects_all_images(spark, sf):
    o = fixtures.known_objects(spark, sf, KNOWN)
    s, p = _all_pairs(spark, sf, o)
    return associate.missed_objects(o, p, s, by=_BY).select("image_id", "object_id")


@workload(f"""{_SEEN}, p AS ({_ALL_PAIRS}), f AS (SELECT DISTINCT image_id, floor(dec_deg) AS zone, floor(ra_deg) AS cell FROM d)
SELECT image_id, 'new' AS kind, source_id, CAST(NULL AS BIGINT) AS object_id FROM d WHERE source_id NOT IN (SELECT source_id FROM p)
UNION ALL SELECT f.image_id, 'gone', NULL, o.object_id FROM o JOIN f ON f.zone = floor(o.dec_deg) AND f.cell = floor(o.ra_deg) WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.image_id = f.image_id AND p.object_id = o.object_id)""")
def transient_candidates(spark, sf):
    """Sources that may be new and objects that may be gone, image by image."""
    o = written(fixtures.known_objects(spark, sf, KNOWN), "known")
    s = written(fixtures.detections(spark, sf).select("image_id", "source_id", "ra_deg", "dec_deg", "x", "y", "z"), "lists")
    return places.candidates(o, written(places.pairs(s, o).select("image_id", "place", "source_id"), "pairs"), s, _BY)


@workload(_registered["distance_forms"][1].replace(f"WHERE image_id = {IMAGE}", ""))
def distance_forms_all_images(spark, sf):
    return places.distance_forms(fixtures.detections(spark, sf), fixtures.objects(spark, sf))


@workload(_registered["bench_layouts"][1].replace(f"WHERE image_id = {IMAGE}", ""))
def bench_layouts_all_images(spark, sf):
    return experiments.layouts(fixtures.detections(spark, sf), fixtures.objects(spark, sf))


@workload(f"{_ALL}, {_ALL_RESOLVED} SELECT object_id, source_id, d.image_id, mjd, flux, flux_err, sep_arcsec, topology FROM res JOIN d USING (source_id)")
def lightcurve_points_all_images(spark, sf):
    o = fixtures.objects(spark, sf)
    p = places.pairs(fixtures.detections(spark, sf), o, ("image_id", "mjd", "flux", "flux_err"))
    return conform(places.expand(places.resolve(p, _BY), o), LIGHTCURVE)


# light curves: resolved pairs of the static catalogue


def _curve(spark, sf):
    s = _list(spark, sf)
    return lightcurve.points(associate.resolve(match.match_zones(s, fixtures.objects(spark, sf), 1.0, 1 / 60, 1.0)), s)


_CURVE = f"{_with()}, {_RESOLVED}, lc AS (SELECT object_id, source_id, image_id, mjd, flux, flux_err, sep_arcsec, topology FROM res JOIN d USING (source_id))"
_TRUE = f"lc AS (SELECT true_object AS object_id, source_id, mjd, flux, flux_err FROM ({_DETECTIONS}))"


def _true_curve(spark, sf):
    return fixtures.detections(spark, sf).select(F.col("true_object").alias("object_id"), "source_id", "mjd", "flux", "flux_err")


@workload(f"{_CURVE} SELECT * FROM lc")
def lightcurve_points(spark, sf):
    return _curve(spark, sf)


_STATS = """SELECT object_id, count(*) AS n, min(mjd) AS mjd_min, max(mjd) AS mjd_max, avg(flux) AS mean_flux, stddev_samp(flux) AS sd_flux, stddev_samp(flux) / avg(flux) AS scatter,
CASE WHEN count(*) > 1 THEN (sum(flux * flux / (flux_err * flux_err)) - power(sum(flux / (flux_err * flux_err)), 2) / sum(1 / (flux_err * flux_err))) / (count(*) - 1) END AS chi2 FROM lc GROUP BY object_id"""


@workload(f"WITH {_TRUE} SELECT object_id, n, mjd_min, mjd_max, round(mean_flux + 1e-6, 2) AS mean_flux, round(sd_flux + 1e-6, 2) AS sd_flux, round(scatter, 5) AS scatter, round(chi2, 4) AS chi2 FROM ({_STATS})")
def lightcurve_stats(spark, sf):
    s = lightcurve.statistics(_true_curve(spark, sf))
    return s.select("object_id", "n", "mjd_min", "mjd_max", *[F.round(F.col(c) + e, d).alias(c) for c, d, e in (("mean_flux", 2, 1e-6), ("sd_flux", 2, 1e-6), ("scatter", 5, 0.0), ("chi2", 4, 0.0))])


@workload(f"WITH {_TRUE}, o AS ({_objects_sql()}), c AS ({_vector('SELECT 359.9e0 AS ra_deg, 0.5e0 AS dec_deg')}) SELECT lc.* FROM lc JOIN o USING (object_id), c d WHERE {_CHORD} < 4 * power(sin(radians(0.5e0) / 2), 2)")
def lightcurves_of_cone(spark, sf):
    return lightcurve.of_cone(_true_curve(spark, sf), fixtures.objects(spark, sf), 359.9, 0.5, 0.5)


@workload(f"WITH {_TRUE}, o AS ({_objects_sql()}) SELECT lc.* FROM lc JOIN o USING (object_id) WHERE (o.ra_deg >= 359.5 OR o.ra_deg <= 0.2) AND o.dec_deg BETWEEN -1 AND 1")
def lightcurves_of_box(spark, sf):
    """A box that goes through right ascension 0."""
    return lightcurve.of_box(_true_curve(spark, sf), fixtures.objects(spark, sf), (359.5, 360.2), (-1.0, 1.0))


@workload(f"WITH {_TRUE} SELECT object_id, n FROM ({_STATS}) WHERE n >= 5 AND scatter > 0.5")
def variability(spark, sf):
    return lightcurve.variability(_true_curve(spark, sf)).select("object_id", "n")


@workload(f"WITH {_TRUE} SELECT object_id, source_id, lag(source_id) OVER w AS prev_source_id, mjd - lag(mjd) OVER w AS gap_days, round(flux - lag(flux) OVER w, 4) AS flux_change FROM lc WINDOW w AS (PARTITION BY object_id ORDER BY mjd, source_id)")
def previous_detection(spark, sf):
    return lightcurve.previous(_true_curve(spark, sf)).select("object_id", "source_id", "prev_source_id", "gap_days", F.round("flux_change", 4).alias("flux_change"))


@workload(f"WITH {_TRUE} SELECT object_id, len(list(mjd)) AS n, round(sum(flux), 4) AS total FROM lc GROUP BY object_id")
def folded_lightcurves(spark, sf):
    f = lightcurve.folded(_true_curve(spark, sf))
    return f.select("object_id", F.size("points").cast("long").alias("n"), F.round(F.aggregate("points", F.lit(0.0), lambda a, p: a + p["flux"]), 4).alias("total"))


# ids


@workload("SELECT max(l_orderkey) AS max_id FROM lineitem")
def max_id_scan(spark, sf):
    return ids.max_id_scan(read_table(spark, sf, "lineitem"), "l_orderkey")


@workload("SELECT max(l_orderkey) AS max_id FROM lineitem")
def max_id_footer(spark, sf):
    return ids.max_id_footer(spark, f"{sf}/lineitem.parquet", "l_orderkey")


@workload("SELECT max(p_partkey) AS max_id FROM part")
def max_id_counter(spark, sf):
    """From the counter in the manifest (set when the catalogue was made), without reading a table."""
    return spark.createDataFrame([(_static_catalog(spark, sf).ids.value - 1,)], "max_id long")


# reads


_CONE = f"round(degrees(2 * asin(sqrt({_CHORD}) / 2)) * 3600e0, 6) AS sep_arcsec"


@workload(f"WITH o AS ({_objects_sql()}), d AS ({_vector('SELECT 359.9e0 AS ra_deg, 0.5e0 AS dec_deg')}) SELECT o.object_id, {_CONE} FROM o, d WHERE {_CHORD} < 4 * power(sin(radians(0.5e0) / 2), 2)")
def cone_search(spark, sf):
    return match.cone_search(fixtures.objects(spark, sf), 359.9, 0.5, 0.5)


@workload(f"WITH o AS ({_objects_sql()}), d AS (SELECT object_id AS source_id, * EXCLUDE (object_id) FROM ({_objects_sql('supplier', 's_suppkey')})) SELECT o.object_id, d.source_id, {_CONE} FROM o JOIN d ON {_CHORD} < 4 * power(sin(radians(0.05e0) / 2), 2)")
def cone_search_bulk(spark, sf):
    s = fixtures.objects(spark, sf, "supplier", "s_suppkey").withColumnRenamed("object_id", "source_id")
    return match.match_zones(s, fixtures.objects(spark, sf), 180.0, 0.25, 1.0)


@workload(f"SELECT strip, count(*) AS objects FROM ({_objects_sql()}) GROUP BY strip")
def strip_histogram(spark, sf):
    return fixtures.objects(spark, sf).groupBy("strip").agg(F.count(F.lit(1)).alias("objects"))


@workload(f"""SELECT CAST(floor(dec_deg / 10) AS INTEGER) AS band, strip, CAST(floor(ra_deg) AS INTEGER) AS cell, count(*) AS objects, CAST(grouping(band, strip, cell) AS BIGINT) AS level
FROM (SELECT *, CAST(floor(dec_deg / 10) AS INTEGER) AS band, CAST(floor(ra_deg) AS INTEGER) AS cell FROM ({_objects_sql()})) GROUP BY ROLLUP (band, strip, cell)""".replace("CAST(floor(dec_deg / 10) AS INTEGER) AS band, strip, CAST(floor(ra_deg) AS INTEGER) AS cell, count", "band, strip, cell, count"))
def sky_layers(spark, sf):
    """All sky, ten-degree bands, strips, cells: one rollup."""
    o = fixtures.objects(spark, sf).select(F.floor(F.col("dec_deg") / 10).cast("int").alias("band"), "strip", F.floor("ra_deg").cast("int").alias("cell"))
    return o.rollup("band", "strip", "cell").agg(F.count(F.lit(1)).alias("objects"), F.grouping_id().cast("long").alias("level"))


@workload("SELECT r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def region_layers(spark, sf):
    c, n, r = (read_table(spark, sf, t) for t in ("customer", "nation", "region"))
    return c.join(n, c["c_nationkey"] == n["n_nationkey"]).join(r, n["n_regionkey"] == r["r_regionkey"]).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


# measures, over a log whose seconds are set by the growth curve: a constant query, one linear in N, one linear in rows


def _r(c: str):
    """Six places. Sums of exact decimals sit on ties; a shift far below the last place moves them off."""
    return F.round(F.col(c) + 1e-9, 6)


def _log(spark, sf):
    g = _sizes(spark, sf).withColumn("q", F.explode(F.array(F.lit("constant"), F.lit("scan"), F.lit("baseline"))))
    s = F.when(F.col("q") == "constant", F.lit(0.5)).when(F.col("q") == "scan", F.col("n_database") * 1e-4).otherwise(F.col("n_database") * F.col("n").cast("double") * 1e-7)
    return g.select(F.lit("run").alias("run_id"), "image_id", F.lit("associate").alias("step"), F.col("q").alias("query"), s.alias("seconds"), F.col("n").alias("rows_out"), F.lit(0).cast("long").alias("rows_scanned"), "n_database")


_LOG = f"""g AS (SELECT image_id, n, CAST(sum(n) OVER (ORDER BY image_id) AS BIGINT) AS n_database FROM ({_GROWTH})),
lg AS (SELECT 'run' AS run_id, image_id, 'constant' AS query, 0.5e0 AS seconds, n AS rows_out, n_database FROM g UNION ALL SELECT 'run', image_id, 'scan', n_database * 1e-4, n, n_database FROM g
UNION ALL SELECT 'run', image_id, 'baseline', n_database * CAST(n AS DOUBLE) * 1e-7, n, n_database FROM g)"""


@workload(f"WITH {_LOG} SELECT run_id, query, image_id, round(seconds + 1e-9, 6) AS seconds, round(sum(seconds) OVER (PARTITION BY query ORDER BY image_id) + 1e-9, 6) AS accumulated FROM lg")
def measure_accumulated(spark, sf):
    return metrics.accumulated(_log(spark, sf)).select("run_id", "query", "image_id", _r("seconds").alias("seconds"), _r("accumulated").alias("accumulated"))


@workload(f"WITH {_LOG} SELECT run_id, query, image_id, round(seconds + 1e-9, 6) AS seconds, n_database FROM lg")
def measure_instantaneous(spark, sf):
    return metrics.instantaneous(_log(spark, sf)).withColumn("seconds", _r("seconds"))


@workload(f"WITH {_LOG} SELECT run_id, image_id, round(sum(seconds) + 1e-9, 6) AS seconds, max(n_database) AS n_database FROM lg GROUP BY ALL")
def measure_per_image(spark, sf):
    return metrics.per_image(_log(spark, sf)).withColumn("seconds", _r("seconds"))


@workload(f"WITH {_LOG} SELECT run_id, query, CAST((image_id >= 20)::INT + (image_id >= 60)::INT AS INTEGER) AS band, round(avg(seconds) + 1e-9, 6) AS seconds, round(avg(rows_out) + 1e-9, 6) AS rows_out, count(*) AS n FROM lg GROUP BY ALL")
def measure_banded(spark, sf):
    return metrics.banded(_log(spark, sf), [20, 60]).withColumns({"seconds": _r("seconds"), "rows_out": _r("rows_out")})


@workload(f"WITH {_LOG} SELECT query, round(regr_slope(ln(seconds), ln(n_database)), 4) AS slope_n, CASE WHEN regr_slope(ln(seconds), ln(n_database)) < 0.2 THEN 'constant' WHEN regr_slope(ln(seconds), ln(n_database)) < 0.8 THEN 'sublinear' WHEN regr_slope(ln(seconds), ln(n_database)) <= 1.25 THEN 'linear in N' ELSE 'N times M' END AS class FROM lg GROUP BY query")
def measure_scaling_class(spark, sf):
    return metrics.scaling_class(_log(spark, sf)).select("query", F.round("slope_n", 4).alias("slope_n"), "class")


@workload(f"WITH {_LOG}, c AS (SELECT query, regr_slope(ln(seconds), ln(n_database)) AS s FROM lg GROUP BY query) SELECT 'run' AS run_id, round(avg(CASE WHEN s >= 0.8 THEN 1e0 ELSE 0e0 END) + 1e-9, 6) AS linear_share FROM c")
def measure_linear_share(spark, sf):
    return metrics.linear_share(metrics.scaling_class(_log(spark, sf))).withColumn("linear_share", _r("linear_share"))


@workload(f"WITH {_LOG} SELECT run_id, round(sum(seconds) + 1e-9, 6) AS query_seconds, 1e6 AS pipeline_seconds, round(1e6 - sum(seconds) + 1e-9, 6) AS overhead_seconds FROM lg GROUP BY run_id")
def measure_totals(spark, sf):
    return metrics.totals(_log(spark, sf), 1e6).withColumns({c: _r(c) for c in ("query_seconds", "overhead_seconds")})


@workload(f"WITH {_LOG}, i AS (SELECT image_id, sum(seconds) AS s FROM lg GROUP BY image_id) SELECT 'run' AS run_id, round(max(s) + 1e-9, 6) AS limiting_cadence, round(avg(s) + 1e-9, 6) AS mean_seconds, max(s) <= 60 AS keeps_up, avg(s) <= 60 AS average_keeps_up FROM i")
def measure_cadence(spark, sf):
    return metrics.cadence_report(_log(spark, sf), 60.0).withColumns({c: _r(c) for c in ("limiting_cadence", "mean_seconds")})


@workload(f"""WITH {_LOG}, i AS (SELECT image_id, sum(seconds) AS seconds, max(n_database) AS n_database FROM lg GROUP BY image_id), c AS (SELECT *, sum(seconds - 5e0) OVER (ORDER BY image_id) AS s FROM i)
SELECT 'run' AS run_id, image_id, round(seconds + 1e-9, 6) AS seconds, n_database, round(s - least(min(s) OVER (ORDER BY image_id), 0) + 1e-9, 6) AS waiting FROM c""")
def measure_backlog(spark, sf):
    return metrics.backlog(_log(spark, sf), 5.0).withColumns({c: _r(c) for c in ("seconds", "waiting")})


@workload(f"WITH {_LOG} SELECT query, round(avg(seconds) + 1e-9, 6) AS mean, round(stddev_samp(seconds) + 1e-9, 6) AS sd FROM lg GROUP BY query")
def measure_spread(spark, sf):
    return metrics.spread(_log(spark, sf)).select("query", _r("mean").alias("mean"), _r("sd").alias("sd"))


@workload(f"WITH {_LOG} SELECT query, CASE WHEN regr_slope(seconds, n_database) > 1e-12 THEN round((60 - regr_intercept(seconds, n_database)) / regr_slope(seconds, n_database)) END AS rows_at_cadence FROM lg WHERE query = 'scan' GROUP BY query")
def measure_time_to_cadence(spark, sf):
    return metrics.time_to_cadence(metrics.scaling_class(_log(spark, sf)), 60.0).where("query = 'scan'").select("query", F.round("rows_at_cadence").alias("rows_at_cadence"))


@workload("SELECT mode, images_per_night, images_per_night * 170000 AS sources_per_night, images_per_night * 170000 * 402 / 1e9 AS gb_per_night FROM (VALUES ('nominal', 120::BIGINT), ('fast', 600::BIGINT)) t(mode, images_per_night)")
def volume_model(spark, sf):
    return metrics.capacity(spark)


# streams


@workload("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS \"end\", count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def stream_windows(spark, sf):
    """Events per hour: the windowed plan that also runs on a stream."""
    return lists.counts_per_window(read_table(spark, sf, "events")).withColumn("total", F.round("total", 4))


@workload("""SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS "end", count(*) AS n, round(sum(value), 4) AS total FROM events
GROUP BY 1 HAVING time_bucket(INTERVAL 1 HOUR, any_value(ts)) + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""")
def stream_ingest(spark, sf):
    """The same through a file stream and a watermark, run over all that is there; windows still open are not emitted."""
    schema = read_table(spark, sf, "events").schema
    root = f"{shared_dir(spark)}/stripmatch/stream-{uuid.uuid4().hex}"
    read_table(spark, sf, "events").repartitionByRange(4, "ts").write.parquet(f"{root}/in")
    q = lists.counts_per_window(lists.list_stream(spark, f"{root}/in", schema, 10)).writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{root}/out").withColumn("total", F.round("total", 4))


@workload(f"{_with()} {_pairs_sql()}")
def stream_match(spark, sf):
    """A month's list as files, matched batch by batch."""
    root = f"{shared_dir(spark)}/stripmatch/stream-{uuid.uuid4().hex}"
    s = _list(spark, sf).select("source_id", "ra_deg", "dec_deg", "x", "y", "z")
    s.repartition(3, "source_id").write.parquet(f"{root}/in")
    lists.match_stream(lists.list_stream(spark, f"{root}/in", s.schema), lambda: fixtures.objects(spark, sf), f"{root}/out", f"{root}/checkpoint").awaitTermination()
    return spark.read.parquet(f"{root}/out").drop("batch")


def queries() -> dict:
    return {k: f for k, (f, _) in _registered.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _registered.items() if s}
