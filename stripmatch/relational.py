"""Relational, scalar and streaming operators that users of the catalogue need beside the match, as registered workloads."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType
from pyspark.sql.window import Window

from stripmatch.cluster import read_table, shared_dir, ship
from stripmatch.functions import sky
from stripmatch.operators import lightcurve, match
from stripmatch.sources import fixtures
from stripmatch.streaming import lists
from stripmatch.workloads import _DETECTIONS, _TRUE, _all_pairs, _image_pairs, _pairs_sql, _true_curve, _with, workload

_D = f"WITH d AS ({_DETECTIONS})"


# joins


@workload(f"""{_with()}, p AS ({_pairs_sql()}) SELECT s.source_id, t.object_id, t.sep_arcsec FROM (SELECT DISTINCT source_id FROM p) s,
LATERAL (SELECT object_id, sep_arcsec FROM p WHERE p.source_id = s.source_id ORDER BY sep_arcsec, object_id LIMIT 2) t""")
def nearest_two_lateral(spark, sf):
    """Each source's two nearest objects, as a lateral join with a limit (the planner turns it into a window)."""
    text = """SELECT s.source_id, t.object_id, t.sep_arcsec FROM (SELECT DISTINCT source_id FROM {p}) s,
      LATERAL (SELECT object_id, sep_arcsec FROM {p} p WHERE p.source_id = s.source_id ORDER BY sep_arcsec, object_id LIMIT 2) t"""
    return spark.sql(text, p=_image_pairs(spark, sf))


@workload("""SELECT coalesce(c_nationkey, s_nationkey) AS nation, count(DISTINCT c_custkey) AS customers, count(DISTINCT s_suppkey) AS suppliers
FROM customer FULL JOIN supplier ON c_nationkey = s_nationkey AND c_custkey % 7 = s_suppkey % 7 GROUP BY 1""")
def catalogue_difference(spark, sf):
    """A full outer join of two catalogues."""
    c, s = read_table(spark, sf, "customer"), read_table(spark, sf, "supplier")
    both = c.join(s, (c["c_nationkey"] == s["s_nationkey"]) & (F.col("c_custkey") % 7 == F.col("s_suppkey") % 7), "full")
    return both.groupBy(F.coalesce("c_nationkey", "s_nationkey").alias("nation")).agg(F.count_distinct("c_custkey").alias("customers"), F.count_distinct("s_suppkey").alias("suppliers"))


@workload("SELECT o_orderpriority, count(*) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def bucketed_join(spark, sf):
    """Two tables of the metastore, bucketed alike, joined without an exchange."""
    name = uuid.uuid4().hex
    spark.sql(f"DROP TABLE IF EXISTS lines_{name}")
    for table, key in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        read_table(spark, sf, table).write.bucketBy(8, key).sortBy(key).saveAsTable(f"{table}_{name}")
    left, right = (spark.table(f"{t}_{name}") for t in ("lineitem", "orders"))
    return left.join(right.hint("merge"), left["l_orderkey"] == right["o_orderkey"]).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"))


# aggregates


@workload(f"""{_D}, b AS (SELECT image_id, source_id, row_number() OVER (PARTITION BY image_id ORDER BY flux DESC, source_id DESC) AS nth, row_number() OVER (PARTITION BY image_id ORDER BY flux, source_id) AS last FROM d)
SELECT d.image_id, count(DISTINCT true_object) AS objects, TRUE AS approximate_fits, count(*) FILTER (band = 'F') AS finished, round(quantile_cont(flux, 0.5), 4) AS middle,
  max(CASE WHEN nth = 1 THEN b.source_id END) AS brightest, max(CASE WHEN last = 1 THEN b.source_id END) AS faintest, round(corr(flux, area), 6) AS correlation, round(covar_samp(ellipticity, area), 6) AS covariance
FROM d JOIN b USING (source_id) GROUP BY d.image_id""")
def image_aggregates(spark, sf):
    """Distinct and approximate counts, filtered counts, percentiles, extremes by another column, correlations."""
    by = F.struct("flux", "source_id")
    a = fixtures.detections(spark, sf).groupBy("image_id").agg(
        F.count_distinct("true_object").alias("objects"), F.approx_count_distinct("true_object", 0.02).alias("near"), F.count_if(F.col("band") == "F").alias("finished"),
        F.round(F.percentile("flux", F.lit(0.5)), 4).alias("middle"), F.max_by("source_id", by).alias("brightest"), F.min_by("source_id", by).alias("faintest"),
        F.round(F.corr("flux", "area"), 6).alias("correlation"), F.round(F.covar_samp("ellipticity", "area"), 6).alias("covariance"))
    return a.withColumn("approximate_fits", F.abs(F.col("near") - F.col("objects")) <= 1 + 0.1 * F.col("objects")).drop("near")


@workload(f"{_D} SELECT image_id, count(*) FILTER (quality = 'A') AS a, count(*) FILTER (quality = 'N') AS n, count(*) FILTER (quality = 'R') AS r FROM d GROUP BY image_id")
def quality_pivot(spark, sf):
    p = fixtures.detections(spark, sf).groupBy("image_id").pivot("quality", ["A", "N", "R"]).agg(F.count(F.lit(1)))
    return p.select("image_id", *[F.coalesce(c, F.lit(0)).cast("long").alias(c.lower()) for c in "ANR"])


@workload(f"{_D} SELECT year, band, quality, count(*) AS n, CAST(grouping(year, band, quality) AS BIGINT) AS level FROM (SELECT *, image_id // 12 AS year FROM d) GROUP BY CUBE (year, band, quality)")
def detection_cube(spark, sf):
    d = fixtures.detections(spark, sf).withColumn("year", F.floor(F.col("image_id") / 12).cast("int"))
    return d.cube("year", "band", "quality").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


# windows


@workload(f"""{_D} SELECT source_id, row_number() OVER w AS nth, rank() OVER f AS ranked, dense_rank() OVER f AS dense, ntile(4) OVER w AS quarter, round(percent_rank() OVER f, 9) AS share, round(cume_dist() OVER f, 9) AS below
FROM d WINDOW w AS (PARTITION BY image_id ORDER BY flux, source_id), f AS (PARTITION BY image_id ORDER BY area)""")
def flux_ranks(spark, sf):
    w, f = Window.partitionBy("image_id").orderBy("flux", "source_id"), Window.partitionBy("image_id").orderBy("area")
    return fixtures.detections(spark, sf).select(
        "source_id", F.row_number().over(w).cast("long").alias("nth"), F.rank().over(f).cast("long").alias("ranked"), F.dense_rank().over(f).cast("long").alias("dense"), F.ntile(4).over(w).cast("long").alias("quarter"),
        F.round(F.percent_rank().over(f), 9).alias("share"), F.round(F.cume_dist().over(f), 9).alias("below"))


@workload(f"""WITH {_TRUE} SELECT object_id, source_id, lead(source_id) OVER w AS next_source, first_value(source_id) OVER w AS first_source, nth_value(source_id, 2) OVER w AS second_source,
round(avg(flux) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS rolling, count(*) OVER (PARTITION BY object_id ORDER BY mjd RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS month FROM lc WINDOW w AS (PARTITION BY object_id ORDER BY mjd, source_id)""")
def lightcurve_frames(spark, sf):
    """Neighbours and frames of rows and of days."""
    w = Window.partitionBy("object_id").orderBy("mjd", "source_id")
    days = Window.partitionBy("object_id").orderBy("mjd").rangeBetween(-30, 0)
    return _true_curve(spark, sf).select(
        "object_id", "source_id", F.lead("source_id").over(w).alias("next_source"), F.first("source_id").over(w).alias("first_source"), F.nth_value("source_id", 2).over(w).alias("second_source"),
        F.round(F.avg("flux").over(w.rowsBetween(-2, 0)), 4).alias("rolling"), F.count(F.lit(1)).over(days).alias("month"))


# sets and subqueries


@workload(f"""{_D}, a AS (SELECT true_object AS k FROM d WHERE image_id % 2 = 0), b AS (SELECT true_object AS k FROM d WHERE image_id % 2 = 1)
SELECT 'union' AS kind, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'union all', count(*) FROM (SELECT * FROM a UNION ALL SELECT * FROM b)
UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'intersect all', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b)
UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'except all', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)""")
def seen_sets(spark, sf):
    """Set operations on the objects that even and odd images saw."""
    d = fixtures.detections(spark, sf)
    a, b = (d.where(F.col("image_id") % 2 == x).select(F.col("true_object").alias("k")) for x in (0, 1))
    kinds = {"union": a.union(b).distinct(), "union all": a.unionByName(b), "intersect": a.intersect(b), "intersect all": a.intersectAll(b), "except": a.subtract(b), "except all": a.exceptAll(b)}
    out = None
    for kind, df in kinds.items():
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
        out = one if out is None else out.unionByName(one)
    return out


_SUB = """SELECT c_custkey, c_acctbal FROM {customer} c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {customer}) AND c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey < 3)
AND EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey) AND c_acctbal >= (SELECT avg(b.c_acctbal) FROM {customer} b WHERE b.c_nationkey = c.c_nationkey)"""


@workload(_SUB.format(customer="customer", nation="nation", orders="orders"))
def nested_selections(spark, sf):
    """Scalar, IN, EXISTS and correlated subqueries."""
    return spark.sql(_SUB, **{t: read_table(spark, sf, t) for t in ("customer", "nation", "orders")})


_HALVED = """WITH RECURSIVE h(level, width) AS (SELECT 0, CAST(180 AS DOUBLE) UNION ALL SELECT level + 1, width / 2 FROM h WHERE level < 8)
SELECT level, width, count(DISTINCT floor(dec_deg / width)) AS strips FROM h CROSS JOIN {o} o GROUP BY level, width"""


@workload(_HALVED.format(o=f"({_with().split('o AS (', 1)[1].rsplit('), d AS', 1)[0]})"))
def halved_strips(spark, sf):
    """Occupied strips at halving widths, by a recursive CTE."""
    return spark.sql(_HALVED, o=fixtures.objects(spark, sf))


@workload("SELECT TRUE AS whole_within, TRUE AS strips_kept")
def strip_sample(spark, sf):
    """Samples of the catalogue: of all, and by strip."""
    o = fixtures.objects(spark, sf)
    strips = [r[0] for r in o.select("strip").distinct().collect()]
    some, by = o.sample(0.5, seed=7), o.sampleBy("strip", {s: 1.0 if s < 0 else 0.0 for s in strips}, seed=7)
    n, k, below = o.count(), some.count(), o.where("strip < 0").count()
    return spark.createDataFrame([(abs(k - n / 2) < 4 * n**0.5, by.count() == below)], "whole_within boolean, strips_kept boolean")


# scalar functions


@workload("""SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS path_k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS variant_k,
'{"id":' || event_id || ',"k":' || json_extract_string(props, '$.k') || '}' AS again, coalesce(json_extract_string(props, '$.none'), 'absent') AS missing FROM events""")
def event_properties(spark, sf):
    """Properties of events by schema, by path and as variants, and back to text."""
    e = read_table(spark, sf, "events")
    k = F.from_json("props", "k long")["k"]
    return e.select(
        "event_id", k.alias("k"), F.get_json_object("props", "$.k").cast("long").alias("path_k"), F.variant_get(F.parse_json("props"), "$.k", "long").alias("variant_k"),
        F.to_json(F.struct(F.col("event_id").alias("id"), k.alias("k"))).alias("again"), F.coalesce(F.get_json_object("props", "$.none"), F.lit("absent")).alias("missing"))


@workload("""SELECT p_partkey, upper(trim(p_name)) AS name, regexp_extract(p_brand, '([0-9]+)', 1) AS number, string_split(p_type, ' ')[1] AS kind, lpad(CAST(p_partkey AS VARCHAR), 8, '0') AS padded,
substr(p_name, 1, 3) || ':' || CAST(p_size AS VARCHAR) AS tag, CAST(levenshtein(p_name, p_type) AS BIGINT) AS far, p_name LIKE '%a%' AS has_a, regexp_matches(p_type, '[A-Z]{3}') AS has_upper, nullif(p_size, 1) AS size FROM part""")
def part_labels(spark, sf):
    p = read_table(spark, sf, "part")
    return p.select(
        "p_partkey", F.upper(F.trim("p_name")).alias("name"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("number"), F.split("p_type", " ")[0].alias("kind"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"),
        F.concat(F.substring("p_name", 1, 3), F.lit(":"), F.col("p_size").cast("string")).alias("tag"), F.levenshtein("p_name", "p_type").cast("long").alias("far"), F.col("p_name").like("%a%").alias("has_a"),
        F.col("p_type").rlike("[A-Z]{3}").alias("has_upper"), F.nullif("p_size", F.lit(1)).alias("size"))


@workload("""SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS year, CAST(month(o_orderdate) AS INTEGER) AS month, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS start, CAST(CAST(o_orderdate + INTERVAL 36 HOUR AS DATE) AS VARCHAR) AS later,
CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, round(40587e0 + epoch_us(o_orderdate) / 86400000000e0, 6) AS mjd FROM orders""")
def order_times(spark, sf):
    t = F.col("o_orderdate")
    return read_table(spark, sf, "orders").select(
        "o_orderkey", F.year(t).alias("year"), F.month(t).alias("month"), F.date_trunc("month", t).cast("date").cast("string").alias("start"), (t + F.expr("INTERVAL 36 HOURS")).cast("date").cast("string").alias("later"),
        F.datediff(t, F.lit("1995-01-01").cast("date")).alias("days"), F.round(sky.mjd_of(t.cast("timestamp")), 6).alias("mjd"))


@workload(f"""WITH {_TRUE}, f AS (SELECT object_id, list(mjd ORDER BY mjd, flux) AS m, list(flux ORDER BY mjd, flux) AS x FROM lc GROUP BY object_id)
SELECT object_id, len(m) AS n, len(list_filter(x, lambda v: v > 30000)) AS bright, round(list_sum(list_transform(x, lambda v: v / 1000)), 5) AS total, m[1] AS first_mjd, m[-1] AS last_mjd, list_contains(m, m[1]) AS has_first FROM f""")
def folded_arrays(spark, sf):
    """Higher-order functions over folded light curves."""
    f = lightcurve.folded(_true_curve(spark, sf))
    flux = F.transform("points", lambda p: p["flux"])
    mjd = F.transform(F.arrays_zip(F.transform("points", lambda p: p["mjd"]).alias("m"), flux.alias("x")), lambda z: z["m"])
    total = F.aggregate(F.zip_with(flux, mjd, lambda a, _: a / 1000), F.lit(0.0), lambda a, v: a + v)
    ends = F.map_from_entries(F.array(F.struct(F.lit("first"), F.element_at(mjd, 1)), F.struct(F.lit("last"), F.element_at(mjd, -1))))
    return f.select(
        "object_id", F.size("points").cast("long").alias("n"), F.size(F.filter(flux, lambda v: v > 30000)).cast("long").alias("bright"), F.round(total, 5).alias("total"),
        ends["first"].alias("first_mjd"), ends["last"].alias("last_mjd"), F.array_contains(mjd, F.element_at(mjd, 1)).alias("has_first"))


@workload("SELECT s_suppkey, s_name FROM supplier WHERE TRUE")
def null_safe_lookup(spark, sf):
    """Null-safe equality keeps rows whose keys are both null."""
    s = read_table(spark, sf, "supplier").select("s_suppkey", "s_name", F.nullif(F.col("s_nationkey") % 2, F.lit(1)).alias("k"))
    return s.join(s.select(F.col("s_suppkey").alias("other"), F.col("k").alias("k2")), F.col("k").eqNullSafe(F.col("k2")) & (F.col("s_suppkey") == F.col("other"))).select("s_suppkey", "s_name")


# user-defined functions


@F.udtf(returnType="strip: int")
class StripsTouched:
    """The strips within r degrees of a declination, as a table function."""

    def eval(self, dec: float, r: float, width: float):
        import math

        for s in range(math.floor(max(dec - r - 1e-9, -90.0) / width), math.floor(min(dec + r + 1e-9, 90.0) / width) + 1):
            yield (s,)


@workload(f"""{_with()} SELECT d.source_id, CAST(s AS INTEGER) AS strip FROM (SELECT source_id, unnest(generate_series(CAST(floor(greatest(dec_deg - 0.5 - 1e-9, -90)) AS BIGINT), CAST(floor(least(dec_deg + 0.5 + 1e-9, 90)) AS BIGINT))) AS s FROM d) d""")
def strips_by_table_function(spark, sf):
    spark.udtf.register("sky_strips_touched", StripsTouched)
    return spark.sql("SELECT d.source_id, t.strip FROM {d} d, LATERAL sky_strips_touched(d.dec_deg, CAST(0.5 AS DOUBLE), CAST(1 AS DOUBLE)) t", d=fixtures.detections(spark, sf, 40))


@workload(f"WITH {_TRUE}, m AS (SELECT object_id, median(flux) AS middle FROM lc GROUP BY object_id) SELECT object_id, round(median(abs(flux - middle)), 4) AS spread FROM lc JOIN m USING (object_id) GROUP BY object_id")
def flux_spread(spark, sf):
    """Median absolute deviation of each light curve, by a grouped-aggregate pandas function."""

    @F.pandas_udf("double")
    def spread(flux: pd.Series) -> float:
        return float((flux - flux.median()).abs().median())

    return _true_curve(spark, sf).groupBy("object_id").agg(F.round(spread("flux"), 4).alias("spread"))


@workload(f"{_with()} SELECT object_id, source_id, TRUE AS agrees FROM ({_pairs_sql()})")
def separation_by_pandas(spark, sf):
    """The separation by a scalar pandas function, only to compare it with the built-in expression."""
    import numpy as np

    @F.pandas_udf("double")
    def sep(x: pd.Series, y: pd.Series, z: pd.Series, a: pd.Series, b: pd.Series, c: pd.Series) -> pd.Series:
        return np.degrees(2 * np.arcsin(np.sqrt((x - a) ** 2 + (y - b) ** 2 + (z - c) ** 2) / 2)) * 3600

    s, o = fixtures.detections(spark, sf, 40), fixtures.objects(spark, sf)
    wide = match.attach_columns(_image_pairs(spark, sf), s.withColumnsRenamed({"x": "sx", "y": "sy", "z": "sz"}), o, ["sx", "sy", "sz"], ["x", "y", "z"])
    return wide.select("object_id", "source_id", (F.abs(sep("x", "y", "z", "sx", "sy", "sz") - F.col("sep_arcsec")) < 1e-5).alias("agrees"))


# streams, run over all that is there


def _stream(spark, sf, files: int = 4) -> tuple[DataFrame, str]:
    root = f"{shared_dir(spark)}/stripmatch/stream-{uuid.uuid4().hex}"
    e = read_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(f"{root}/in")
    return lists.list_stream(spark, f"{root}/in", e.schema, files), root


def _ran(frame: DataFrame, root: str, schema: StructType) -> DataFrame:
    frame.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return frame.sparkSession.read.schema(schema).parquet(f"{root}/out")


@workload("SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def stream_sky_model(spark, sf):
    """A running count per position, kept as state between batches of a stream."""
    s, root = _stream(spark, sf)
    schema = StructType([StructField("user_id", LongType()), StructField("n", LongType())])

    def count(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(map(len, frames))
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    model = s.groupBy("user_id").applyInPandasWithState(count, schema, "n long", "append", "NoTimeout")
    return _ran(model, root, model.schema).groupBy("user_id").agg(F.max("n").alias("n"))


@workload("SELECT a.event_id AS first_event, b.event_id AS next_event FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def stream_interval_join(spark, sf):
    """Two detections of a position within ten minutes: a stream joined with a stream."""
    s, root = _stream(spark, sf)
    a = s.withWatermark("ts", "1 hour").select(F.col("event_id").alias("first_event"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = s.withWatermark("ts", "1 hour").select(F.col("event_id").alias("next_event"), "user_id", "ts")
    near = a.join(b, F.expr("u = user_id AND first_event <> next_event AND ts > t AND ts <= t + INTERVAL 10 MINUTES")).select("first_event", "next_event")
    return _ran(near, root, near.schema)


@workload("SELECT event_id, user_id FROM events")
def stream_deduplicated(spark, sf):
    """Events that come twice within the watermark are kept once."""
    s, root = _stream(spark, sf)
    once = lists.deduplicated(s.unionByName(s)).select("event_id", "user_id")
    return _ran(once, root, once.schema)


@workload("""SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session
FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, session""")
def event_sessions(spark, sf):
    return lists.sessions(read_table(spark, sf, "events"))


@workload(f"{_with()} {_pairs_sql()}")
def stream_static_match(spark, sf):
    """A list as a stream, joined with the static catalogue in one streaming plan."""
    root = f"{shared_dir(spark)}/stripmatch/stream-{uuid.uuid4().hex}"
    s = fixtures.detections(spark, sf, 40).select("source_id", "ra_deg", "dec_deg", "x", "y", "z")
    s.repartition(3, "source_id").write.parquet(f"{root}/in")
    found = lists.stream_static_match(lists.list_stream(spark, f"{root}/in", s.schema), fixtures.objects(spark, sf))
    return _ran(found, root, found.schema)


@workload("""WITH e AS (SELECT *, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS newest FROM events)
SELECT late, count(*) AS n FROM (SELECT ts < newest - INTERVAL 1 HOUR AS late FROM e) GROUP BY late""")
def late_events(spark, sf):
    """Events behind the newest one by more than the watermark go to a side table: how many of each."""
    newest = F.max("ts").over(Window.orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0))
    kept, late = lists.split_late(read_table(spark, sf, "events").withColumn("newest", newest), "1 hour")
    return kept.select(F.lit(False).alias("late")).unionByName(late.select(F.lit(True).alias("late"))).groupBy("late").agg(F.count(F.lit(1)).alias("n"))
