"""Mixing sources to target weights along a time-varying curriculum, in DataFrame functions only.

Targets: each source's share of share * (all words) by weight, at most cap times its own words; what a full source
can't take is shared again by weight (found in closed form from the sources sorted by cap / weight). Each source has
a weight schedule over the training time t in [0, 1], w(t) = w * (1 + slope * (2t - 1)); its integral is the
cumulative demand, and a document that starts at word c of its source's order gets the time at which the demand
reaches c. A source that is asked for more than it has starts over; a document is taken whole if its middle lies
within the target. Documents are range-sorted by time.

A hot source is never one task's work: documents are summed by (source, hash bucket), offsets run over the buckets,
and the order within is made per bucket. Buckets are beginnings of the hash, as long as it takes to keep them at about
BUCKET rows; their length changes no result. The windows over all sources have a row per source.

Defined cases: null text has size 0; a null source is a source of its own, last in order; an empty table gives no
rows; a corpus without words takes nothing; ties of the hash go by doc_id, then size; repeated rows each count; in
`mixed`, rows of one doc_id are taken as often, and at the times, as the one of them that is taken most often; extra
columns are kept whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stripmatch.cluster import written

WEIGHTS, SLOPES = (5.0, 2.0, 1.0), (-0.5, 0.0, 0.5)
BUCKET = 100_000


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, slopes=SLOPES, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """One row per source (key, source): source_size, weight, slope, target. sizes: key, source, size."""
    total = sizes.groupBy("key", "source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())  # a row per source
    nth = F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1
    ranked = total.withColumn("nth", nth).select("*", F.element_at(F.array(*map(F.lit, weights)), F.col("nth").cast("int")).alias("weight"), F.element_at(F.array(*map(F.lit, slopes)), F.col("nth").cast("int")).alias("slope"))
    full = cap * F.col("source_size")
    by_ratio = Window.orderBy((full / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    everyone = Window.partitionBy()
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    rest = (share * F.sum("source_size").over(everyone) - F.coalesce(F.sum(full).over(before), F.lit(0.0))) / (F.sum("weight").over(everyone) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    level = ranked.withColumn("full", full).withColumn("level", rest)
    level = level.withColumn("level", F.max(F.when(F.col("level") * F.col("weight") <= F.col("full"), F.col("level"))).over(everyone))
    return level.select("key", "source", "source_size", "weight", "slope", F.coalesce(F.least(F.col("level") * F.col("weight"), F.col("full")), F.col("full")).alias("target"))


def _placed(docs: DataFrame, weights, slopes, share: float, cap: float) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, copies and the times of its copies (positions)."""
    h = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    key = F.coalesce(F.concat(F.lit("="), F.col("source").cast("string")), F.lit(""))
    sizes = written(docs.select("doc_id", F.col("source").cast("string").alias("source"), words(F.col("text")).alias("size"), key.alias("key"), h.alias("hash")), "sizes")
    n, digits = sizes.count(), 3
    while 16**digits * BUCKET < n:
        digits += 1
    sizes = sizes.withColumn("bucket", F.substring("hash", 1, digits))
    buckets = sizes.groupBy("key", "source", "bucket").agg(F.sum("size").alias("bucket_size"))
    running = Window.partitionBy("key").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    targets = source_targets(sizes, weights, slopes, share, cap).drop("source", "weight")
    offsets = written(buckets.drop("source").withColumn("offset", F.coalesce(F.sum("bucket_size").over(running), F.lit(0))).join(targets, "key").drop("bucket_size"), "offsets")
    within = Window.partitionBy("key", "bucket").orderBy("hash", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = sizes.join(offsets, ["key", "bucket"]).withColumn("start", F.col("offset") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    middle = F.col("start") + F.col("size") / F.lit(2.0)
    copies = F.when((F.col("size") > 0) & (middle <= F.col("target")), F.floor((F.col("target") - middle) / F.col("source_size")) + 1).otherwise(F.lit(0)).cast("long")

    def time(c: Column) -> Column:
        u, s = F.least(c / F.col("target"), F.lit(1.0)), F.col("slope")
        return 2 * u / ((1 - s) + F.sqrt((1 - s) * (1 - s) + 4 * s * u))

    nth = F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)
    times = F.when(F.col("copies") > 0, F.transform(nth, lambda k: time(F.col("start") + k * F.col("source_size"))))
    return placed.withColumn("copies", copies).select("doc_id", "size", "source_size", "target", "copies", times.alias("positions"))


def plan_mix(docs: DataFrame, weights=WEIGHTS, slopes=SLOPES, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """One row per document, range-sorted by its first training time: doc_id, size, source_size, target, copies, taken, position, position_again."""
    out = _placed(docs, weights, slopes, share, cap)
    first, again = F.get("positions", F.lit(0)), F.get("positions", F.lit(1))
    return out.select("doc_id", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), first.alias("position"), again.alias("position_again")).orderBy("position", "doc_id")


def mixed(docs: DataFrame, weights=WEIGHTS, slopes=SLOPES, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """docs as the mix takes them, range-sorted by training time: those not taken go, each copy of the others stands at its own time. Columns of docs are kept."""
    plan = _placed(docs, weights, slopes, share, cap).where("copies > 0")
    taken = plan.groupBy(F.col("doc_id").alias("id")).agg(F.max_by("positions", "copies").alias("times"))
    row = docs.select(F.struct("*").alias("row"))  # inside a struct, no name of docs can clash
    joined = row.join(taken, F.col("row.doc_id").eqNullSafe(taken["id"])).select("row", F.explode("times").alias("time"))
    return joined.orderBy("time", "row.doc_id").select("row.*")
