"""The object catalogue: a directory per declination strip and right-ascension cell, sorted within, in immutable versions behind a manifest."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from stripmatch.functions import sky
from stripmatch.operators.ids import IdCounter, assign_ids
from stripmatch.schema import SKY_OBJECT, conform

_STORED = StructType([*SKY_OBJECT.fields, StructField("cell", IntegerType())])


class Catalog:
    """Readers see the version of the manifest they opened; one writer commits the next by an atomic rename.

    A strip is cut into equal cells of right ascension: one at first, more where `split` finds it too full. Only
    touched cells are rewritten, each by a task of its own; the others stay where an older version put them. width:
    degrees. The manifest holds, by strip, the number of cells and the version that has each.
    """

    def __init__(self, spark: SparkSession, root: str, width: float = 1.0, sort: bool = True, block_mb: int = 32, bloom: bool = False):
        self.spark, self.root, self.width, self.sort, self.block_mb, self.bloom = spark, root.rstrip("/"), width, sort, block_mb, bloom
        self.state = self._latest() or {"version": 0, "next_id": 0, "strips": {}}

    @property
    def ids(self) -> IdCounter:
        """The counter that the manifest keeps: no table is read for the next id."""
        return IdCounter(self.state["next_id"])

    def cells_in(self, strip: Column) -> Column:
        """How many cells a strip has."""
        cut = {int(k): v["cells"] for k, v in self.state["strips"].items() if v["cells"] > 1}
        if not cut:
            return F.lit(1)
        return F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in cut.items() for x in kv]), strip), F.lit(1))

    def cell_of(self, ra: Column, strip: Column) -> Column:
        n = self.cells_in(strip)
        return F.least(F.floor(F.pmod(ra, F.lit(360.0)) * n / 360.0), n - 1).cast("int")

    def touched(self, sources: DataFrame, r: float | str = 1.0) -> list[tuple[int, int]]:
        """The (strip, cell) that a list touches: no more values than the catalogue has cells, and one for each strip it lacks."""
        radius = (F.col(r) if isinstance(r, str) else F.lit(float(r))) / F.lit(3600.0)
        s = sources.select("ra_deg", "dec_deg", radius.alias("r_deg")).withColumn("strip", F.explode(sky.strips_touched("dec_deg", F.col("r_deg"), self.width)))
        half, n = sky.ra_halfwidth("dec_deg", F.col("r_deg")) + sky.PAD, self.cells_in(F.col("strip"))
        lo, hi = F.floor((F.col("ra_deg") - half) * n / 360.0), F.floor((F.col("ra_deg") + half) * n / 360.0)
        all_round = F.sequence(F.lit(0).cast("long"), (n - 1).cast("long"))
        cells = F.when(hi - lo + 1 >= n, all_round).otherwise(F.transform(F.sequence(lo, hi), lambda c: F.pmod(c, n.cast("long"))))
        rows = s.withColumn("cell", F.explode(cells)).select("strip", F.col("cell").cast("int").alias("cell")).distinct().collect()
        return sorted((x["strip"], x["cell"]) for x in rows)

    # the manifest, through Hadoop's file system so that any store works
    def _fs(self):
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.root)
        return jvm, path.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def _latest(self) -> dict | None:
        jvm, fs = self._fs()
        found = fs.globStatus(jvm.org.apache.hadoop.fs.Path(f"{self.root}/manifest-*.json"))
        names = sorted(s.getPath().toString() for s in found or [])
        if not names:
            return None
        text = "".join(r[0] for r in self.spark.read.text(names[-1]).collect())
        return json.loads(text)

    def _publish(self, state: dict) -> None:
        jvm, fs = self._fs()
        temp = jvm.org.apache.hadoop.fs.Path(f"{self.root}/.manifest-{uuid.uuid4().hex}")
        out = fs.create(temp, False)
        out.write(bytearray(json.dumps(state).encode()))
        out.close()
        if not fs.rename(temp, jvm.org.apache.hadoop.fs.Path(f"{self.root}/manifest-{state['version']:010d}.json")):
            raise RuntimeError("another writer committed this version")
        self.state = state

    def cells(self, wanted: list[tuple[int, int]]) -> DataFrame:
        """The rows of some (strip, cell): only their directories are read."""
        held = self.state["strips"]
        paths = [f"{self.root}/v={v}/strip={s}/cell={c}" for s, c in wanted if (v := held.get(str(s), {"v": {}})["v"].get(str(c))) is not None]
        if not paths:
            return self.spark.createDataFrame([], SKY_OBJECT)
        return conform(self.spark.read.schema(_STORED).option("basePath", self.root).parquet(*paths), SKY_OBJECT)

    def strips(self, wanted: list[int]) -> DataFrame:
        """The rows of whole strips."""
        return self.cells([(s, int(c)) for s in wanted for c in self.state["strips"].get(str(s), {"v": {}})["v"]])

    def all(self) -> DataFrame:
        return self.strips([int(s) for s in self.state["strips"]])

    def commit(self, rows: DataFrame, touched: list[tuple[int, int]], next_id: int | None = None, cut: dict[int, int] | None = None) -> None:
        """Replace the touched cells by rows. cut: new numbers of cells of strips that are replaced whole.

        Rows may lie beyond those cells (a mean that crossed an edge): a cell that was not replaced keeps its rows and gets these.
        """
        version, state = self.state["version"] + 1, json.loads(json.dumps(self.state))
        for strip, n in (cut or {}).items():
            state["strips"][str(strip)] = {"cells": n, "v": {}}
        before, self.state = self.state, state
        try:
            self._write(rows, touched, version, state, next_id)
        except BaseException:
            self.state = before
            raise

    def _write(self, rows, touched, version, state, next_id) -> None:
        for strip, cell in touched:
            state["strips"].get(str(strip), {"v": {}})["v"].pop(str(cell), None)
        ready = conform(rows, SKY_OBJECT).withColumn("cell", self.cell_of(F.col("mean_ra_deg"), F.col("strip")))
        ready = ready.repartition("strip", "cell")
        ready = ready.sortWithinPartitions("strip", "cell", "mean_dec_deg") if self.sort else ready
        attempt = f"{version}-{uuid.uuid4().hex[:8]}"  # what a writer that failed has left is never read
        target = f"{self.root}/v={attempt}"
        self._put(ready, target)
        jvm, fs = self._fs()  # a cell that has lost all its rows has no directory
        found = fs.globStatus(jvm.org.apache.hadoop.fs.Path(f"{target}/strip=*/cell=*")) or []
        has = [tuple(p.split("=")[1] for p in x.getPath().toString().rsplit("/", 2)[1:]) for x in found]
        beyond = [(int(s), int(c)) for s, c in has if state["strips"].get(s, {"v": {}})["v"].get(c) is not None]
        if beyond:  # rows came into cells that were not read
            kept = self.cells(beyond).withColumn("cell", self.cell_of(F.col("mean_ra_deg"), F.col("strip")))
            self._put(kept.repartition("strip", "cell").sortWithinPartitions("strip", "cell", "mean_dec_deg") if self.sort else kept, target)
        for strip, cell in has:
            state["strips"].setdefault(strip, {"cells": 1, "v": {}})["v"][cell] = attempt
        state["strips"] = {k: v for k, v in state["strips"].items() if v["v"] or v["cells"] > 1}
        self._publish(state | {"version": version, "next_id": state["next_id"] if next_id is None else next_id})

    def _put(self, rows: DataFrame, target: str) -> None:
        out = rows.write.mode("append").option("parquet.block.size", self.block_mb << 20)
        if self.bloom:
            out = out.option("parquet.bloom.filter.enabled#object_id", "true")
        out.partitionBy("strip", "cell").parquet(target)

    def strip_stats(self) -> DataFrame:
        """Rows of each strip: growth control."""
        return self.all().groupBy("strip").agg(F.count(F.lit(1)).alias("objects"))

    def table_stats(self, column: str = "mean_dec_deg") -> DataFrame:
        """Count, mean, extremes and scatter of a column, strip by strip, as storage would keep them."""
        return self.all().groupBy("strip").agg(F.count(column).alias("n"), F.avg(column).alias("mean"), F.min(column).alias("low"), F.max(column).alias("high"), F.stddev_samp(column).alias("scatter"))

    def split(self, limit: int) -> dict[int, int]:
        """Cut strips whose cells would hold more than limit rows into as many cells as bring them below it, in powers of two."""
        cut = {}
        for x in self.strip_stats().where(F.col("objects") > limit).collect():  # at most 180 / width rows
            n = 1
            while n * limit < x["objects"]:
                n *= 2
            if n > self.state["strips"][str(x["strip"])]["cells"]:
                cut[x["strip"]] = n
        if cut:
            self.commit(self.strips(list(cut)), [], cut=cut)
        return cut


def new_objects(sources: DataFrame, start: int, width: float = 1.0) -> DataFrame:
    """Catalogue rows founded by unmatched sources."""
    rows = assign_ids(sources, start, ["source_id"])
    return conform(rows.select("object_id", F.col("source_id").alias("first_source_id"), F.lit(1).alias("datapoints"), F.lit(True).alias("active"), F.col("ra_deg").alias("mean_ra_deg"), F.col("dec_deg").alias("mean_dec_deg"), "x", "y", "z", sky.strip_of("dec_deg", width).alias("strip")), SKY_OBJECT)


def update_stats(objects: DataFrame, new: DataFrame, width: float = 1.0, mean_mode: str = "vector") -> DataFrame:
    """objects with the new measurements (object_id, ra_deg, dec_deg, x, y, z) folded in; the strip follows the mean.

    vector: running mean of unit vectors, normalised (safe at the wrap and the poles). angles: running mean of
    declination and of the circular difference in right ascension.
    """
    n = F.col("datapoints")
    add = new.groupBy("object_id").agg(F.count(F.lit(1)).alias("k"), *[F.sum(c).alias(f"s{c}") for c in ("x", "y", "z", "dec_deg")])
    if mean_mode == "angles":
        base = objects.select("object_id", F.col("mean_ra_deg").alias("_ra"))
        gap = F.pmod(F.col("ra_deg") - F.col("_ra") + 540.0, F.lit(360.0)) - 180.0
        add = add.join(new.join(base, "object_id").groupBy("object_id").agg(F.sum(gap).alias("sra")), "object_id")
    j = objects.join(add, "object_id", "left")
    hit, total = F.col("k").isNotNull(), n + F.coalesce("k", F.lit(0))
    if mean_mode == "angles":
        ra = F.pmod(F.col("mean_ra_deg") + F.col("sra") / total, F.lit(360.0))
        dec = F.col("mean_dec_deg") + (F.col("sdec_deg") - F.col("k") * F.col("mean_dec_deg")) / total
        j = j.withColumn("_ra", ra).withColumn("_dec", dec).select("*", *[v.alias(f"_{c}") for c, v in zip("xyz", sky.unit_vector("_ra", "_dec"))])
    else:
        for c in "xyz":
            j = j.withColumn(f"_{c}", F.col(c) + (F.col(f"s{c}") - F.col("k") * F.col(c)) / total)
        norm = F.sqrt(F.col("_x") * F.col("_x") + F.col("_y") * F.col("_y") + F.col("_z") * F.col("_z"))
        ra, dec = sky.radec_libm("_x", "_y", "_z")  # of the sum itself: one rounding less than of its unit vector
        j = j.withColumns({"_ra": F.when(norm > 0, ra).otherwise(F.col("mean_ra_deg")), "_dec": F.when(norm > 0, dec).otherwise(F.col("mean_dec_deg")), "_n": norm})
        j = j.withColumns({f"_{c}": F.when(F.col("_n") > 0, F.col(f"_{c}") / F.col("_n")).otherwise(F.col(c)) for c in "xyz"})
    pick = lambda new_, old: F.when(hit, F.col(new_)).otherwise(F.col(old)).alias(old)
    out = j.select("object_id", "first_source_id", total.cast("int").alias("datapoints"), "active", pick("_ra", "mean_ra_deg"), pick("_dec", "mean_dec_deg"), pick("_x", "x"), pick("_y", "y"), pick("_z", "z"))
    return out.withColumn("strip", sky.strip_of("mean_dec_deg", width))
