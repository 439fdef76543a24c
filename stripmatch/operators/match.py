"""Positional cross-match: a scan-style baseline, strips, fine zones, zone-and-cell keys, trees, and brute force.

All give the same pairs (object_id, source_id, sep_arcsec): those closer than the radius. A list is `source_id,
ra_deg, dec_deg, x, y, z` (and a radius column if it varies), objects the same with `object_id`.

At scale the list of an image is small and the catalogue streams past it: the list is broadcast if its counted size
is below a bound, else both sides are shuffled by the zone (and cell), which AQE can split where the sky is dense. A
catalogue below the bound goes to all tasks itself. Objects that share positions are matched by place.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship
from stripmatch.functions import sky

SMALL_LIST = 500_000
FINE, CELL = 1 / 60, 1.0  # degrees of the join key
SCAN = 5e10  # comparisons that a scan of the whole catalogue may have
ARCSEC = 1 / 3600.0


def small(df: DataFrame, rows: int = SMALL_LIST) -> DataFrame:
    """df with a broadcast hint if it has at most that many rows."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def _radius(r: float | str) -> Column:
    """Degrees, from arcseconds that are constant or in a column."""
    return (F.col(r) if isinstance(r, str) else F.lit(float(r))) / F.lit(3600.0)


def prepared(sources: DataFrame, r: float | str, keep: tuple[str, ...] = ()) -> DataFrame:
    """Each source's bounds, worked out once. keep: more columns that come along."""
    own = sources.select("source_id", *keep, F.col("ra_deg").alias("s_ra"), F.col("dec_deg").alias("s_dec"), F.col("x").alias("sx"), F.col("y").alias("sy"), F.col("z").alias("sz"), _radius(r).alias("r_deg"))
    own = own.withColumn("half", sky.ra_halfwidth("s_dec", F.col("r_deg")) + sky.PAD).withColumn("most", sky.chord2_of(F.col("r_deg") if isinstance(r, str) else float(r) / 3600.0))
    return own.withColumn("low", F.col("s_dec") - F.col("r_deg") - sky.PAD).withColumn("high", F.col("s_dec") + F.col("r_deg") + sky.PAD)


def _d2() -> Column:
    return sky.chord2("x", "y", "z", "sx", "sy", "sz")


def in_box() -> Column:
    return F.col("dec_deg").between(F.col("low"), F.col("high")) & (sky.ra_gap("ra_deg", "s_ra") <= F.col("half"))


def _close(threshold: str) -> Column:
    return _d2() < F.col("most") if threshold == "chord2" else F.asin(F.least(F.sqrt(_d2()) / 2, F.lit(1.0))) < F.radians(F.col("r_deg")) / 2


def separation() -> Column:
    return sky.rounded(sky.sep_arcsec(_d2()), 6).alias("sep_arcsec")


def _pairs(joined: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    if "held" in joined.columns:  # the separation is worked out once a place
        joined = joined.select("held", "source_id", separation(), *keep)
        return joined.select(F.explode("held").alias("object_id"), "source_id", "sep_arcsec", *keep)
    return joined.select("object_id", "source_id", separation(), *keep)


def _positions(objects: DataFrame) -> DataFrame:
    return objects.select("object_id", "ra_deg", "dec_deg", "x", "y", "z")


def places(objects: DataFrame) -> DataFrame:
    """Objects by position, as what is near one object of a place is near them all: the smallest id (place), the ids (held) and their number (n)."""
    return _positions(objects).groupBy("ra_deg", "dec_deg", "x", "y", "z").agg(F.min("object_id").alias("place"), F.collect_list("object_id").alias("held"), F.count(F.lit(1)).alias("n"))


def sides(left: DataFrame, objects: DataFrame, by_place: bool | None = None) -> tuple[DataFrame, DataFrame]:
    """Both sides of a match, the one that goes to all tasks with a hint: the objects if they are few, else the list if it is short.

    Where at least half of the objects share their position with others, or by_place is set, they are matched by place.
    Rows and positions are counted over all objects (the latter approximately: it decides the plan, not the result).
    """
    size = objects.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.xxhash64("ra_deg", "dec_deg")).alias("d")).first()
    by_place = 2 * size["d"] <= size["n"] if by_place is None else by_place
    right = places(objects) if by_place else _positions(objects)
    if (size["d"] if by_place else size["n"]) <= SMALL_LIST and size["n"] <= 8 * SMALL_LIST:
        return left, F.broadcast(right)
    return small(left), right


def match_baseline(sources: DataFrame, objects: DataFrame, r: float | str = 1.0, zones: bool = False) -> DataFrame:
    """The comparator: every source against the whole catalogue through range predicates, the half-angle as threshold.

    zones: the range of declinations goes by arcminute zones as keys, where a scan would have more than SCAN comparisons.
    """
    if zones:
        return match_zones(sources, objects, r, FINE, threshold="angle")
    left, right = sides(prepared(sources, r), objects)
    return _pairs(right.join(left, in_box() & _close("angle")))


def match_bruteforce(sources: DataFrame, objects: DataFrame, r: float | str = 1.0) -> DataFrame:
    """All pairs by distance alone; for tests."""
    return _pairs(_positions(objects).join(prepared(sources, r), _d2() < F.col("most")))


def match_zones(sources: DataFrame, objects: DataFrame, r: float | str = 1.0, width: float = 1.0, cell: float | None = None, threshold: str = "chord2", keep: tuple[str, ...] = ()) -> DataFrame:
    """Band join as an equi-join: see zone_join. keep: more columns of the list that the pairs get."""
    return _pairs(zone_join(sources, objects, r, width, cell, threshold, keep), keep)


def zone_join(sources: DataFrame, objects: DataFrame, r: float | str = 1.0, width: float = 1.0, cell: float | None = None, threshold: str = "chord2", keep: tuple[str, ...] = (), by_place: bool | None = None) -> DataFrame:
    """Sources beside the objects, or places, that they match, with all columns of both: a source stands in every zone (and right-ascension cell) that its box touches.

    width and cell in degrees. A box is cut where the sky ends, and goes round at 0/360.
    """
    left, right = sides(prepared(sources, r, keep), objects, by_place)
    left = left.withColumn("zone", F.explode(sky.strips_touched("s_dec", F.col("r_deg"), width)))
    right = right.withColumn("zone", sky.strip_of("dec_deg", width))
    keys = ["zone"]
    if cell:
        n = max(1, round(360 / cell))
        cell = 360 / n  # cells divide the circle
        lo, hi = F.floor((F.col("s_ra") - F.col("half")) / cell), F.floor((F.col("s_ra") + F.col("half")) / cell)
        every = F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))
        cells = F.when(F.col("half") * 2 + 2 * cell >= 360, every).otherwise(F.array_distinct(F.transform(F.sequence(lo, hi), lambda c: F.floor(F.pmod(c * cell + cell / 2, F.lit(360.0)) / cell))))
        left = left.withColumn("cell", F.explode(cells))
        right = right.withColumn("cell", F.floor(F.pmod(F.col("ra_deg"), F.lit(360.0)) / cell))
        keys.append("cell")
    return right.join(left, keys).where(in_box() & _close(threshold))


def match_strips(sources: DataFrame, catalog, r: float | str = 1.0, width: float = 1.0) -> DataFrame:
    """The partitioned form: only the strips that the list touches are read; within them the join is by arcminute and cell.

    A strip is the unit of storage. As a join key it would set every source against all of its strip (match_strip_key).
    """
    return match_zones(sources, slice_for(sources, catalog, r, width), r, FINE, CELL)


def match_strip_key(sources: DataFrame, catalog, r: float | str = 1.0, width: float = 1.0) -> DataFrame:
    """The same, joined by the strip itself: to measure what the finer key is worth."""
    return match_zones(sources, slice_for(sources, catalog, r, width), r, width)


def match_probe(sources: DataFrame, catalog, r: float | str = 1.0, width: float = 1.0) -> DataFrame:
    """Range probes: each batch of a touched strip, sorted by declination as it is stored, is searched for both ends of every source's range.

    The list goes to all tasks, so it must be small; a longer one takes match_strips.
    """
    own = prepared(sources, r).select("source_id", "s_ra", "s_dec", "sx", "sy", "sz", "r_deg", "half", "most").limit(SMALL_LIST + 1).toPandas().sort_values("s_dec")
    if len(own) > SMALL_LIST:
        return match_strips(sources, catalog, r, width)
    ends = [np.floor((own["s_dec"] + way * (own["r_deg"] + sky.PAD)).clip(-90.0, 90.0) / width).astype(int) for way in (-1, 1)]
    strips = sorted({s for lo, hi in set(zip(*ends)) for s in range(lo, hi + 1)})
    held = strips_of(catalog, strips)
    ids = own.pop("source_id").to_numpy()
    s_ra, s_dec, sx, sy, sz, r_deg, half, most = own.to_numpy(np.float64).T
    reach = float(r_deg.max()) + sky.PAD if len(ids) else 0.0

    def probe(batches):
        for batch in batches:
            o = [np.asarray(batch.column(i)) for i in range(6)]
            if not batch.num_rows or not len(ids):
                continue
            if (np.diff(o[2]) < 0).any():  # a batch may begin in one cell and end in the next
                order = np.argsort(o[2], kind="stable")
                o = [x[order] for x in o]
            dec = o[2]
            a, b = np.searchsorted(s_dec, dec[0] - reach, "left"), np.searchsorted(s_dec, dec[-1] + reach, "right")
            lo = np.searchsorted(dec, s_dec[a:b] - r_deg[a:b] - sky.PAD, "left")
            size = np.searchsorted(dec, s_dec[a:b] + r_deg[a:b] + sky.PAD, "right") - lo
            i = np.repeat(np.arange(a, b), size)
            j = np.repeat(lo, size) + np.arange(len(i)) - np.repeat(np.cumsum(size) - size, size)
            near = np.abs((o[1][j] - s_ra[i] + 540.0) % 360.0 - 180.0) <= half[i]
            i, j = i[near], j[near]
            d2 = (o[3][j] - sx[i]) ** 2 + (o[4][j] - sy[i]) ** 2 + (o[5][j] - sz[i]) ** 2
            ok = d2 < most[i]
            yield pa.RecordBatch.from_arrays([pa.array(o[0][j[ok]]), pa.array(ids[i[ok]]), pa.array(d2[ok])], ["object_id", "source_id", "d2"])

    pairs = _positions(held).mapInArrow(probe, "object_id long, source_id long, d2 double")
    return pairs.select("object_id", "source_id", sky.rounded(sky.sep_arcsec("d2"), 6).alias("sep_arcsec"))


def touched_strips(sources: DataFrame, r: float | str, width: float = 1.0) -> list[int]:
    """The strips that a list touches: at most 180 / width values."""
    rows = sources.select(F.explode(sky.strips_touched("dec_deg", _radius(r), width)).alias("strip")).distinct().collect()
    return sorted(x["strip"] for x in rows)


def slice_for(sources: DataFrame, catalog, r: float | str, width: float = 1.0) -> DataFrame:
    """The catalogue's rows in those strips, by literal partition values. catalog: a DataFrame with strip, or a Catalog."""
    return strips_of(catalog, touched_strips(sources, r, width))


def strips_of(catalog, strips: list[int]) -> DataFrame:
    """The rows of some strips of a DataFrame or a Catalog, with the columns of objects."""
    df = catalog.strips(strips) if hasattr(catalog, "strips") else catalog.where(F.col("strip").isin(strips) if strips else F.lit(False))
    return df if "object_id" in df.columns and "ra_deg" in df.columns else df.withColumnsRenamed({"mean_ra_deg": "ra_deg", "mean_dec_deg": "dec_deg"})


def attach_columns(pairs: DataFrame, sources: DataFrame, objects: DataFrame, source_cols: list[str], object_cols: list[str]) -> DataFrame:
    """Late fetch: wide columns joined by id once the pairs are known."""
    return pairs.join(sources.select("source_id", *source_cols), "source_id").join(objects.select("object_id", *object_cols), "object_id")


class Tree:
    """A static k-d tree over unit vectors, in arrays; leaves hold up to `leaf` points."""

    def __init__(self, points: np.ndarray, leaf: int = 16):
        self.points, self.leaf = points, leaf
        self.order, self.nodes, self.depth = np.arange(len(points)), [], 0
        stack = [(0, len(points), 0, -1, False)]
        while stack:
            lo, hi, level, parent, right = stack.pop()
            self.depth = max(self.depth, level)
            me = len(self.nodes)
            if parent >= 0 and right:
                self.nodes[parent][3] = me
            if hi - lo <= leaf:
                self.nodes.append([-1, lo, hi, -1])
                continue
            part = self.order[lo:hi]
            axis = int(np.argmax(np.ptp(points[part], axis=0)))
            mid = (hi - lo) // 2
            self.order[lo:hi] = part[np.argpartition(points[part, axis], mid)]
            self.nodes.append([axis, points[self.order[lo + mid], axis], 0, -1])
            stack.append((lo + mid, hi, level + 1, me, True))
            stack.append((lo, lo + mid, level + 1, me, False))

    def near(self, p: np.ndarray, chord: float) -> np.ndarray:
        """Indices of points closer than chord."""
        if not len(self.points):
            return np.zeros(0, int)
        found, stack = [], [0]
        while stack:
            i = stack.pop()
            axis, a, b, right = self.nodes[i]
            if axis < 0:
                at = self.order[a:b]
                d = self.points[at] - p
                found.append(at[(d * d).sum(axis=1) < chord * chord])
                continue
            if p[axis] - a <= chord:
                stack.append(i + 1)
            if a - p[axis] <= chord:
                stack.append(right)
        return np.concatenate(found)


class Forest:
    """Trees of doubling sizes: an insert merges the small ones, so each point is rebuilt about log2(n) times."""

    def __init__(self, leaf: int = 16):
        self.trees: list[tuple[Tree, np.ndarray]] = []
        self.leaf, self.rebuilt = leaf, 0
        self.gone: set[int] = set()

    def remove(self, ids: np.ndarray) -> None:
        """Drop points; a tree that has lost half of its own is rebuilt without them, smaller losses are only masked."""
        self.gone |= set(ids.tolist())
        for k, (tree, own) in enumerate(self.trees):
            lost = np.isin(own, list(self.gone))
            if 2 * lost.sum() > len(own):
                self.gone -= set(own[lost].tolist())
                self.rebuilt += int((~lost).sum())
                self.trees[k] = Tree(tree.points[~lost], self.leaf), own[~lost]

    def update(self, points: np.ndarray, ids: np.ndarray) -> None:
        """Move points: the old places go, the new ones are inserted."""
        for k, (tree, own) in enumerate(self.trees):
            lost = np.isin(own, ids)
            if lost.any():
                self.rebuilt += int((~lost).sum())
                self.trees[k] = Tree(tree.points[~lost], self.leaf), own[~lost]
        self.gone -= set(ids.tolist())
        self.insert(points, ids)

    def insert(self, points: np.ndarray, ids: np.ndarray) -> None:
        while self.trees and len(self.trees[-1][1]) <= len(ids):
            tree, own = self.trees.pop()
            points, ids = np.concatenate([tree.points, points]), np.concatenate([own, ids])
        self.rebuilt += len(ids)
        self.trees.append((Tree(points, self.leaf), ids))

    def near(self, p: np.ndarray, chord: float) -> np.ndarray:
        found = np.concatenate([ids[t.near(p, chord)] for t, ids in self.trees] or [np.zeros(0, np.int64)])
        return found[~np.isin(found, list(self.gone))] if self.gone else found


class GrowingTree:
    """One tree over points that come in batches. rebuild: never (later points are searched one by one), every (at each
    batch), ratio (when the points outside exceed a quarter of those inside)."""

    def __init__(self, rebuild: str = "ratio", leaf: int = 16):
        if rebuild not in ("never", "every", "ratio"):
            raise ValueError(rebuild)
        self.rebuild, self.leaf, self.rebuilt = rebuild, leaf, 0
        self.tree, self.points, self.ids = Tree(np.zeros((0, 3)), leaf), np.zeros((0, 3)), np.zeros(0, np.int64)

    def insert(self, points: np.ndarray, ids: np.ndarray) -> None:
        self.points, self.ids = np.concatenate([self.points, points]), np.concatenate([self.ids, ids])
        inside = len(self.tree.points)
        outside = len(self.points) - inside
        if not inside or self.rebuild == "every" or (self.rebuild == "ratio" and 4 * outside > inside):
            self.tree = Tree(self.points, self.leaf)
            self.rebuilt += len(self.points)

    def near(self, p: np.ndarray, chord: float) -> np.ndarray:
        inside = len(self.tree.points)
        d = self.points[inside:] - p
        late = inside + np.flatnonzero((d * d).sum(axis=1) < chord * chord)
        return self.ids[np.concatenate([self.tree.near(p, chord), late]).astype(int)]


def match_tree(sources: DataFrame, objects: DataFrame, r: float = 1.0, width: float = 1.0, forest: bool = False, rebuild: str | None = None) -> DataFrame:
    """Tree-index baseline: one tree per strip, probed by that strip's sources. A forest, or a tree with a policy of rebuilding, is fed in batches."""
    ship(sources.sparkSession)
    chord = 2 * np.sin(np.radians(r * ARCSEC) / 2)
    left = prepared(sources, r).withColumn("zone", F.explode(sky.strips_touched("s_dec", F.col("r_deg"), width))).select("zone", "source_id", "sx", "sy", "sz")
    right = _positions(objects).withColumn("zone", sky.strip_of("dec_deg", width)).select("zone", "object_id", "x", "y", "z")

    def probe(own: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        ids, points = held["object_id"].to_numpy(), held[["x", "y", "z"]].to_numpy()
        index = GrowingTree(rebuild) if rebuild else Forest()
        step = max(1, len(ids) // 7) if forest or rebuild else max(1, len(ids))
        for i in range(0, len(ids), step):
            index.insert(points[i : i + step], ids[i : i + step])
        out = [(o, s, *p) for s, *p in own[["source_id", "sx", "sy", "sz"]].itertuples(index=False) for o in index.near(np.array(p), chord)]
        return pd.DataFrame([(o, s) for o, s, *_ in out], columns=["object_id", "source_id"]).astype("int64")

    pairs = left.groupBy("zone").cogroup(right.groupBy("zone")).applyInPandas(probe, "object_id long, source_id long")
    return _pairs(pairs.join(_positions(objects), "object_id").join(prepared(sources, r).select("source_id", "sx", "sy", "sz"), "source_id"))


def tree_stats(points: np.ndarray, batches: int = 8) -> pd.DataFrame:
    """Depth and rebuilt points of a tree rebuilt at every batch and of a forest, as points come in."""
    forest, rows, rebuilt = Forest(), [], 0
    step = max(1, len(points) // batches)
    for i in range(0, len(points), step):
        forest.insert(points[i : i + step], np.arange(i, min(i + step, len(points))))
        tree = Tree(points[: i + step])
        rebuilt += len(tree.points)
        rows.append((len(tree.points), tree.depth, rebuilt, max(t.depth for t, _ in forest.trees), len(forest.trees), forest.rebuilt))
    return pd.DataFrame(rows, columns=["points", "tree_depth", "tree_rebuilt", "forest_depth", "forest_trees", "forest_rebuilt"])


def cone_search(objects: DataFrame, ra: float, dec: float, r_deg: float) -> DataFrame:
    """Objects within r of a centre, nearest first: strip filter, box, chord."""
    spark = objects.sparkSession
    centre = spark.range(1).select(F.lit(0).cast("long").alias("source_id"), F.lit(float(ra)).alias("ra_deg"), F.lit(float(dec)).alias("dec_deg"))
    centre = centre.select("*", *sky.unit_vector("ra_deg", "dec_deg"))
    return match_strips(centre, objects, r_deg * 3600).drop("source_id")


def match_accuracy(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """recall and purity of pairs against true pairs (object_id, source_id)."""
    p, t = pairs.select("object_id", "source_id").distinct(), truth.select("object_id", "source_id").distinct()
    both = p.withColumn("p", F.lit(1)).join(t.withColumn("t", F.lit(1)), ["object_id", "source_id"], "full")
    hit = F.sum(F.when(F.col("p").isNotNull() & F.col("t").isNotNull(), 1).otherwise(0))
    return both.agg(F.count("p").alias("n_pairs"), F.count("t").alias("n_true"), hit.alias("n_hit"), (hit / F.count("t")).alias("recall"), (hit / F.count("p")).alias("purity"))
