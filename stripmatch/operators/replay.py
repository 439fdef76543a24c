"""A cold start by groups: sources that can never meet need no common order, so the images of each group are replayed apart, many
groups in one task.

An object's mean lies within 2 r of a source that it last took: that one was within r of the mean before, which it moved by less
than r. So a source that an object takes is within 3 r of one that it has, and sources that no chain of such steps joins never have
to do with one another. Cells as wide as 3 r stand for the sources in them; cells beside one another are taken as joined.
"""

from __future__ import annotations

import math
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship, shuffle_parts, written
from stripmatch.operators.components import connected_components

MOST, PAIRS = 500_000, 25_000_000  # sources of a group that one task replays, and pairs that one of its images may have; what is larger is left to the image loop
TASK = 100_000  # sources a task, about
CHUNK = 4_000_000  # candidates compared at once, unless one group has more
BITS, MIDDLE = 21, 2**19 + 2  # a cell's key: three numbers of so many bits, which never reach the ends of their range
FOUND = "first_source_id long, pos int, source_id long, sep_arcsec double, topology string, datapoints int, mean_ra_deg double, mean_dec_deg double, x double, y double, z double"


def side(r_arcsec: float) -> float:
    """Edge of cells that are as wide as a chord of r, and wide enough for the bits of a key."""
    return max(2 * math.sin(math.radians(min(r_arcsec / 3600, 180.0)) / 2) * (1 + 1e-9) + 1e-15, 2.0**-19)


def cell_of(edge: float) -> Column:
    at = [F.floor(F.col(c) / F.lit(edge)) + F.lit(MIDDLE) for c in ("x", "y", "z")]
    return F.shiftleft(at[0], 2 * BITS) + F.shiftleft(at[1], BITS) + at[2]


def groups(sources: DataFrame, r: float) -> DataFrame:
    """cell, its group, the sources of the group (group_size) and the most pairs that one of its images can have (most_pairs).

    Sources without a position have the cell null, and no group.
    """
    counted = written(sources.groupBy(cell_of(side(3 * r)).alias("cell"), "image_id").agg(F.count(F.lit(1)).alias("n")), "cells")
    cells = written(counted.select("cell").distinct(), "cells")
    beside = [(a << 2 * BITS) + (b << BITS) + c for a, b, c in product((-1, 0, 1), repeat=3) if (a, b, c) > (0, 0, 0)]
    steps = cells.select(F.col("cell").alias("a"), F.explode(F.array(*[F.col("cell") + F.lit(k) for k in beside])).alias("b"))
    edges = steps.join(cells.select(F.col("cell").alias("b")), "b").select("a", "b")
    named = cells.join(connected_components(edges).withColumnRenamed("node", "cell"), "cell", "left").select("cell", F.coalesce("component", "cell").alias("group"))
    sizes = counted.join(named, "cell").groupBy("group", "image_id").agg(F.sum("n").alias("n")).groupBy("group").agg(F.sum("n").alias("group_size"), (F.sum("n") * F.max("n")).alias("most_pairs"))
    return written(named.join(sizes, "group").select("cell", "group", "group_size", "most_pairs"), "groups")


def _cells(p: np.ndarray, edge: float) -> np.ndarray:
    c = np.floor(p / edge).astype(np.int64) + MIDDLE
    return (c[:, 0] << 2 * BITS) + (c[:, 1] << BITS) + c[:, 2]


def _near(s: np.ndarray, lo: np.ndarray, size: np.ndarray, order: np.ndarray, p: np.ndarray, mean: np.ndarray, most: float):
    """Rows of sources, objects and squared chords below most, of the candidates that each source has in its ranges."""
    lo, size = lo.ravel(), size.ravel()
    i = np.repeat(np.repeat(s, 3 * 3), size)
    j = order[np.repeat(lo - np.cumsum(size) + size, size) + np.arange(len(i))]
    d = mean[j] - p[i]
    d2 = d[:, 0] * d[:, 0] + d[:, 1] * d[:, 1] + d[:, 2] * d[:, 2]
    near = d2 < most
    return i[near], j[near], d2[near]


def _degrees(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How many objects the source of each pair has, and how many sources its object has."""
    count = lambda v: (lambda u: u[1][u[0]])(np.unique(v, return_inverse=True, return_counts=True)[1:])
    return count(i), count(j)


def replay(pdf: pd.DataFrame, r: float) -> pd.DataFrame:
    """All images of whole groups, in order, as the image loop takes them: nearest, merged, means of vectors.

    One row per light-curve point; that of an object's first source has the object as it is in the end (datapoints is 0 in the others).
    """
    pdf = pdf.sort_values(["pos", "group", "source_id"], kind="stable")
    ids, pos, group, p = pdf["source_id"].to_numpy(), pdf["pos"].to_numpy(), pdf["group"].to_numpy(), pdf[["x", "y", "z"]].to_numpy(np.float64)
    edge, most, held = side(r), 4 * math.sin(math.radians(r / 3600) / 2) ** 2, 0
    first, total = np.zeros(len(p), np.int64), np.ones(len(p), np.int64)  # of objects, in the order of their founding
    mean, raw = np.zeros_like(p), np.full_like(p, np.nan)
    points = []
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(pos)) + 1, [len(pos)]])
    for begin, end in zip(bounds[:-1], bounds[1:]):
        keys = _cells(mean[:held], edge)
        order = np.argsort(keys, kind="stable")
        keys, own = keys[order], _cells(p[begin:end], edge)
        column = np.array([(a << 2 * BITS) + (b << BITS) for a, b in product((-1, 0, 1), repeat=2)])
        lo = np.searchsorted(keys, own[:, None] + column - 1, "left")  # cells above one another are a range of keys
        size = np.searchsorted(keys, own[:, None] + column + 1, "right") - lo
        seen = np.zeros(end - begin, bool)
        for a, b in _chunks(size.sum(axis=1), group[begin:end]):
            i, j, d2 = _near(np.arange(begin + a, begin + b), lo[a:b], size[a:b], order, p, mean, most)
            if not len(i):
                continue
            seen[i - begin] = True
            sep = np.floor(np.degrees(2 * np.arcsin(np.minimum(np.sqrt(d2) / 2, 1.0))) * 3600.0 * 1e6 + 0.5) / 1e6
            by = np.lexsort((j, sep, i))
            i, j, sep = i[by], j[by], sep[by]
            objects, sources = _degrees(i, j)
            kept = (objects == 1) | (sources == 1) | np.concatenate([[True], i[1:] != i[:-1]])
            i, j, sep = i[kept], j[kept], sep[kept]
            objects, sources = _degrees(i, j)
            names = np.where(objects == 1, np.where(sources == 1, "one-to-one", "one-to-many"), np.where(sources == 1, "many-to-one", "many-to-many"))
            points.append((j, i, sep, names.astype(object)))
            hit, of, k = np.unique(j, return_inverse=True, return_counts=True)
            total[hit] += k
            sums = np.stack([np.bincount(of, p[i, c]) for c in range(3)], axis=1)
            moved = mean[hit] + (sums - k[:, None] * mean[hit]) / total[hit][:, None]
            norm = np.sqrt(moved[:, 0] * moved[:, 0] + moved[:, 1] * moved[:, 1] + moved[:, 2] * moved[:, 2])
            fine = norm > 0
            raw[hit[fine]], mean[hit[fine]] = moved[fine], moved[fine] / norm[fine][:, None]
        new = begin + np.flatnonzero(~seen)
        first[held : held + len(new)], mean[held : held + len(new)] = new, p[new]
        held += len(new)
    first, total, mean, raw = first[:held], total[:held], mean[:held], raw[:held]
    ra, dec = pdf["ra_deg"].to_numpy()[first], pdf["dec_deg"].to_numpy()[first]
    for o in np.flatnonzero(~np.isnan(raw[:, 0])):  # by the C library, as in sky.radec_libm
        x, y, z = raw[o].tolist()
        ra[o], dec[o] = math.degrees(math.atan2(y, x)) % 360.0 % 360.0, math.degrees(math.atan2(z, math.sqrt(x * x + y * y)))
    founding = {"first_source_id": ids[first], "pos": pos[first], "source_id": ids[first], "sep_arcsec": 0.0, "topology": "none", "datapoints": total, "mean_ra_deg": ra, "mean_dec_deg": dec, "x": mean[:, 0], "y": mean[:, 1], "z": mean[:, 2]}
    out = [pd.DataFrame(founding)]
    for j, i, sep, names in points:
        out.append(pd.DataFrame({"first_source_id": ids[first[j]], "pos": pos[i], "source_id": ids[i], "sep_arcsec": sep, "topology": names, "datapoints": 0, "mean_ra_deg": np.nan, "mean_dec_deg": np.nan, "x": np.nan, "y": np.nan, "z": np.nan}))
    return pd.concat(out, ignore_index=True)


def _chunks(size: np.ndarray, group: np.ndarray) -> list[tuple[int, int]]:
    """Runs of whole groups (sorted) that have up to CHUNK candidates, or one group."""
    ends = np.concatenate([np.flatnonzero(np.diff(group)) + 1, [len(group)]])
    upto = np.cumsum(size)[ends - 1]
    out, begin, before = [], 0, 0
    while begin < len(group):
        last = max(np.searchsorted(upto, before + CHUNK, "right") - 1, np.searchsorted(ends, begin, "right"))
        out.append((begin, int(ends[last])))
        begin, before = int(ends[last]), upto[last]
    return out


def replayed(sources: DataFrame, r: float) -> DataFrame:
    """replay over a table of source_id, pos (of the image in the sequence), group and position: columns as in FOUND."""
    spark = sources.sparkSession
    ship(spark)
    tasks = max(shuffle_parts(spark), sources.count() // TASK)
    dealt = sources.select("source_id", "pos", "group", "ra_deg", "dec_deg", "x", "y", "z", F.pmod(F.xxhash64("group"), F.lit(tasks)).alias("task"))
    return dealt.repartition(tasks, "task").groupBy("task").applyInPandas(lambda pdf: replay(pdf, r), FOUND)
