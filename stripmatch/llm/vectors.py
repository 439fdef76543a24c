"""Embedding near-duplicates by sorted projection passes.

Equal vectors fall together first. In each pass every vector gets PLANES random-hyperplane bits of that pass, and the
vectors stand in the lexicographic order of these bits. A vector's window is the run of those that agree with it in the
leading bits: all in a run are compared in double precision, and the last of a run with the first of the next one that
the task holds. A run over `block` vectors is compared block against block, so windows stay bounded and yet nothing
limits how many stand between the two of a pair. Pairs found in all passes are united into components. Then links are
counted exactly within each component, again in blocks: no list of pairs is ever emitted.

A pair at cosine t agrees in the leading bits of a pass with probability (1 - acos(t) / pi)^bits, however dense its
surroundings are, so the passes that miss a pair at the threshold with probability `miss` follow from the bits alone.
What density changes is the cost: `plan` weighs passes against the length of runs, from the angles of a sample, and
takes the cheapest number of bits. No bits at all is one pass that compares everything and misses nothing.

Vectors are written once, as arrays that tasks map; what passes shuffle is a key and a place of each.

Defined cases: null or zero vectors and those with null or non-finite components link with nothing; vectors of
different lengths never link; a vector is an id and its components: repeated rows of both are one vector and share its
result, rows of one id with different components are vectors that link like any others; equal vectors of different ids
link with one another; a null id is kept without links; an empty table gives no rows; extra columns are dropped.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship, shuffle_parts, written
from stripmatch.llm import store
from stripmatch.operators.components import connected_components

PLANES = 40
EDGE = 16  # neighbours compared across the border of two runs
SAMPLE = 2_000
ROW, BUCKET, PAIR, TERM = 2e-5, 3e-5, 3e-9, 2e-10  # seconds of a row dealt, a bucket, a pair, a component of a pair
FEW = 100_000  # large buckets that may be broadcast


def passes_for(bits: int, threshold: float, miss: float = 1e-4) -> int:
    """Passes after which a pair at the threshold is missed with probability of at most miss."""
    meet = (1 - math.acos(max(-1.0, min(1.0, threshold))) / math.pi) ** bits
    return 1 if meet >= 1 else math.ceil(math.log(miss) / math.log1p(-meet))


def plan(n: int, dim: int, sample: np.ndarray, threshold: float, miss: float, block: int) -> tuple[int, int]:
    """(bits, passes) of least cost for n vectors like the unit rows of the sample."""
    i, j = np.triu_indices(len(sample), 1)
    agree = 1 - np.arccos(np.clip((sample @ sample.T)[i, j], -1, 1)) / np.pi if len(i) else np.array([0.5])
    best, meet = None, np.ones(len(agree))
    for bits in range(PLANES + 1):
        size, passes = n * meet.mean(), passes_for(bits, threshold, miss)
        cost = passes * (n * (1 + size / block) * ROW + min(n, 2.0**bits) * BUCKET + n * size / 2 * (PAIR + dim * TERM))
        if best is None or cost < best[0]:
            best = cost, bits, passes
        meet *= agree
    return best[1:]


def unit_rows(flat: np.ndarray, n: int) -> np.ndarray:
    x = flat.reshape(n, -1).astype(np.float64)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _forest(pairs: np.ndarray, ids: np.ndarray, parent: dict[int, int]) -> list[tuple[int, int]]:
    """The pairs that join two trees of the task's forest."""
    out = []

    def root(v):
        while parent.setdefault(v, v) != v:
            parent[v] = parent[parent[v]]
            v = parent[v]
        return v

    for i, j in pairs:
        a, b = int(ids[i]), int(ids[j])
        ra, rb = root(a), root(b)
        if ra != rb:
            parent[max(ra, rb)] = min(ra, rb)
            out.append((a, b))
    return out


def _joined(x: np.ndarray, y: np.ndarray | None, threshold: float) -> np.ndarray:
    """(i, j) of rows of x and y (of x alone: y is None) at or above the threshold; a spanning forest of all such pairs."""
    every = x if y is None else np.concatenate([x, y])
    tree, found = np.arange(len(every)), []
    first = 0 if y is None else len(x)
    for s in range(0, len(x), 512):
        lo = s if y is None else first
        near = x[s : s + 512] @ every[lo:].T >= threshold
        if y is None:
            near[:, : near.shape[0]] = np.triu(near[:, : near.shape[0]], 1)
        for i in np.flatnonzero(near.any(axis=1)):
            j = np.flatnonzero(near[i]) + lo
            trees, at = np.unique(tree[j], return_index=True)
            for t, k in zip(trees, at):
                if t != tree[s + i]:
                    found.append((s + i, j[k]))
                    tree[tree == t] = tree[s + i]
    return np.array(found, int).reshape(-1, 2)


def near_vectors(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", threshold: float = 0.95, miss: float = 1e-4, block: int = 512, bucket: int = 2048) -> DataFrame:
    """One row per row: vec_id, n_links, component_id, kept (is the component's smallest)."""
    spark = vectors.sparkSession
    ship(spark)
    folder = store.new_folder(spark, "vectors")
    every = vectors.select(F.col(id_col).alias("vec_id"), F.col(vec_col).alias("v"))
    fine = F.col("v").isNotNull() & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    valid = every.where(F.coalesce(fine, F.lit(False)) & F.col("vec_id").isNotNull())
    alike = valid.groupBy("v", "vec_id").agg(F.lit(1).alias("one")).groupBy("v").agg(F.min("vec_id").alias("low"), F.count("vec_id").alias("copies"))
    reps = written(alike.withColumn("node", F.monotonically_increasing_id()), "reps")
    sizes = {r["dim"]: r["count"] for r in reps.groupBy(F.size("v").alias("dim")).count().collect()}
    some = reps.where(F.pmod(F.xxhash64("node"), F.lit(max(1, sum(sizes.values()) // SAMPLE))) == 0).select("v").limit(2 * SAMPLE).collect()
    sample = {d: [r["v"] for r in some if len(r["v"]) == d] for d in sizes}
    plans = {d: plan(n, d, unit_rows(np.array(sample[d], np.float64), len(sample[d])) if sample[d] else np.zeros((0, d)), threshold, miss, bucket) for d, n in sizes.items()}

    def keyed(batches):
        held: dict[int, list] = {}
        part = TaskContext.get().partitionId()
        for batch in batches:
            lists = batch.column(1)
            lengths = np.asarray(lists.value_lengths())
            for d in np.unique(lengths).tolist():
                rows = np.flatnonzero(lengths == d)
                x = unit_rows(np.asarray(lists.take(pa.array(rows)).flatten()), len(rows))
                ids = np.asarray(batch.column(0))[rows]
                at = sum(map(len, held.setdefault(d, []))) + np.arange(len(rows))
                held[d].append(x)
                bits, passes = plans[d]
                rng = np.random.default_rng(d)
                same = lambda v, kind: pa.array(np.full(len(rows), v, kind))
                for p in range(passes):
                    planes = rng.standard_normal((d, PLANES))
                    order = (x @ planes > 0).astype(np.int64) @ (1 << np.arange(PLANES - 1, -1, -1, dtype=np.int64))
                    yield pa.RecordBatch.from_arrays([same(p, np.int32), same(d, np.int32), pa.array(order >> (PLANES - bits)), pa.array(order), pa.array(ids), same(part, np.int32), pa.array(at)], ["pass", "dim", "run", "order", "node", "part", "at"])
        for d, x in held.items():
            store.put(folder, f"x{d}-{part}", np.concatenate(x).tobytes())

    rows = reps.select("node", "v").mapInArrow(keyed, "pass int, dim int, run long, order long, node long, part int, at long")
    run_of = ["pass", "dim", "run"]
    large = written(rows.groupBy(*run_of).count().where(F.col("count") > bucket).select(*run_of, F.ceil(F.col("count") / bucket).cast("int").alias("blocks")), "runs")
    large = F.broadcast(large) if large.count() <= FEW else large
    cut = rows.join(large, run_of, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    cut = cut.withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    group_of = [*run_of, "p", "q"]
    cut = cut.select(*run_of, F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), "own", "order", "node", "part", "at")
    grouped = cut.repartition(max(shuffle_parts(spark), 1), *group_of).sortWithinPartitions(*group_of, "order", "node")

    def compared(batches):
        parent: dict[int, int] = {}
        files, before = store.Files(folder), None

        def gathered(dim, part, at):
            x = np.empty((len(at), dim))
            for n in np.unique(part).tolist():
                rows = np.flatnonzero(part == n)
                x[rows] = files.named(f"x{dim}-{n}").view("f8").reshape(-1, dim)[at[rows]]
            return x

        def tree_edges(group, parts):
            nonlocal before
            t = pa.Table.from_batches(parts)
            own, ids, part, at = (t[c].to_numpy() for c in ("own", "node", "part", "at"))
            x = gathered(int(group[1]), part, at)
            if group[3] != group[4]:
                left, right = own == group[3], own == group[4]
                return _forest(_joined(x[left], x[right], threshold), np.concatenate([ids[left], ids[right]]), parent)
            found = _forest(_joined(x, None, threshold), ids, parent)
            if before is not None and before[0] == group[:2]:
                found += _forest(_joined(before[1], x[:EDGE], threshold), np.concatenate([before[2], ids[:EDGE]]), parent)
            before = group[:2], x[-EDGE:].copy(), ids[-EDGE:]
            return found

        def out(edges):
            e = np.array(edges, np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(e[:, 0]), pa.array(e[:, 1])], ["a", "b"])

        group, parts, edges = None, [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.column_stack([np.asarray(batch.column(i)).astype(np.int64) for i in range(5)])
            starts = np.flatnonzero(np.append(True, (keys[1:] != keys[:-1]).any(axis=1)))
            for s, e in zip(starts, np.append(starts[1:], len(keys))):
                if (g := tuple(keys[s])) != group:
                    if parts:
                        edges += tree_edges(group, parts)
                    group, parts = g, []
                parts.append(batch.slice(s, e - s))
            yield out(edges)
            edges = []
        if parts:
            yield out(tree_edges(group, parts))

    edges = grouped.mapInArrow(compared, "a long, b long")
    labels = connected_components(edges)
    linked = written(labels.join(reps, "node"), "linked")
    lows = linked.groupBy("component").agg(F.min("low").alias("low"), F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    at = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    dealt = linked.join(lows.select("component", "blocks"), "component").withColumn("own", at).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("component", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), "own", "node", "copies", "v")

    def count_links(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for d, part in pdf.groupby(pdf["v"].map(len)):
            x = unit_rows(np.concatenate(part["v"].to_numpy()), len(part))
            own, copies, ids = part["own"].to_numpy(), part["copies"].to_numpy().astype(float), part["node"].to_numpy()
            p, q = int(part["p"].iloc[0]), int(part["q"].iloc[0])
            left, right = own == p, own == q
            near = x[left] @ x[right].T >= threshold
            if p == q:
                np.fill_diagonal(near, False)
                out.append((ids[left], near @ copies[right]))
            else:
                out += [(ids[left], near @ copies[right]), (ids[right], near.T @ copies[left])]
        return pd.DataFrame({"node": np.concatenate([o[0] for o in out]), "links": np.concatenate([o[1] for o in out]).astype("int64")})

    links = dealt.groupBy("component", "p", "q").applyInPandas(count_links, "node long, links long").groupBy("node").agg(F.sum("links").alias("links"))
    told = reps.join(labels.join(lows.select("component", F.col("low").alias("lowest")), "component").select("node", "lowest"), "node", "left").join(links, "node", "left")
    told = told.select("v", F.coalesce("lowest", "low").alias("component"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"))
    known = every.withColumn("v", F.when(F.col("vec_id").isNotNull(), F.col("v"))).join(told, "v", "left")
    component = F.coalesce("component", "vec_id").cast("long")
    return known.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))
