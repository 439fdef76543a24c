"""Quality classifier: a linear model on n-gram indicators scaled by naive-Bayes log-count ratios.

Training: indicators of hashed word 1- and 2-grams (A-Z folded) and of word shapes, scaled by the classes' log-count
ratios and to unit length, then an L1-loss linear SVM by dual coordinate descent; its margin on rows kept out of the
fit is calibrated to a probability. Training rows come to the driver, at most about `bound` of them (a documented
parameter), chosen by a hash over all labelled rows; scoring reads every whole text.

Defined cases: null or empty text scores by the intercept; labels that are null are left out; with no rows of one
class every score is 0.5; repeated rows are scored each, and train as one (the smallest text of their id); ties at the
threshold count as 1; extra columns are dropped, and kept by `accepted` whatever their names; an empty table gives no
rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship
from stripmatch.llm.quality_rules import sampled_labels
from stripmatch.llm.textnp import U, Chunk, chunks, mix

BITS = 18
_SHAPE = np.zeros(256, np.uint8)
_SHAPE[65:91], _SHAPE[97:123], _SHAPE[48:58], _SHAPE[128:] = 1, 2, 3, 2
_SHAPE[list(b".,;:?!'\"()")] = 4


def features(c: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed features of a chunk's texts: (text of each, feature of each), ordered by text."""
    if not len(c.ws):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    h = c.hashes(fold=True)
    two, at = c.windows(h, 2)
    head, tail = _SHAPE[c.b[c.ws]], _SHAPE[c.b[c.we - 1]]
    shape = mix((head.astype(U) * U(8) + tail.astype(U)) * U(64) + np.minimum(c.we - c.ws, 40).astype(U) + U(7_000_003))
    last2 = mix(c.b[c.we - 1].astype(U) * U(256) + c.b[np.maximum(c.we - 2, c.ws)].astype(U) + U(9_000_011))
    doc = np.concatenate([c.wd, c.wd[at], c.wd, c.wd]).astype(U)
    f = np.concatenate([h, two, shape, last2]) >> U(64 - BITS)
    both = np.unique((doc << U(BITS)) | f)
    return (both >> U(BITS)).astype(np.int64), (both & U((1 << BITS) - 1)).astype(np.int64)


@dataclass
class Model:
    weights: np.ndarray  # by feature, the ratio included
    ratio2: np.ndarray  # squared ratios, for the unit length
    slope: float
    offset: float

    def score(self, doc: np.ndarray, f: np.ndarray, n: int) -> np.ndarray:
        top = np.bincount(doc, weights=self.weights[f], minlength=n)
        norm = np.sqrt(np.bincount(doc, weights=self.ratio2[f], minlength=n))
        return 1 / (1 + np.exp(-np.clip(self.slope * top / np.maximum(norm, 1e-9) + self.offset, -30, 30)))


def dual_descent(indptr: np.ndarray, cols: np.ndarray, vals: np.ndarray, y: np.ndarray, dims: int, cost: float = 1.0, epochs: int = 12, seed: int = 1) -> np.ndarray:
    """The hinge-loss linear SVM of rows of unit length, by coordinate descent on its dual. y: +1 or -1."""
    w, alpha = np.zeros(dims), np.zeros(len(y))
    square = [float(vals[s:e] @ vals[s:e]) for s, e in zip(indptr[:-1], indptr[1:])]
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(y)):
            s, e = indptr[i], indptr[i + 1]
            if s == e or square[i] <= 0:
                continue
            j, v = cols[s:e], vals[s:e]
            g = y[i] * (w[j] @ v) - 1
            new = min(max(alpha[i] - g / square[i], 0.0), cost)
            if new != alpha[i]:
                w[j] += (new - alpha[i]) * y[i] * v
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w


def calibrated(margin: np.ndarray, y: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """Slope and offset of a logistic fit of y (0 or 1) on margins, with smoothed targets, by Newton's method."""
    pos, neg = y.sum(), len(y) - y.sum()
    if not pos or not neg:
        return 1.0, 0.0
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    z, b = np.column_stack([margin, np.ones(len(y))]), np.zeros(2)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ b, -30, 30)))
        h = (z * (p * (1 - p))[:, None]).T @ z + 1e-3 * np.eye(2)
        b = b - np.linalg.solve(h, z.T @ (p - target) + 1e-3 * b)
    return float(b[0]), float(b[1])


def fit(sets: list[np.ndarray], y: np.ndarray, blend: float = 0.5) -> Model:
    """sets: each row's features; y: 0 or 1. A fifth of the rows only calibrates."""
    dims = 1 << BITS
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(dims), np.zeros(dims), 1.0, 0.0)

    def ratios(rows):
        count = np.ones((2, dims))
        for i in rows:
            count[int(y[i] > 0), sets[i]] += 1
        return np.log(count[1] / count[1].sum()) - np.log(count[0] / count[0].sum())

    def train(rows):
        r = ratios(rows)
        indptr = np.concatenate([[0], np.cumsum([len(sets[i]) for i in rows])])
        cols = np.concatenate([sets[i] for i in rows])
        vals = r.astype(np.float32)[cols]
        for s, e in zip(indptr[:-1], indptr[1:]):  # in place: the training rows are most of the driver's memory
            vals[s:e] /= max(float(np.sqrt(vals[s:e] @ vals[s:e])), 1e-9)
        w = dual_descent(indptr, cols, vals, np.where(y[rows] > 0, 1.0, -1.0), dims)
        used = w[w != 0]
        w = (1 - blend) * (np.abs(used).mean() if len(used) else 0.0) + blend * w  # towards the plain ratios
        return Model(w * r, r**2, 1.0, 0.0)

    rows = np.arange(len(y))
    part = rows[rows % 5 != 0]
    trial, rest = train(part), rows[rows % 5 == 0]
    doc = np.repeat(np.arange(len(rest)), [len(sets[i]) for i in rest])
    f = np.concatenate([sets[i] for i in rest])
    raw = np.bincount(doc, weights=trial.weights[f], minlength=len(rest)) / np.maximum(np.sqrt(np.bincount(doc, weights=trial.ratio2[f], minlength=len(rest))), 1e-9)
    slope, offset = calibrated(raw, y[rest])
    final = train(rows)
    return Model(final.weights, final.ratio2, slope, offset)


def held_out(doc_id: Column, folds: int, which: int) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == which, F.lit(False))


def fit_classifier(docs: DataFrame, labels: DataFrame, folds: int = 5, which: int = 0, bound: int = 12_000, target: str = "quality") -> Model:
    """Learn from labelled rows outside the held-out fold."""
    ship(docs.sparkSession)
    chosen = sampled_labels(labels.where(~held_out(F.col("doc_id"), folds, which)), target, bound)
    joined = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text"))

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(2)):
                doc, f = features(c)
                cut = np.searchsorted(doc, np.arange(c.n + 1))
                packed = pa.array([f[cut[i] : cut[i + 1]].astype(np.int32).tobytes() for i in range(c.n)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c.lo, c.n).cast(pa.string()), batch.column(1).slice(c.lo, c.n), packed], ["doc_id", "label", "packed"])

    rows = joined.mapInArrow(run, "doc_id string, label int, packed binary").toArrow()
    ids, y = rows.column("doc_id").to_pylist(), rows.column("label").to_numpy()
    sets = [np.frombuffer(p.as_buffer(), np.int32) for p in rows.column("packed")]  # views of the table, no second copy
    order = sorted(range(len(ids)), key=lambda i: (ids[i] or "", int(y[i]), len(sets[i])))  # the same model on every run
    return fit([sets[i] for i in order], y[order])


def accepted(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """The rows of docs that score at least the threshold, all columns kept: judged where they are read, without a shuffle."""
    ship(docs.sparkSession)
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            ok = [model.score(*features(c), c.n) >= threshold for c in chunks(batch.column(at))]
            yield batch.filter(pa.array(np.concatenate(ok) if ok else np.zeros(0, bool)))

    return docs.mapInArrow(run, docs.schema)


def classify(docs: DataFrame, model: Model, folds: int = 5, which: int = 0, threshold: float = 0.3) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted."""
    ship(docs.sparkSession)
    narrow = docs.select(docs["doc_id"], held_out(docs["doc_id"], folds, which).alias("held_out"), docs["text"])

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(2)):
                score = model.score(*features(c), c.n)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c.lo, c.n), batch.column(1).slice(c.lo, c.n), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, held_out boolean, score double, predicted int")
