"""Quality rules: base counts of a text, and boosted trees over document statistics with monotone constraints.

Defined cases: null or empty text has no words and fails the base; exact ties in scores keep the document; labels
that are null are left out; without labelled rows of both kinds the trees are empty and the base decides alone;
repeated rows are judged each; extra columns are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship
from stripmatch.llm.textnp import Chunk, chunks, doc_mix

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
STAT_NAMES = ["log_words", "word_len", "symbols", "dup_lines", "repeats", "distinct", "upper", "digits", "punct", "line_words", "not_ascii", "short", "bangs", "links", "one_char"]
#: Statistics that may only lower a document's quality as they rise.
MONOTONE = {"symbols": -1, "dup_lines": -1, "repeats": -1, "bangs": -1}
_CLASS = {name: np.isin(np.arange(256), list(members)) for name, members in {
    "upper": range(65, 91), "digits": range(48, 58), "punct": b".,;:?\"'()", "bangs": b"!", "links": b"/@_={}\\"}.items()}


def base_counts(c: Chunk) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of each text of a chunk."""
    solid = np.zeros(256, bool)
    solid[:] = True
    solid[[9, 10, 11, 12, 13, 32]] = False
    solid[128:192] = False
    n_words = np.diff(c.wo)
    out = {"n_words": n_words, "word_chars": c.per_text(solid[c.b]), "n_symbols": c.per_text(SYMBOLS[c.b])}
    # lines
    cut = np.flatnonzero(c.b == 10)
    starts = np.union1d(c.off[:-1][np.diff(c.off) > 0], cut + 1)
    starts = starts[starts < len(c.b)]
    ends = np.append(starts[1:], len(c.b)) if len(starts) else starts
    ends = np.where((ends > 0) & (c.b[ends - 1] == 10), ends - 1, ends) if len(ends) else ends
    solid_line = np.searchsorted(c.ws, ends) > np.searchsorted(c.ws, starts)
    starts, ends = starts[solid_line], ends[solid_line]
    doc = np.searchsorted(c.off, starts, "right") - 1
    h = doc_mix(c.spans_hash(starts, ends), doc)
    _, first = np.unique(h, return_index=True)
    lines = np.bincount(doc, minlength=c.n)
    out["n_lines"] = lines
    out["n_dup_lines"] = lines - np.bincount(doc[first], minlength=c.n)
    # repeated windows
    h = c.hashes()
    w, at = c.windows(h, 5)
    covered = np.zeros(len(h) + 1, np.int64)
    if len(w):
        w = doc_mix(w, c.wd[at])
        order = np.argsort(w, kind="stable")
        same = w[order][1:] == w[order][:-1]
        twice = np.zeros(len(w), bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        np.add.at(covered, at[twice], 1)
        np.add.at(covered, at[twice] + 5, -1)
    hit = np.cumsum(covered[:-1]) > 0
    out["n_repeat_words"] = np.bincount(c.wd[hit], minlength=c.n)
    u = np.unique(doc_mix(h, c.wd), return_index=True)[1]
    out["distinct"] = np.bincount(c.wd[u], minlength=c.n)
    length = c.we - c.ws
    out["short"] = np.bincount(c.wd[length <= 3], minlength=c.n)
    out["one_char"] = np.bincount(c.wd[length == 1], minlength=c.n)
    for name, members in _CLASS.items():
        out[name] = c.per_text(members[c.b])
    out["not_ascii"] = c.per_text(c.b >= 192)
    return out


def statistics(s: dict[str, np.ndarray]) -> np.ndarray:
    """The matrix of STAT_NAMES."""
    words, chars = np.maximum(s["n_words"], 1), np.maximum(s["word_chars"], 1)
    return np.column_stack([
        np.log1p(s["n_words"]), s["word_chars"] / words, s["n_symbols"] / chars, s["n_dup_lines"] / np.maximum(s["n_lines"], 1), s["n_repeat_words"] / words, s["distinct"] / words,
        s["upper"] / chars, s["digits"] / chars, s["punct"] / chars, s["n_words"] / np.maximum(s["n_lines"], 1), s["not_ascii"] / chars, s["short"] / words, s["bangs"] / chars, s["links"] / chars, s["one_char"] / words])


@dataclass
class Trees:
    """Flattened complete trees: node i of a tree has children 2i+1 and 2i+2; a leaf repeats its value below itself."""

    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray
    bias: float
    depth: int

    def score(self, x: np.ndarray) -> np.ndarray:
        """P(good), all rows of a tree advancing together."""
        total = np.full(len(x), self.bias)
        rows = np.arange(len(x))
        for f, t, v in zip(self.feature, self.threshold, self.value):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + (x[rows, f[node]] > t[node])
            total += v[node]
        return 1 / (1 + np.exp(-total))


def fit_trees(x: np.ndarray, y: np.ndarray, monotone: dict[int, int], rounds: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 48, ridge: float = 1.0, least: float = 5.0) -> Trees:
    """Newton boosting of the logistic loss on quantile histograms; monotone maps a feature to +1 or -1."""
    n, k = x.shape
    nodes, inner = 2 ** (depth + 1) - 1, 2**depth - 1
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) if n else np.zeros(0) for j in range(k)]
    code = np.column_stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(edges)]) if n else np.zeros((0, k), int)
    flat = code + np.arange(k) * bins
    share = np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3)
    bias = float(np.log(share / (1 - share)))
    margin = np.full(n, bias)
    features, cuts, values = [], [], []
    for _ in range(rounds if n and 0 < y.sum() < n else 0):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, np.maximum(p * (1 - p), 1e-6)
        f, t, v = np.zeros(inner, np.int64), np.full(inner, np.inf), np.zeros(nodes)
        held = {0: (np.arange(n), -np.inf, np.inf)}
        for node in range(nodes):
            if node not in held:
                if node:
                    v[node] = v[(node - 1) // 2]
                continue
            rows, low, high = held[node]
            v[node] = np.clip(-g[rows].sum() / (h[rows].sum() + ridge), low, high)
            if node >= inner or len(rows) < 2 * least:
                continue
            cells = flat[rows].ravel()
            sums = [np.cumsum(np.bincount(cells, weights=np.repeat(q[rows], k), minlength=k * bins).reshape(k, bins), axis=1) for q in (g, h, np.ones(n))]
            (gl, hl, nl), tot = sums, [s[:, -1:] for s in sums]
            gr, hr, nr = tot[0] - gl, tot[1] - hl, tot[2] - nl
            left, right = np.clip(-gl / (hl + ridge), low, high), np.clip(-gr / (hr + ridge), low, high)
            gain = -(gl * left + 0.5 * (hl + ridge) * left**2) - (gr * right + 0.5 * (hr + ridge) * right**2)
            gain[(nl < least) | (nr < least)] = -np.inf
            for j, way in monotone.items():
                gain[j][(right[j] - left[j]) * way < 0] = -np.inf
            j, b = np.unravel_index(np.argmax(gain), gain.shape)
            if not np.isfinite(gain[j, b]) or gain[j, b] <= -(g[rows].sum() * v[node] + 0.5 * (h[rows].sum() + ridge) * v[node] ** 2) + 1e-9 or b >= len(edges[j]):
                continue
            f[node], t[node] = j, edges[j][b]
            go = code[rows, j] > b
            mid = (left[j, b] + right[j, b]) / 2
            bound = {1: ((low, mid), (mid, high)), -1: ((mid, high), (low, mid))}.get(monotone.get(int(j), 0), ((low, high), (low, high)))
            held[2 * node + 1], held[2 * node + 2] = (rows[~go], *bound[0]), (rows[go], *bound[1])
        v *= rate
        features.append(f), cuts.append(t), values.append(v)
        one = Trees(np.array([f]), np.array([t]), np.array([v]), 0.0, depth)
        step = one.score(x)
        margin += np.log(step / (1 - step))
    shape = (len(features), inner)
    return Trees(np.array(features, np.int64).reshape(shape), np.array(cuts, float).reshape(shape), np.array(values, float).reshape(len(features), nodes), bias, depth)


def sampled_labels(labels: DataFrame, column: str, bound: int) -> DataFrame:
    """About bound labelled rows at most, chosen by a hash of the id over all labels."""
    good = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", F.col(column).cast("int").alias("label"))
    n = good.count()
    return good if n <= bound else good.where(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1_000_000)) < int(1_000_000 * bound / n))


def fit_rules(docs: DataFrame, labels: DataFrame, bound: int = 20_000, **how) -> Trees:
    """Fit on at most about bound labelled documents (their statistics only come to the driver)."""
    ship(docs.sparkSession)
    joined = docs.select("doc_id", "text").join(F.broadcast(sampled_labels(labels, "quality", bound)), "doc_id").select("label", "text")

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(1)):
                x = statistics(base_counts(c))
                y = batch.column(0).slice(c.lo, c.n).cast(pa.float64())
                yield pa.RecordBatch.from_arrays([y, *map(pa.array, x.T)], ["label", *STAT_NAMES])

    rows = joined.mapInArrow(run, "label double, " + ", ".join(f"{n} double" for n in STAT_NAMES)).toArrow()
    x = np.column_stack([rows.column(n).to_numpy() for n in STAT_NAMES])
    order = np.lexsort(x.T)
    return fit_trees(x[order], rows.column("label").to_numpy()[order], {STAT_NAMES.index(k): v for k, v in MONOTONE.items()}, **how)


def quality_rules(docs: DataFrame, trees: Trees, least_words: int = 10, most_repeats: int = 20, threshold: float = 0.3) -> DataFrame:
    """One row per document with the base counts, base_failed, score and kept."""
    ship(docs.sparkSession)
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    narrow = docs.select("doc_id", "text")

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(1)):
                s = base_counts(c)
                failed = (s["n_words"] < least_words) | (100 * s["n_repeat_words"] > most_repeats * s["n_words"])
                score = trees.score(statistics(s))
                cols = [pa.array(s[n].astype(np.int64)) for n in names] + [pa.array(failed), pa.array(~failed & (score >= threshold)), pa.array(score)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c.lo, c.n), *cols], ["doc_id", *names, "base_failed", "kept", "score"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, " + ", ".join(f"{n} long" for n in names) + ", base_failed boolean, kept boolean, score double")
