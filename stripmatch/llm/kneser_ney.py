"""An interpolated modified Kneser-Ney model of order 3 (or 2), counted in Spark, kept as sorted arrays.

Tokens of a text are its words, A-Z folded, then an end; before the first stand starts. Words get dense numbers by the
order of their hashes (ranges of hashes, each a file); a pair of numbers is mixed to a 64-bit key and back, whose
ranges are dealt out evenly whatever words are frequent. A gram (u, v, w) is the key of (v, w) and the number u, so it
goes to the range of its pair, which counts the kinds of u at once; what its context (u, v) and the words v and w have
is sent on. Each task combines its grams before it sends them; keys are sent as differences and numbers as planes of
bytes, which the shuffle's compression makes short. Workers map the files; no table of the model is ever whole in one
memory.

p(w | uv) = max(c(uvw) - D(c), 0) / c(uv) + g(uv) p(w | v); p(w | v) is the same form over the kinds of u before vw,
p(w) over the kinds of v before w, and rests on 1 / (V + 1). With order 2, p(w | v) is over c(vw). D1, D2, D3+ follow
from the counts of counts of each order.

Files: words (count), pairs (of order 2: c, its count; of order 3: o, its first gram, and t, is it seen more than once),
grams (u and n), contexts (c and n1, n2, n3+ of those seen more than once; a pair seen but absent there is a context seen
once), stats by word. Counts have 64 bits; the files hold a byte of each and the few large ones apart. A pair is seen as
often as a context, so contexts seen once are known from the pairs and never sent. The shuffles of a step are let go
before the next one. Distinct words, not their uses, are numbered with 32 bits: beyond 2^32 of them the fit stops.

Defined cases: null or empty text is one end; a corpus without training texts gives uniform scores; words unknown to
training share the rest 1 / (V + 1); repeated rows count each; a null doc_id is in training; extra columns are
dropped; an empty table gives no rows. Words are equal if their 64-bit hashes are.
"""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship
from stripmatch.llm import store
from stripmatch.llm.quality_classifier import held_out
from stripmatch.llm.textnp import U, Chunk, chunks, mix, unmix

END, START = U(0x5A5A5A5A00000001), U(0xA5A5A5A500000002)
SIZE = 2 << 20
CONTEXT = dict.fromkeys(("c", "n1", "n2", "n3"), store.SMALL)
STATS = ("cont", "n1", "n2", "n3", "total")


def tokens(c: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """(token hashes, first token of each text and the total): each text's words and one end."""
    off = c.wo + np.arange(c.n + 1)
    out = np.full(len(c.ws) + c.n, END, U)
    out[np.arange(len(c.ws)) + c.wd] = c.hashes(fold=True)
    return out, off


def discounts(n: list[int]) -> np.ndarray:
    """D for counts 0, 1, 2, 3+ from the numbers of entries seen once to four times."""
    n1, n2, n3, n4 = map(float, n)
    if not (n1 and n2):
        return np.array([0.0, 0.5, 0.75, 0.75]) if n1 or n2 or n3 else np.array([0.0, 0.5, 0.5, 0.5])
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return np.array([0.0, *(min(max(x, 0.05), k - 0.05) for k, x in zip((1, 2, 3), d))])


@dataclass
class Model:
    folder: str
    bits: int
    offsets: np.ndarray  # the number of the first word of each range
    words: int  # V
    total: int  # N
    texts: int
    order: int
    gram_discount: np.ndarray
    pair_discount: np.ndarray
    word_discount: np.ndarray
    types: int
    spare: float  # what continuation counts leave to 1 / (V + 1)
    stores: dict = field(default_factory=dict)

    def __getstate__(self):
        return self.__dict__ | {"stores": {}}

    def vocabulary(self) -> store.Store:
        return self.stores.setdefault("w", store.Store(f"{self.folder}/words", self.bits, {"c": store.SMALL}))

    def numbers(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(known, count, number) of word hashes."""
        known, got = self.vocabulary().find(h)
        r = (h >> U(64 - self.bits)).astype(np.int64)
        return known, got["c"].astype(np.int64), self.offsets[r] + got["at"]

    def stats(self, number: np.ndarray, known: np.ndarray) -> np.ndarray:
        """Columns continuation, n1, n2, n3+, total of word numbers; zeros where unknown."""
        out = np.zeros((len(number), 5))
        r = np.searchsorted(self.offsets, number, "right") - 1
        held = self.stores.setdefault("s", store.Files(f"{self.folder}/stats"))
        order = np.argsort(number, kind="stable")
        order = order[known[order]]
        cut = np.append(np.flatnonzero(np.diff(r[order], prepend=-1)), len(order))
        for s, e in zip(cut[:-1], cut[1:]):
            part = order[s:e]
            k = int(r[part[0]])
            if k in held:
                for i, name in enumerate(STATS):
                    out[part, i] = store.Small(held.array(k, name, "u1"))[number[part] - self.offsets[k]]
        return out

    def pairs(self) -> store.Store:
        return self.stores.setdefault("p", store.Store(f"{self.folder}/pairs", self.bits, {"c": store.SMALL} if self.order == 2 else {"o": "u4", "t": "u1"}))

    def grams(self, key: np.ndarray, pair: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(kinds of u, c(uvw)) of known pairs by their keys, places in their ranges and first numbers."""
        kinds, out = np.zeros(len(key), np.int64), np.zeros(len(key), np.int64)
        r = (key >> U(64 - self.bits)).astype(np.int64)
        order = np.argsort(r, kind="stable")
        cut = np.append(np.flatnonzero(np.diff(r[order], prepend=-1)), len(order))
        grams = self.stores.setdefault("g", store.Files(f"{self.folder}/grams"))
        for s, e in zip(cut[:-1], cut[1:]):
            part = order[s:e]
            k = int(r[part[0]])
            o, us = self.pairs().array(k, "o", "u4"), grams.array(k, "u", "u4")
            at, want = pair[part], u[part]
            lo = o[at].astype(np.int64)
            end = np.where(at + 1 < len(o), o[np.minimum(at + 1, len(o) - 1)], len(us)).astype(np.int64)
            kinds[part], hi = end - lo, end.copy()
            while (apart := lo < hi).any():
                mid = (lo + hi) >> 1
                less = apart & (us[np.minimum(mid, len(us) - 1)] < want)
                hi = np.where(apart & ~less, mid, hi)
                lo = np.where(less, mid + 1, lo)
            at = np.minimum(lo, len(us) - 1)
            n = store.Small(grams.array(k, "n", "u1"))[at]
            out[part] = np.where((lo < end) & (us[at] == want), n, 0)
        return kinds, out

    def score(self, c: Chunk) -> dict[str, np.ndarray]:
        t, off = tokens(c)
        h, back = np.unique(np.append(t, START), return_inverse=True)
        known, count, number = self.numbers(h)
        stat = self.stats(number, known)
        u, v, w = contexts_of(back[:-1], off, back[-1])
        cont, total = stat[:, 0], np.maximum(stat[:, 4], 1)
        rest = 1 / (self.words + 1)
        low = (np.maximum(cont - self.word_discount[np.minimum(cont, 3).astype(int)], 0) / self.types + self.spare * rest) if self.types else np.full(len(h), rest)
        left = np.where(stat[:, 4] > 0, (stat[:, 1:4] @ self.pair_discount[1:]) / total, 1.0)
        p = left[v] * low[w]
        both = np.flatnonzero(known[v] & known[w])
        key = pair_key(number[v[both]], number[w[both]])
        there, got = self.pairs().find(key)
        gram = np.zeros(len(w), np.int64)
        if self.order == 3:
            n = np.zeros(len(key), np.int64)
            n[there], gram[both[there]] = self.grams(key[there], got["at"][there], number[u[both[there]]])
            gram[~known[u]] = 0
        else:
            n = got["c"].astype(np.int64)
        p[both] += np.maximum(n - self.pair_discount[np.minimum(n, 3)], 0) / total[v[both]]
        if self.order == 3:
            seen = np.zeros(len(w) + 1, bool)
            seen[both[there] + 1] = True  # the pair is the next token's context
            seen[off[:-1]] = False
            have = np.zeros((len(w), 4))
            have[seen[:-1], :2] = 1
            ask = np.flatnonzero(known[u] & known[v])
            held = self.stores.setdefault("c", store.Store(f"{self.folder}/contexts", self.bits, CONTEXT))
            more, stats = held.find(pair_key(number[u[ask]], number[v[ask]]))
            have[ask[more]] = np.column_stack([stats[x][more] for x in CONTEXT])
            whole = (np.maximum(gram - self.gram_discount[np.minimum(gram, 3)], 0) + (have[:, 1:] @ self.gram_discount[1:]) * p) / np.maximum(have[:, 0], 1)
            p = np.where(have[:, 0] > 0, whole, p)
        kc = np.where(known, count, 0)
        base = np.log10((kc + 1) / (self.total + self.words + 1))
        add = lambda x: np.add.reduceat(x, off[:-1]) if c.n else x[:0]
        return {"n_tokens": np.diff(off), "n_known": add((kc[w] > 0).astype(np.int64)), "base_score": add(base[w]), "score": add(np.log10(p))}


def contexts_of(w: np.ndarray, off: np.ndarray, start: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(u, v, w) of all tokens: starts stand before each text."""
    out = [w]
    for _ in range(2):
        before = np.empty_like(w)
        before[1:] = out[0][:-1]
        before[off[:-1]] = start
        out.insert(0, before)
    return tuple(out)


def planes(x: np.ndarray, kind: str) -> bytes:
    """All first bytes, all second bytes and so on: what is mostly zero is compressed well."""
    x = np.ascontiguousarray(x.astype(kind))
    return x.view(np.uint8).reshape(len(x), x.itemsize).T.tobytes()


def unplanes(data: bytes, kind: str) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def stepped(keys: np.ndarray) -> bytes:
    """Sorted keys as differences."""
    return planes(np.diff(keys, prepend=U(0)), "<u8")


def unstepped(data: bytes) -> np.ndarray:
    return np.cumsum(unplanes(data, "<u8"), dtype=U)


def runs(*columns: np.ndarray) -> np.ndarray:
    """Where the runs of equal rows of sorted columns begin."""
    if not len(columns[0]):
        return np.zeros(0, np.int64)
    return np.flatnonzero(np.append(True, np.any([x[1:] != x[:-1] for x in columns], axis=0)))


def joined(parts: list[np.ndarray], kind) -> np.ndarray:
    return np.concatenate(parts) if parts else np.zeros(0, kind)


def grouped(key: np.ndarray, u: np.ndarray, n: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """Entries (key, u), each counting n or 1, summed: (sorted distinct keys, where each one's entries begin, u, n).

    Sorts of single words of 64 bits are several times as fast as one over two columns.
    """
    by = np.argsort(key)
    key = key[by]
    first = runs(key)
    both = (np.repeat(np.arange(len(first), dtype=U), np.diff(np.append(first, len(key)))) << U(32)) | u[by].astype(U)
    key = key[first]
    if n is None:
        both.sort()
        at = runs(both)
        n = np.diff(np.append(at, len(both)))
    else:
        again = np.argsort(both)
        both = both[again]
        at = runs(both)
        n = np.add.reduceat(n[by[again]], at) if len(at) else n
    both = both[at]
    return key, runs(both >> U(32)), (both & U(0xFFFFFFFF)).astype(np.uint32), n


def pair_key(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    return mix((v.astype(U) << U(32)) | w.astype(U))


def fit(texts: DataFrame, folder: str | None = None, order: int = 3) -> Model:
    """texts: one column text, the training documents."""
    if order not in (2, 3):
        raise ValueError("order is 2 or 3")
    spark = texts.sparkSession
    ship(spark)
    bits = store.range_bits(spark)
    folder = folder or store.new_folder(spark, "language-model")

    def pack_counts(cols):
        k, back = np.unique(cols["key"], return_inverse=True)
        n = np.bincount(back, weights=cols["n"]).astype(np.int64)
        return [(r, s.stop - s.start, [k[s].tobytes(), n[s].tobytes()]) for r, s in store.by_range(k, bits)]

    def added(parts):
        k, back = np.unique(np.concatenate([np.frombuffer(d[0], U) for _, d in parts]), return_inverse=True)
        return k, np.bincount(back, weights=np.concatenate([np.frombuffer(d[1], np.int64) for _, d in parts])).astype(np.int64)

    def count_words(batches):
        held = store.Held(pack_counts, ["key", "n"])
        for batch in batches:
            for c in chunks(batch.column(0), SIZE):
                k, n = np.unique(tokens(c)[0], return_counts=True)
                yield from held.add(key=np.append(k, START), n=np.append(n, c.n))
        yield from held.flush()

    def word_range(r, parts):
        k, n = added(parts)
        store.write_range(f"{folder}/words", r, k, {"c": store.Small.packed(n)})
        start = n[k == START].sum()
        return {"words": len(k) - (k == START).sum(), "total": n.sum() - start, "texts": start, "size": len(k)}

    with _shuffles_let_go(spark):
        rows = store.run_ranges(texts.mapInArrow(count_words, store.PACKED_DDL), bits, word_range, ["words", "total", "texts", "size"], [f"{folder}/words"])
    sizes = np.zeros(1 << bits, np.int64)
    sizes[[row["r"] for row in rows]] = [row["size"] for row in rows]
    words, total, n_texts = (store.total(rows, name) for name in ("words", "total", "texts"))
    model = Model(folder, bits, np.concatenate([[0], np.cumsum(sizes)[:-1]]), words, total, n_texts, order, np.zeros(4), np.zeros(4), np.zeros(4), 0, 1.0)
    if sizes.sum() >= 1 << 32:
        raise OverflowError("more than 2^32 distinct words")

    def count_grams(batches):
        held = store.Held(pack_grams, ["key", "u"])
        for batch in batches:
            for c in chunks(batch.column(0), SIZE):
                t, off = tokens(c)
                h, back = np.unique(np.append(t, START), return_inverse=True)
                number = model.numbers(h)[2]
                u, v, w = contexts_of(number[back[:-1]], off, number[back[-1]])
                yield from held.add(key=pair_key(v, w), u=(u if order == 3 else np.zeros_like(u)).astype("u4"))
        yield from held.flush()

    def pack_grams(cols):
        key, first, u, n = grouped(cols["key"], cols["u"])
        size, out = np.diff(np.append(first, len(u))), []
        for r, s in store.by_range(key, bits):
            g = slice(first[s.start], first[s.start] + size[s].sum())
            out.append((r, g.stop - g.start, [stepped(key[s]), planes(size[s], "<u4"), planes(u[g], "<u4"), planes(n[g], "<u4")]))
        return out

    def gram_ranges(batches):
        """Write each range's pairs and grams; send on, by the words' ranges, what words have of them."""
        held = store.Held(pack_stats, ["word", "kind", "n"])
        ranges = store.ranges_of(batches)
        for r in sorted(ranges):
            parts = ranges.pop(r)
            key = joined([np.repeat(unstepped(k), unplanes(size, "<u4")) for _, (k, size, _, _) in parts], U)
            u = joined([unplanes(x, "<u4") for _, (_, _, x, _) in parts], np.uint32)
            n = joined([unplanes(x, "<u4") for _, (_, _, _, x) in parts], np.uint32).astype(np.int64)
            del parts
            key, first, u, n = grouped(key, u, n)
            size = np.diff(np.append(first, len(u)))
            seen = np.add.reduceat(n, first) if len(n) else n
            many = size if order == 3 else seen  # order 2: u is 0 throughout
            store.write_range(f"{folder}/pairs", r, key, {"c": store.Small.packed(many)} if order == 2 else {"o": first.astype("u4"), "t": (seen > 1).astype("u1")})
            if order == 3:
                store.put(f"{folder}/grams", f"u-{r}", u.astype("u4").tobytes())
                store.put(f"{folder}/grams", f"n-{r}", store.Small.packed(n))
            pair = unmix(key)
            v, w = (pair >> U(32)).astype(np.int64), (pair & U(0xFFFFFFFF)).astype(np.int64)
            code, kinds = np.unique(np.concatenate([w * 8, v * 8 + np.minimum(many, 3)]), return_counts=True)
            before, back = np.unique(v, return_inverse=True)
            yield from held.add(word=np.concatenate([code >> 3, before]), kind=np.concatenate([code & 7, np.full(len(before), 4)]), n=np.concatenate([kinds, np.bincount(back, weights=many).astype(np.int64)]))
        yield from held.flush()

    start = model.numbers(np.array([START]))[2] if model.texts else np.zeros(1, np.int64)
    starts = pair_key(start, start)[0]  # a context, but no pair of the pairs

    def send_contexts(batches):
        """By range, what each range's grams say of the contexts seen more than once."""
        grams = store.Files(f"{folder}/grams")
        for batch in batches:
            for r in batch.column(0).to_pylist():
                key, first, u = model.pairs().array(r, "key", "u8"), model.pairs().array(r, "o", "u4"), grams.array(r, "u", "u4")
                n = store.Small(grams.array(r, "n", "u1")).all()
                size = np.diff(first.astype(np.int64), append=len(u))
                context = pair_key(u.astype(np.int64), np.repeat((unmix(key) >> U(32)).astype(np.int64), size))
                for s in range(0, len(context), store.HELD):
                    part = context[s : s + store.HELD]
                    keep = (model.pairs().find(part)[1]["t"] > 0) | (part == starts)
                    for i in range(0, len(rows := pack_contexts(part[keep], n[s : s + store.HELD][keep])), 64):
                        yield store.packed_rows(rows[i : i + 64])

    def context_sums(key, columns):
        by = np.argsort(key)
        at = runs(key[by])
        return key[by][at], [np.add.reduceat(x[by], at) if len(at) else x[by] for x in columns]

    def pack_contexts(key, n):
        key, (c, *kinds) = context_sums(key, [n, *((n == k).astype(np.int64) for k in (1, 2)), (n > 2).astype(np.int64)])
        out = []
        for r, s in store.by_range(key, bits):
            out.append((r, s.stop - s.start, [stepped(key[s]), *(planes(x[s], "<u4") for x in (c, *kinds))]))
        return out

    def pack_stats(cols):
        code, back = np.unique(cols["word"] * 8 + cols["kind"], return_inverse=True)
        n = np.bincount(back, weights=cols["n"]).astype(np.int64)
        word, kind = code >> 3, (code & 7).astype(np.uint8)
        cut = np.append(np.searchsorted(word, model.offsets), len(word))
        out = []
        for r in np.flatnonzero(np.diff(cut)).tolist():
            s = slice(cut[r], cut[r + 1])
            out.append((r, s.stop - s.start, [planes(np.diff(word[s] - model.offsets[r], prepend=0), "<u4"), kind[s].tobytes(), planes(n[s], "<u8")]))
        return out

    def stat_range(r, parts):
        table = np.zeros((int(sizes[r]), 5), np.int64)
        for _, (word, kind, n) in parts:
            np.add.at(table, (np.cumsum(unplanes(word, "<u4").astype(np.int64)), np.frombuffer(kind, np.uint8)), unplanes(n, "<u8").astype(np.int64))
        for i, name in enumerate(STATS):
            store.put(f"{folder}/stats", f"{name}-{r}", store.Small.packed(table[:, i]))
        cont = table[:, 0]
        return {"types": cont.sum(), "any": (cont > 0).sum()} | {f"t{k}": (cont == k).sum() for k in (1, 2, 3, 4)}

    def context_range(r, parts):
        columns = [np.concatenate([unplanes(d[i], "<u4").astype(np.int64) for _, d in parts]) for i in (1, 2, 3, 4)]
        key, columns = context_sums(np.concatenate([unstepped(d[0]) for _, d in parts]), columns)
        store.write_range(f"{folder}/contexts", r, key, {k: store.Small.packed(x) for k, x in zip(CONTEXT, columns)})
        return {"contexts": len(key)}

    with _shuffles_let_go(spark):
        grams = store.dealt(texts.mapInArrow(count_grams, store.PACKED_DDL), bits, every=True).mapInArrow(gram_ranges, store.PACKED_DDL)
        rows = store.run_ranges(grams, bits, stat_range, ["types", "any", "t1", "t2", "t3", "t4"], [f"{folder}/stats"])
        s = {name: store.total(rows, name) for name in ("types", "any", "t1", "t2", "t3", "t4")}
        for f in ("pairs", "grams"):
            store.seal(f"{folder}/{f}", list(range(1 << bits)))
        if order == 3:
            sent = spark.range(0, 1 << bits, 1, 1 << bits).mapInArrow(send_contexts, store.PACKED_DDL)
            store.run_ranges(sent, bits, context_range, ["contexts"], [f"{folder}/contexts"])
    model.types = s["types"]
    if model.types:
        model.pair_discount, model.gram_discount = map(discounts, _seen(spark, folder, order, bits))
        model.word_discount = discounts([s[f"t{k}"] for k in (1, 2, 3, 4)])
        model.spare = float(model.word_discount[1:] @ np.array([s["t1"], s["t2"], s["any"] - s["t1"] - s["t2"]])) / model.types
    return model


@contextmanager
def _shuffles_let_go(spark):
    """Within it, a job's shuffles leave the disk when the job is done."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def _seen(spark, folder: str, order: int, bits: int) -> tuple[list[int], list[int]]:
    """How many pairs and how many grams have counts of one to four."""

    def run(batches):
        held, grams = store.Files(f"{folder}/pairs"), store.Files(f"{folder}/grams")
        for batch in batches:
            for r in batch.column(0).to_pylist():
                if order == 2:
                    n, pairs = np.zeros(0, np.int64), store.Small(held.array(r, "c", "u1")).all()
                else:
                    n = store.Small(grams.array(r, "n", "u1")).all()
                    pairs = np.diff(held.array(r, "o", "u4").astype(np.int64), append=len(n))
                yield pa.RecordBatch.from_arrays([pa.array([int((x == k).sum())], pa.int64()) for x in (pairs, n) for k in (1, 2, 3, 4)], [f"n{i}" for i in range(8)])

    row = spark.range(1 << bits).mapInArrow(run, ", ".join(f"n{i} long" for i in range(8))).agg(*(F.sum(f"n{i}") for i in range(8))).first()
    return [int(x) for x in row[:4]], [int(x) for x in row[4:]]


def score_documents(docs: DataFrame, folds: int = 7, which: int = 2, order: int = 3) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    ship(docs.sparkSession)
    out = held_out(docs["doc_id"], folds, which)
    model = fit(docs.where(~out).select("text"), order=order)
    narrow = docs.select("doc_id", out.alias("held_out"), "text")

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(2), SIZE):
                s = model.score(c)
                cols = [pa.array(s["n_tokens"]), pa.array(s["n_known"]), pa.array(np.full(c.n, model.total, np.int64)), pa.array(s["base_score"]), pa.array(s["score"])]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c.lo, c.n), batch.column(1).slice(c.lo, c.n), *cols], ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
