"""N-gram Jaccard join by prefix trees, and the components of its links.

A document's set holds the hashes of its k-word shingles. All sets are ordered alike: shingles rarer than FREQUENT
documents first, by hash, then the frequent ones from rare to frequent, by counts over all documents (from CLASSES - 1
on by hash alone). Equal sets fall together first. If two sets reach the threshold, their prefixes (the first
n - ceil(t n) + 1 in that order) share a shingle; the first one they share is where they meet.

The sets that meet at a shingle form a prefix tree: its root is the shingle, and each set's path is what its prefix
holds from there on. The trees of a range of shingles are walked together, level by level, by all of their sets at
once: what stands at a level is a set and a subtree (an interval of the sorted paths) with their overlap so far, so
sets that share a path share the work, and the subtree goes when that overlap and what is left of both can't reach
the threshold. Only pairs whose prefixes pass the whole walk leave the task; their whole sets are then compared.

No meeting place emits all its pairs. Each is first walked by one of its sets (small ones by all); what is then
connected needs no more comparison, and the second walk skips subtrees of the walker's own component. The sets of a
hot shingle are dealt to blocks of about LIMIT, which are walked two by two in tasks of their own.

Defined cases: null or empty text has the empty set and links with nothing; a text of fewer than k words is one
shingle; a null doc_id links with nothing; rows of one doc_id count as one document that links by any of its sets,
and each row has its own n_shingles; ties in the order are impossible but for equal hashes; extra columns are dropped;
an empty table gives no rows. Shingles are equal if 54 bits of their hashes are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship, written
from stripmatch.llm import store
from stripmatch.llm.textnp import _MULT, U, Chunk, chunks, mix, release
from stripmatch.operators.components import connected_components

FREQUENT, SMALL, CLASSES = 24, 8, 1024
LIMIT = 512  # sets of a meeting place that are walked together
DEEP = 64  # levels that trees are walked; what is left is counted pair by pair
STEP, HELD_TOKENS = 500_000, 4_000_000  # (set, subtree) that a walk begins with, shingles of paths held at once
RARE_BYTES, PLACE_BYTES = 4, 6
LONE = np.uint32(1 << 31)  # mark of a hot shingle's set, whose block is kept even if it has no other


def shingle_sets(c: Chunk, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(text, shingle) of a chunk's sets, ordered by both; shingles are 54-bit."""
    h = c.hashes(fold=True)
    w, at = c.windows(h, k)
    doc = c.wd[at]
    n = np.diff(c.wo)
    few = np.flatnonzero((n > 0) & (n < k))
    if len(few):
        whole = np.zeros(len(few), U)
        for j in range(k - 1):
            ok = n[few] > j
            whole[ok] += h[c.wo[few[ok]] + j] * _MULT[20 + j]
        w, doc = np.concatenate([w, mix(whole + n[few].astype(U))]), np.concatenate([doc, few])
    both = np.unique((doc.astype(U) << U(54)) | (w >> U(10)))
    return (both >> U(54)).astype(np.int64), both & U((1 << 54) - 1)


def frequent_shingles(docs: DataFrame, k: int, bits: int, folder: str) -> None:
    """Write the shingles of more than FREQUENT documents, with their counts. (Keys are cut short: it is only an order.)"""

    def pack(cols):
        u, n = np.unique(cols["key"], return_counts=True)
        n = np.minimum(n, 65_535).astype(np.uint16)
        return [(r, s.stop - s.start, [store.short(u[s], bits, RARE_BYTES), n[s].tobytes()]) for r, s in store.by_range(u, bits)]

    def run(batches):
        held = store.Held(pack, ["key"])
        for batch in batches:
            for c in chunks(batch.column(0)):
                yield from held.add(key=store.trimmed(shingle_sets(c, k)[1] << U(10), bits, RARE_BYTES))
        yield from held.flush()

    def each(r, parts):
        key = np.concatenate([store.long(d[0], r, bits, RARE_BYTES) for _, d in parts])
        u, back = np.unique(key, return_inverse=True)
        n = np.bincount(back, weights=np.concatenate([np.frombuffer(d[1], np.uint16) for _, d in parts]))
        often = n > FREQUENT
        store.write_range(folder, r, u[often], {"n": n[often].astype("u4")})
        return {"n": often.sum()}

    store.run_ranges(docs.select("text").mapInArrow(run, store.PACKED_DDL), bits, each, ["n"], [folder])


def least_shared(n: np.ndarray, percent: int) -> np.ndarray:
    return -(-percent * n // 100)


def signatures(docs: DataFrame, k: int, percent: int, bits: int, frequent: str) -> DataFrame:
    """row (its number), doc_id, n, two hashes of the set, and its prefix."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches):
        often = store.Store(frequent, bits, {"n": "u4"})
        for batch in batches:
            for c in chunks(batch.column(1)):
                doc, s = shingle_sets(c, k)
                n = np.bincount(doc, minlength=c.n)
                off = np.concatenate([[0], np.cumsum(n)])
                sums = []
                for salt in (U(1), U(2)):
                    total = np.zeros(len(s) + 1, U)
                    np.cumsum(mix(s + salt * _MULT[30]), out=total[1:])
                    sums.append((total[off[1:]] - total[off[:-1]]).view(np.int64))
                _, got = often.find(store.trimmed(s << U(10), bits, RARE_BYTES))
                place = (np.minimum(got["n"], CLASSES - 1).astype(U) << U(54)) | s  # the global order
                place = place[np.lexsort((place, doc))] if got["n"].any() else place
                size = np.where(n > 0, n - least_shared(n, percent) + 1, 0)
                prefix = [place[o : o + z].tobytes() for o, z in zip(off.tolist(), size.tolist())]
                cols = [batch.column(0).slice(c.lo, c.n), pa.array(n), *map(pa.array, sums), pa.array(prefix, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n", "s1", "s2", "prefix"])

    found = docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n long, s1 long, s2 long, prefix binary")
    return found.withColumn("row", F.monotonically_increasing_id())


def hot_shingles(sets: DataFrame, bits: int, first: str, folder: str) -> None:
    """Write the shingles that are in the prefixes of more than LIMIT sets, with their number. sets: row, rep, n, prefix, of which those with a row in first count."""

    def pack(cols):
        u, n = np.unique(cols["key"], return_counts=True)
        return [(r, s.stop - s.start, [u[s].tobytes(), n[s].tobytes()]) for r, s in store.by_range(u, bits)]

    def run(batches):
        held = store.Held(pack, ["key"])
        for batch in store.among(batches, first, bits):
            place = np.frombuffer(b"".join(batch.column(3).to_pylist()), U)
            yield from held.add(key=place[place >> U(54) >= U(LIMIT)] << U(10))
        yield from held.flush()

    def each(r, parts):
        u, back = np.unique(np.concatenate([np.frombuffer(d[0], U) for _, d in parts]), return_inverse=True)
        n = np.bincount(back, weights=np.concatenate([np.frombuffer(d[1], np.int64) for _, d in parts])).astype(np.int64)
        store.write_range(folder, r, u[n > LIMIT], {"n": n[n > LIMIT]})
        return {"n": (n > LIMIT).sum()}

    store.run_ranges(sets.mapInArrow(run, store.PACKED_DDL), bits, each, ["n"], [folder])


def block_key(key: np.ndarray, block: np.ndarray, bits: int) -> np.ndarray:
    """The meeting place of a block of a shingle's sets; mixed, as prefixes hold the smallest hashes and would crowd the first ranges."""
    return store.trimmed(mix(key + block.astype(U) * _MULT[33]), bits, PLACE_BYTES)


def meeting_places(sets: DataFrame, bits: int, first: str, hot: str, paths: str, folder: str) -> None:
    """Write each partition's prefixes (the paths of the trees), and by shingle the paths that pass through it.

    The sets of a hot shingle are dealt to blocks of about LIMIT, each a meeting place of its own. sets: row, rep, n, prefix,
    of which those with a row in first count.
    """

    def pack(cols):
        order = np.argsort(cols["key"], kind="stable")
        key, idx, pos = (cols[c][order] for c in ("key", "idx", "pos"))
        part = TaskContext.get().partitionId()
        return [(r, s.stop - s.start, [np.int64(part).tobytes(), store.short(key[s], bits, PLACE_BYTES), idx[s].tobytes(), pos[s].tobytes()]) for r, s in store.by_range(key, bits)]

    def run(batches):
        held, blocks = store.Held(pack, ["key", "idx", "pos"]), store.Store(hot, bits, {"n": "i8"})
        part, done, kept = TaskContext.get().partitionId(), 0, ([], [], [], [])
        for batch in store.among(batches, first, bits):
            raw = batch.column(3).to_pylist()
            size = np.array([len(p) // 8 for p in raw], np.int64)
            tok = np.frombuffer(b"".join(raw), U)
            for to, x in zip(kept, (tok, size, np.asarray(batch.column(1)), np.asarray(batch.column(2)))):
                to.append(x)
            idx = np.repeat(np.arange(done, done + len(size), dtype=np.uint32), size)
            pos = (np.arange(len(tok)) - np.repeat(np.cumsum(size) - size, size)).astype(np.uint32)
            key, block = tok << U(10), np.zeros(len(tok), np.int64)  # without the class
            often = np.flatnonzero(tok >> U(54) >= U(LIMIT))
            is_hot, got = blocks.find(key[often])
            often, n = often[is_hot], got["n"][is_hot]
            pos[often] |= LONE
            block[often] = (mix(idx[often].astype(U) + np.array([part + 1], U) * _MULT[34]) % (-(-n // LIMIT)).astype(U)).astype(np.int64)
            yield from held.add(key=block_key(key, block, bits), idx=idx, pos=pos)
            done += len(size)
        yield from held.flush()
        if done:
            tok, size, doc, n = (np.concatenate(x) for x in kept)
            for name, x in (("tok", tok), ("off", np.concatenate([[0], np.cumsum(size)])), ("doc", doc.astype("i8")), ("n", n.astype("i8"))):
                store.put(paths, f"{name}-{part}", x.tobytes())

    def each(r, parts):
        cols = [], [], [], []
        for n, (part, key, idx, pos) in parts:
            cols[0].append(store.long(key, r, bits, PLACE_BYTES)), cols[1].append(np.full(n, np.frombuffer(part, np.int64)[0], np.uint32))
            cols[2].append(np.frombuffer(idx, np.uint32)), cols[3].append(np.frombuffer(pos, np.uint32))
        key, part, idx, pos = map(np.concatenate, cols)
        order = np.lexsort((idx, part, pos, key))
        key, part, idx, pos = key[order], part[order], idx[order], pos[order]
        same = np.zeros(len(key), bool)
        same[1:] = key[1:] == key[:-1]
        same[:-1] |= same[1:].copy()
        same |= pos >= LONE
        store.write_range(folder, r, key[same], {"part": part[same], "idx": idx[same], "pos": pos[same] & ~LONE})
        return {"n": same.sum()}

    store.run_ranges(sets.mapInArrow(run, store.PACKED_DDL), bits, each, ["n"], [folder])


class Walk:
    """Prefix trees over sorted paths: intervals of equal beginnings are their subtrees.

    tok holds prefixes; a path is tok[start:end] and begins with the shingle of its meeting place (number `place`);
    pos shingles stand before it in its set of n, whose document has that label. Paths are sorted by place, then as
    sequences, down to DEEP; depth[i] tells how much of paths i - 1 and i is shared.
    """

    def __init__(self, tok: np.ndarray, start, end, n, pos, place, doc, label=None):
        self.tok, m = tok, len(start)
        order = np.argsort(place, kind="stable")
        self.depth = np.zeros(m, np.int64)
        head = np.append(True, place[order][1:] != place[order][:-1]) if m else np.zeros(0, bool)
        slots, group, d = np.arange(m), np.cumsum(head) - 1, 0
        while len(slots) and d < DEEP:
            d += 1
            size = np.bincount(group)
            many = size[group] > 1
            slots, group = slots[many], group[many]
            if not len(slots):
                break
            who = order[slots]
            at = start[who] + d
            there = at < end[who]
            value = np.where(there, tok[np.minimum(at, len(tok) - 1)], 0)
            by = np.lexsort((value, there, group))
            who, value, there = who[by], value[by], there[by]
            order[slots] = who
            new = np.append(True, (group[1:] != group[:-1]))
            apart = ~new & np.append(False, (value[1:] != value[:-1]) | (there[1:] != there[:-1]) | ~there[1:])
            self.depth[slots[apart]] = d
            group = np.cumsum(new | apart) - 1
        same_place = ~head
        deep = slots[1:][group[1:] == group[:-1]] if len(slots) else slots
        self.depth[deep] = DEEP
        self.depth[~same_place] = 0
        self.order = order
        self.start, self.end, self.n, self.pos, self.doc, self.place = (x[order] for x in (start, end, n, pos, doc, place))
        self.label = None if label is None else label[order]
        self.fork_keys = np.sort(self.depth * (m + 1) + np.arange(m))
        self.least_n, self.most_left = self._table(self.n, np.minimum), self._table(self.n - self.pos, np.maximum)
        if label is not None:
            self.changes = np.concatenate([[0], np.cumsum(np.append(False, self.label[1:] != self.label[:-1]) if m else [])])

    @staticmethod
    def _table(x, best):
        table = [x]
        while 2 * (step := 1 << (len(table) - 1)) <= len(x):
            table.append(np.append(best(table[-1][:-step], table[-1][step:]), table[-1][len(x) - step :]))
        return table

    def _best(self, table, best, lo, hi):
        level = np.frexp((hi - lo).astype(np.float64))[1] - 1
        out = np.empty(len(lo), np.int64)
        for k in np.unique(level).tolist():
            a = np.flatnonzero(level == k)
            out[a] = best(table[k][lo[a]], table[k][hi[a] - (1 << k)])
        return out

    def pairs(self, other: "Walk", p: np.ndarray, lo: np.ndarray, hi: np.ndarray, percent: int) -> np.ndarray:
        """Pairs of documents that paths p of `other` and the trees' intervals [lo, hi) leave: whose prefixes may belong to linked sets."""
        out = []
        ok = lo < hi
        p, lo, hi = p[ok], lo[ok], hi[ok]
        begin = np.cumsum(hi - lo)
        cut = np.searchsorted(begin, np.arange(0, begin[-1] if len(begin) else 0, STEP), "left") if len(begin) else np.zeros(0, int)
        for a, b in zip(cut.tolist(), np.append(cut[1:], len(p)).tolist()):
            out += self._walk(other, p[a:b], lo[a:b], hi[a:b], percent)
        found = np.concatenate(out) if out else np.zeros((0, 2), np.int64)
        return np.unique(np.sort(found, axis=1), axis=0)

    def _walk(self, other, p, lo, hi, percent):
        tok, out, d = self.tok, [], 1
        left = other.n - other.pos
        shared, at = np.ones(len(p), np.int64), other.start[p] + 1
        while len(p):
            need = -(-percent * (other.n[p] + self._best(self.least_n, np.minimum, lo, hi)) // (100 + percent))
            most = shared + np.minimum(self._best(self.most_left, np.maximum, lo, hi) - d, left[p] - (at - other.start[p]))
            go = most >= need
            if self.label is not None:
                go &= (self.changes[hi] != self.changes[lo + 1]) | (self.label[lo] != other.label[p])
            p, lo, hi, shared, at = (x[go] for x in (p, lo, hi, shared, at))
            # subtrees part where paths first differ
            first = np.searchsorted(self.fork_keys, d * (len(self.n) + 1) + lo + 1)
            forks = np.searchsorted(self.fork_keys, d * (len(self.n) + 1) + hi) - first
            if forks.any():
                whom = np.repeat(np.arange(len(p)), forks + 1)
                nth = np.arange(len(whom)) - np.repeat(np.cumsum(forks + 1) - forks - 1, forks + 1)
                cut = self.fork_keys[np.minimum(first[whom] + nth, len(self.fork_keys) - 1)] - d * (len(self.n) + 1)
                before = self.fork_keys[np.maximum(first[whom] + nth - 1, 0)] - d * (len(self.n) + 1)
                lo, hi = np.where(nth == 0, lo[whom], before), np.where(nth == forks[whom], hi[whom], cut)
                p, shared, at = p[whom], shared[whom], at[whom]
            over = (at >= other.end[p]) | (self.start[lo] + d >= self.end[lo]) | (d >= DEEP)
            if over.any():
                out.append(self._settled(other, p[over], lo[over], hi[over], shared[over], at[over], d, percent))
                p, lo, hi, shared, at = (x[~over] for x in (p, lo, hi, shared, at))
            if not len(p):
                break
            want = tok[self.start[lo] + d]
            a, b = at.copy(), other.end[p].copy()
            while (apart := a < b).any():
                mid = (a + b) >> 1
                less = apart & (tok[np.minimum(mid, len(tok) - 1)] < want)
                b = np.where(apart & ~less, mid, b)
                a = np.where(less, mid + 1, a)
            past = a >= other.end[p]  # what follows in the trees is beyond the walker's prefix
            if past.any():
                out.append(self._settled(other, p[past], lo[past], hi[past], shared[past], a[past], d, percent))
                p, lo, hi, shared, a, want = (x[~past] for x in (p, lo, hi, shared, a, want))
            hit = tok[np.minimum(a, len(tok) - 1)] == want
            shared, at = shared + hit, a + hit
            d += 1
        return out

    def _settled(self, other, p, lo, hi, shared, at, d, percent):
        """Walkers and single paths: at the end of either prefix, or too deep for the trees."""
        size = hi - lo
        i = np.repeat(np.arange(len(p)), size)
        j = np.repeat(lo, size) + np.arange(len(i)) - np.repeat(np.cumsum(size) - size, size)
        p, shared, at = p[i], shared[i], at[i]
        need = -(-percent * (other.n[p] + self.n[j]) // (100 + percent))
        go = shared + np.minimum(self.n[j] - self.pos[j] - d, other.n[p] - other.pos[p] - (at - other.start[p])) >= need
        go &= other.doc[p] != self.doc[j]
        if self.label is not None:
            go &= self.label[j] != other.label[p]
        before_p, before_j = self.tok[np.maximum(other.start[p] - 1, 0)], self.tok[np.maximum(self.start[j] - 1, 0)]
        go &= (other.pos[p] == 0) | (self.pos[j] == 0) | (before_p != before_j)  # else they meet there too
        p, j, shared, at, need = (x[go] for x in (p, j, shared, at, need))
        keep = np.ones(len(p), bool)
        if d >= DEEP:
            for x in range(len(p)):
                a, b = self.tok[at[x] : other.end[p[x]]], self.tok[self.start[j[x]] + d : self.end[j[x]]]
                if len(a) and len(b):
                    last = min(a[-1], b[-1])
                    a_, b_ = a[: np.searchsorted(a, last, "right")], b[: np.searchsorted(b, last, "right")]
                    rest = min(other.n[p[x]] - other.pos[p[x]] - (at[x] - other.start[p[x]]) - len(a_), self.n[j[x]] - self.pos[j[x]] - d - len(b_))
                    keep[x] = shared[x] + common(a_, b_) + rest >= need[x]
        return np.column_stack([other.doc[p[keep]], self.doc[j[keep]]])


def common(a: np.ndarray, b: np.ndarray) -> int:
    """How many members two sorted sets share."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    return int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())


class Places:
    """The meeting places of a folder, with the paths that pass through them."""

    def __init__(self, folder: str, paths: str, bits: int, percent: int, labels: str | None = None):
        self.places, self.paths, self.bits, self.percent = store.Files(folder), store.Files(paths), bits, percent
        self.labels = None if labels is None else store.Store(labels, bits, {"label": "i8"})

    def range(self, r: int) -> tuple[np.ndarray, ...]:
        """(bounds of the places, partition, number and place in its prefix of each path)."""
        key, part, idx, pos = (self.places.array(r, c, k) for c, k in (("key", "u8"), ("part", "u4"), ("idx", "u4"), ("pos", "u4")))
        at = np.append(np.flatnonzero(np.append(True, key[1:] != key[:-1])), len(key)) if len(key) else np.zeros(1, np.int64)
        return at, part, idx, pos.astype(np.int64)

    def block(self, key: int) -> np.ndarray:
        """Places in its range of the paths of one meeting place."""
        r = int(key >> U(64 - self.bits))
        keys = self.places.array(r, "key", "u8")
        return np.arange(np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right"))

    def described(self, part, idx) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document, size of the set, size of the prefix) of paths."""
        out = np.zeros((3, len(part)), np.int64)
        for x in np.unique(part).tolist():
            a = np.flatnonzero(part == x)
            off, i = self.paths.named(f"off-{x}").view("i8"), idx[a].astype(np.int64)
            out[:, a] = self.paths.named(f"doc-{x}").view("i8")[i], self.paths.named(f"n-{x}").view("i8")[i], off[i + 1] - off[i]
        return tuple(out)

    def label_of(self, doc: np.ndarray) -> np.ndarray:
        known, got = self.labels.find(mix(doc.view(U)))
        return np.where(known, got["label"], doc)

    def walk(self, groups: list[tuple]) -> list[Walk]:
        """A Walk for each (part, idx, pos, place), over prefixes that are held once."""
        part, idx = (np.concatenate([g[i] for g in groups]) for i in (0, 1))
        whole, back = np.unique((part.astype(U) << U(32)) | idx.astype(U), return_inverse=True)
        one, nth = (whole >> U(32)).astype(np.int64), (whole & U(0xFFFFFFFF)).astype(np.int64)
        doc, n, size = self.described(one, nth)
        first = np.cumsum(size) - size
        tok = []
        for x, i, z in zip(one.tolist(), nth.tolist(), size.tolist()):
            o = int(self.paths.named(f"off-{x}").view("i8")[i])
            tok.append(self.paths.named(f"tok-{x}").view("u8")[o : o + z])
        tok = np.concatenate(tok) if tok else np.zeros(0, U)
        label = None if self.labels is None else self.label_of(doc)
        out, s = [], 0
        for _, i, pos, place in groups:
            b = back[s : s + len(i)]
            s += len(i)
            out.append(Walk(tok, first[b] + pos, first[b] + size[b], n[b], pos, place, doc[b], None if label is None else label[b]))
        return out

    def first(self, r: int) -> np.ndarray:
        """Pairs that small places leave, and large ones to the path with fewest shingles before it."""
        return self._within(r, lambda size: size > 1, False)

    def later(self, r: int) -> np.ndarray:
        """Pairs of different components that large places leave."""
        return self._within(r, lambda size: size > SMALL, True)

    def _within(self, r, wanted, all_walk):
        at, part, idx, pos = self.range(r)
        size = np.diff(at)
        found = []
        take = np.flatnonzero(wanted(size))
        place = np.repeat(np.arange(len(size)), size)
        use = np.isin(place, take)
        part, idx, pos, place = (x[use] for x in (part, idx, pos, place))
        doc, _, length = self.described(part, idx)
        if all_walk and len(doc):
            label = self.label_of(doc)
            head = np.append(True, place[1:] != place[:-1])
            nth = np.cumsum(head) - 1
            mixed = np.zeros(nth[-1] + 1, bool)
            mixed[nth[label != label[head][nth]]] = True
            part, idx, pos, place, length = (x[mixed[nth]] for x in (part, idx, pos, place, length))
        head = np.flatnonzero(np.append(True, place[1:] != place[:-1])) if len(place) else np.zeros(0, int)
        load = np.cumsum(length)
        bounds = np.append(head, len(place))
        s = 0
        while s < len(head):
            e = max(s + 1, int(np.searchsorted(load[bounds[1:] - 1], (load[bounds[s] - 1] if bounds[s] else 0) + HELD_TOKENS, "right")))
            x = slice(bounds[s], bounds[e])
            (w,) = self.walk([(part[x], idx[x], pos[x], place[x])])
            edge = np.flatnonzero(np.append(True, w.place[1:] != w.place[:-1]))
            many = np.diff(np.append(edge, len(w.place)))
            stop, p = np.repeat(edge + many, many), np.arange(len(w.place))
            if all_walk:
                found.append(w.pairs(w, p, p + 1, stop, self.percent))
            else:
                few = np.repeat(many <= SMALL, many)
                found.append(w.pairs(w, p[few], p[few] + 1, stop[few], self.percent))
                big = np.flatnonzero(many > SMALL)
                if len(big):
                    rank = np.lexsort((w.order, w.place))  # within a place, paths stand by pos: the first one walks
                    centre = rank[edge[big]]
                    low, high = edge[big], edge[big] + many[big]
                    found.append(w.pairs(w, np.tile(centre, 2), np.concatenate([low, centre + 1]), np.concatenate([centre, high]), self.percent))
            s = e
        return np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)

    def heads(self, key: int, blocks: int) -> np.ndarray:
        """Pairs of the first document of a hot shingle's first block and those of the others."""
        docs = []
        for b in range(blocks):
            k = block_key(np.array([key], U), np.array([b]), self.bits)[0]
            at = self.block(k)[:1]
            r = int(k >> U(64 - self.bits))
            if len(at):
                docs.append(self.described(self.places.array(r, "part", "u4")[at], self.places.array(r, "idx", "u4")[at])[0][0])
        return np.array([(docs[0], d) for d in docs[1:] if d != docs[0]], np.int64).reshape(-1, 2)

    def across(self, key: int, i: int, j: int) -> np.ndarray:
        """Pairs of different components that two blocks of a hot shingle leave."""
        sides = []
        for b in (i, j):
            k = block_key(np.array([key], U), np.array([b]), self.bits)[0]
            r, at = int(k >> U(64 - self.bits)), self.block(k)
            part, idx, pos = (self.places.array(r, c, "u4")[at] for c in ("part", "idx", "pos"))
            sides.append((part, idx, pos.astype(np.int64), np.zeros(len(at), np.int64)))
        if not len(sides[0][0]) or not len(sides[1][0]):
            return np.zeros((0, 2), np.int64)
        left, right = self.walk(sides)
        m = len(left.n)
        return right.pairs(left, np.arange(m), np.zeros(m, np.int64), np.full(m, len(right.n)), self.percent)


def edge_batches(pairs: np.ndarray):
    for i in range(0, len(pairs), 100_000):
        part = pairs[i : i + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array(part[:, 0].copy()), pa.array(part[:, 1].copy())], ["a", "b"])


def all_ranges(spark, bits: int, each) -> DataFrame:
    """The rows of each(r) over all ranges, as an edge table."""

    def run(batches):
        for batch in batches:
            for r in batch.column(0).to_pylist():
                yield from edge_batches(each(int(r)))
        release()

    return spark.range(0, 1 << bits, 1, 1 << bits).mapInArrow(run, "a long, b long")


def hot_blocks(spark, bits: int, hot: str, pairs_of_blocks: bool) -> DataFrame:
    """The hot shingles (key, blocks), or the pairs of their blocks (key, i, j)."""

    def run(batches):
        held = store.Files(hot)
        for batch in batches:
            for r in batch.column(0).to_pylist():
                for key, n in zip(held.array(r, "key", "u8").view("i8").tolist(), (-(-held.array(r, "n", "i8") // LIMIT)).tolist()):
                    if not pairs_of_blocks:
                        yield pa.RecordBatch.from_arrays([pa.array([key]), pa.array([n]), pa.array([0])], ["key", "i", "j"])
                        continue
                    for i in range(n - 1):
                        j = np.arange(i + 1, n)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(j), key)), pa.array(np.full(len(j), i)), pa.array(j)], ["key", "i", "j"])

    return spark.range(0, 1 << bits, 1, 1 << bits).mapInArrow(run, "key long, i long, j long").repartition(1 << bits, "key", "i", "j")


def over_blocks(blocks: DataFrame, each) -> DataFrame:
    def run(batches):
        for batch in batches:
            for key, i, j in zip(np.asarray(batch.column(0)).view(U), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                yield from edge_batches(each(key, i, j))
        release()

    return blocks.mapInArrow(run, "a long, b long")


def verified(docs: DataFrame, pairs: DataFrame, k: int, percent: int, bits: int) -> DataFrame:
    """The pairs (a, b) of which some whole sets reach the threshold."""
    spark = docs.sparkSession
    wanted, sets, where = (store.new_folder(spark, f"jaccard-{x}") for x in ("wanted", "sets", "where"))
    store.write_lookup(pairs.select("a").union(pairs.select("b")).distinct(), bits, wanted)

    def pack(cols):
        order = np.argsort(cols["key"], kind="stable")
        key = cols["key"][order]
        return [(r, s.stop - s.start, [key[s].tobytes(), *(cols[c][order[s]].tobytes() for c in ("first", "size", "part"))]) for r, s in store.by_range(key, bits)]

    def write_sets(batches):
        """A partition's wanted sets in one file; of repeated rows one."""
        held, seen, kept, at = store.Held(pack, ["key", "first", "size", "part"]), set(), [], 0
        part = TaskContext.get().partitionId()
        for batch in store.among(batches, wanted, bits):
            ids = np.asarray(batch.column(0))
            for c in chunks(batch.column(1)):
                doc, s = shingle_sets(c, k)
                off = np.searchsorted(doc, np.arange(c.n + 1)).tolist()
                for i, (x, y) in enumerate(zip(off, off[1:])):
                    mark = int(ids[c.lo + i]), y - x, int(s[x:y].sum()), int(mix(s[x:y]).sum())
                    if x < y and mark not in seen:
                        seen.add(mark)
                        kept.append(s[x:y])
                        yield from held.add(key=mix(ids[c.lo + i : c.lo + i + 1].view(U)), first=np.array([at]), size=np.array([y - x]), part=np.array([part]))
                        at += y - x
        yield from held.flush()
        if kept:
            store.put(sets, f"tok-{part}", np.concatenate(kept).tobytes())
            kept.clear()
        release()

    def each(r, parts):
        cols = [np.concatenate([np.frombuffer(d[i], k) for _, d in parts]) for i, k in enumerate((U, np.int64, np.int64, np.int64))]
        order = np.lexsort(cols[::-1])
        key, first, size, part = (x[order] for x in cols)
        store.write_range(where, r, key, {"first": first, "size": size, "part": part})
        return {"n": len(key)}

    rows = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    store.run_ranges(rows.mapInArrow(write_sets, store.PACKED_DDL), bits, each, ["n"], [where])

    def check(batches):
        place, held = store.Files(where), store.Files(sets)

        def of(doc):
            key = mix(np.array([doc]).view(U))[0]
            r = int(key >> U(64 - bits))
            keys, first, size, part = (place.array(r, c, t) for c, t in (("key", "u8"), ("first", "i8"), ("size", "i8"), ("part", "i8")))
            lo, hi = np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right")
            return [held.named(f"tok-{part[i]}").view("u8")[first[i] : first[i] + size[i]] for i in range(lo, hi)]

        def linked(x, y):
            need = -(-percent * (len(x) + len(y)) // (100 + percent))
            return min(len(x), len(y)) >= need and common(x, y) >= need

        for batch in batches:
            last, own, found = None, [], []
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if a != last:
                    last, own = a, of(a)
                theirs = of(b)
                found.append(any(linked(x, y) for x in own for y in theirs))
            yield batch.filter(pa.array(found, pa.bool_()))
        release()

    return written(pairs.repartition(1 << bits, "a", "b").sortWithinPartitions("a", "b").mapInArrow(check, "a long, b long"), "links")


def jaccard_links(docs: DataFrame, k: int = 4, percent: int = 85) -> tuple[DataFrame, DataFrame]:
    """(sets, links): sets have doc_id, n and rep (the smallest doc_id with the same set); links join documents.

    Links between documents of one component may be missing where others already connect them.
    """
    spark = docs.sparkSession
    ship(spark)
    bits = store.range_bits(spark)
    frequent, hot, paths, places, first, labels = (store.new_folder(spark, f"jaccard-{x}") for x in ("frequent", "hot", "paths", "places", "first", "labels"))
    frequent_shingles(docs, k, bits, frequent)
    sets = written(signatures(docs, k, percent, bits, frequent), "signatures")
    usable = sets.where("n > 0 AND doc_id IS NOT NULL").withColumn("doc_id", F.col("doc_id").cast("long"))
    reps = written(usable.groupBy("s1", "s2", "n").agg(F.min("doc_id").alias("rep"), F.min_by("row", "doc_id").alias("row")), "reps")
    store.write_lookup(reps.select("row"), bits, first)
    prefixes = usable.select("row", F.col("doc_id").alias("rep"), "n", "prefix")
    hot_shingles(prefixes, bits, first, hot)
    meeting_places(prefixes, bits, first, hot, paths, places)

    pairs = all_ranges(spark, bits, lambda r: Places(places, paths, bits, percent).first(r))
    tops = over_blocks(hot_blocks(spark, bits, hot, False), lambda key, n, _: Places(places, paths, bits, percent).heads(key, n))
    links = verified(docs, written(pairs.union(tops).distinct(), "pairs"), k, percent, bits)
    named = usable.join(reps.select("s1", "s2", "n", "rep"), ["s1", "s2", "n"]).groupBy("doc_id").agg(F.min("rep").alias("low"), F.collect_set("rep").alias("reps"))
    several = named.where(F.size("reps") > 1).select(F.col("doc_id").alias("a"), F.explode("reps").alias("b"))  # documents of several sets
    links = written(links.union(several), "links")
    store.write_lookup(connected_components(links).select("node", "component"), bits, labels, "label")

    rest = all_ranges(spark, bits, lambda r: Places(places, paths, bits, percent, labels).later(r))
    more = over_blocks(hot_blocks(spark, bits, hot, True), lambda key, i, j: Places(places, paths, bits, percent, labels).across(key, i, j))
    rest = written(rest.union(more).distinct(), "pairs")
    if not rest.isEmpty():
        links = links.union(verified(docs, rest, k, percent, bits))
    known = sets.drop("prefix", "row").join(reps.drop("row"), ["s1", "s2", "n"], "left")
    return known.select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.col("rep")).alias("rep")), links


def jaccard_components(docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (the smallest doc_id that links reach)."""
    sets, links = jaccard_links(docs, k, percent)
    labels = connected_components(links)
    known = sets.join(labels, sets["rep"] == labels["node"], "left")
    return known.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep", F.col("doc_id").cast("long")).alias("component_id"))
