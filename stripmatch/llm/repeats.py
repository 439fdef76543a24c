"""Substring dedup by recompression.

Every document is parsed in rounds: a run of one symbol gets one name, then each symbol of the left class is joined
with a following symbol of the right class. A name is a hash of what it stands for, so all documents share names
without any exchange, and equal passages get equal names except near their ends, where the context decides. After
`rounds` rounds, neighbouring names form keys; Spark finds the keys that two documents share. A window of `width`
words can repeat elsewhere only if every key that its own words determine is shared; only such windows are compared,
by their hash over the real words, and each gets the smallest document that has it.

A key is determined by a window if the window holds its words, the next name of the last round but one on each side,
and a word more: sides and runs depend on no more. (A run takes the class of its symbol, and its name does not tell
its length, so a run cut by the window's end changes nothing further in.) Windows without such a key are always
compared, so no repeat is lost.

Defined cases: null or empty text has no words; a text shorter than a window keeps all; a null doc_id counts as
larger than any; rows of one doc_id don't remove each other's words; repeats within one document stay; extra columns
are dropped; an empty table gives no rows. Windows are equal if two hashes of them, of 64 and 32 bits, are: among
10^13 windows a false repeat is then expected in fewer than one corpus of a thousand.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship
from stripmatch.llm import store
from stripmatch.llm.textnp import _MULT, U, Chunk, chunks, mix

KEY_BYTES = 5
LAST = np.iinfo(np.int64).max


def _side(symbols: np.ndarray, level: int) -> np.ndarray:
    return (mix(symbols + _MULT[40 + level]) >> U(63)).astype(bool)


def parse(c: Chunk, h: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Keys of neighbouring names of the last round: (text, key, first and one past the last word that determine it)."""
    name, base, doc = h, h, c.wd  # base: the symbol whose class counts
    start = np.arange(len(h))
    end = start + 1
    lo, hi = start - 1, end + 1  # what determines a symbol: for a word, its neighbours decide how it is joined
    first_word, past_word = c.wo[:-1], c.wo[1:]
    for level in range(rounds):
        if not len(name):
            break
        # runs
        new = np.ones(len(name), bool)
        new[1:] = (name[1:] != name[:-1]) | (doc[1:] != doc[:-1])
        at = np.flatnonzero(new)
        size = np.diff(np.append(at, len(name)))
        last = at + size - 1
        side = _side(name[at], level)
        run_name = np.where(size > 1, mix(name[at] * _MULT[50] + U(level + 1)), name[at])
        start_r, end_r, doc_r = start[at], end[last], doc[at]
        # pairs
        n = len(at)
        joins = np.zeros(n, bool)
        joins[:-1] = ~side[:-1] & side[1:] & (doc_r[:-1] == doc_r[1:])
        head = np.ones(n, bool)
        head[1:] = ~joins[:-1]
        i = np.flatnonzero(head)
        two = joins[i]
        j = i + two
        # a name of this round is determined by its parts and by the parts on either side
        left, right = np.maximum(i - 1, 0), np.minimum(j + 1, n - 1)
        lo_r, hi_r = lo[at], hi[last]
        new_lo = np.where((i > 0) & (doc_r[left] == doc_r[i]), lo_r[left] if level else start_r[left], -1)
        new_hi = np.where((j < n - 1) & (doc_r[right] == doc_r[j]), hi_r[right] if level else end_r[right], 1 << 60)
        name = np.where(two, mix(run_name[i] * _MULT[51] + run_name[j] * _MULT[52] + U(level + 1)), run_name[i])
        start, end, doc, lo, hi = start_r[i], end_r[j], doc_r[i], new_lo, new_hi
    if len(name) < 2:
        none = np.zeros(0, np.int64)
        return none, np.zeros(0, U), none, none
    ok = doc[1:] == doc[:-1]
    key = mix(name[:-1] * _MULT[53] + name[1:] * _MULT[54])
    return doc[:-1][ok], key[ok], lo[:-1][ok], hi[1:][ok]


def _distinct(doc: np.ndarray, key: np.ndarray, n: int) -> np.ndarray:
    """The keys of each text once (54 bits tell keys of one text apart)."""
    if n > 1000:
        raise ValueError("too many texts")
    return np.unique((doc.astype(U) << U(54)) | (key >> U(10))) << U(10)


def shared_keys(docs: DataFrame, rounds: int, bits: int, folder: str) -> None:
    """Write the sorted keys that two documents or more hold."""

    def pack(cols):
        k, n = np.unique(cols["key"], return_counts=True)
        return [(r, s.stop - s.start, [store.short(k[s], bits, KEY_BYTES), np.packbits(n[s] > 1).tobytes()]) for r, s in store.by_range(k, bits)]

    def run(batches):
        held = store.Held(pack, ["key"])
        for batch in batches:
            for c in chunks(batch.column(0)):
                doc, key, _, _ = parse(c, c.hashes(), rounds)
                yield from held.add(key=store.trimmed(_distinct(doc, key, c.n), bits, KEY_BYTES))
        yield from held.flush()

    def each(r, parts):
        k = np.concatenate([store.long(d[0], r, bits, KEY_BYTES) for _, d in parts])
        twice = np.concatenate([np.unpackbits(np.frombuffer(d[1], np.uint8), count=n).astype(bool) for n, d in parts])
        u, back, n = np.unique(k, return_inverse=True, return_counts=True)
        shared = (n > 1) | (np.bincount(back, weights=twice) > 0)
        store.write_range(folder, r, u[shared])
        return {"keys": shared.sum()}

    store.run_ranges(docs.select("text").mapInArrow(run, store.PACKED_DDL), bits, each, ["keys"], [folder])


def checks(c: Chunk, h: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """Second hashes, of 32 bits, of the windows at words `at`, by other multipliers than the first."""
    total = np.zeros(len(at), U)
    for j in range(width):
        total += mix(h[at + j] + _MULT[60]) * _MULT[(j + 20) % 60]
    return (mix(total) >> U(32)).astype(np.uint32)


def first_holders(first: store.Store, w: np.ndarray, check: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which windows repeat, and the smallest document that has each."""
    hit, got = first.find(w)
    smallest = got["id"]
    for i in np.flatnonzero(hit & (got["c"] != check)).tolist():  # an unlike window of equal hash: it may stand behind
        r = int(w[i] >> U(64 - first.bits))
        keys, c, ids = first.array(r, "key", "u8"), first.array(r, "c", "u4"), first.array(r, "id", "i8")
        like = [x for x in range(np.searchsorted(keys, w[i], "left"), np.searchsorted(keys, w[i], "right")) if c[x] == check[i]]
        hit[i] = bool(like)
        smallest[i] = ids[like[0]] if like else 0
    return hit, smallest


def repeated_windows(docs: DataFrame, width: int, rounds: int, bits: int, keys: str, folder: str) -> None:
    """Write, for each window that two documents hold, its hash and the smallest doc_id. docs: id, text."""

    def smallest(h, c, low, high):
        """(hash, check) once each, with the smallest and largest id."""
        order = np.argsort(h)
        h, c, low, high = h[order], c[order], low[order], high[order]
        again = np.flatnonzero((h[1:] == h[:-1]) & (c[1:] < c[:-1]))  # equal hashes of unlike windows, out of order
        if len(again):
            order = np.lexsort((c, h))
            h, c, low, high = h[order], c[order], low[order], high[order]
        at = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (c[1:] != c[:-1]))) if len(h) else np.zeros(0, np.int64)
        return (h[at], c[at], np.minimum.reduceat(low, at), np.maximum.reduceat(high, at)) if len(at) else (h, c, low, high)

    def pack(cols):
        h, check, low, high = smallest(cols["h"], cols["c"], cols["id"], cols["id"])
        ids, code = np.unique(np.concatenate([low, high]), return_inverse=True)
        kind = np.uint16 if len(ids) < 65_536 else np.uint32
        code = code.astype(kind)
        out = []
        for r, s in store.by_range(h, bits):
            a, b = code[: len(h)][s], code[len(h) :][s]
            many = a != b
            used, back = np.unique(np.concatenate([a, b[many]]), return_inverse=True)
            small = np.uint16 if len(used) < 65_536 else np.uint32
            out.append((r, len(a), [h[s].tobytes(), check[s].tobytes(), ids[used].tobytes(), np.dtype(small).str.encode(), back[: len(a)].astype(small).tobytes(), np.packbits(many).tobytes(), back[len(a) :].astype(small).tobytes()]))
        return out

    def run(batches):
        shared = store.Store(keys, bits)
        held = store.Held(pack, ["h", "c", "id"])
        for batch in batches:
            ids = np.asarray(batch.column(0))
            for c in chunks(batch.column(1)):
                h = c.hashes()
                w, at = c.windows(h, width)
                if not len(w):
                    continue
                _, key, lo, hi = parse(c, h, rounds)
                inside = hi - lo <= width
                lo, hi = lo[inside], hi[inside]
                known, _ = shared.find(store.trimmed(key[inside] >> U(10) << U(10), bits, KEY_BYTES))
                alone = ~known & (lo >= 0)
                less = np.zeros(len(h) + 1, np.int32)
                np.add.at(less, np.maximum(hi[alone] - width, 0), 1)
                np.add.at(less, lo[alone] + 1, -1)
                go = np.cumsum(less[:-1])[at] == 0
                yield from held.add(h=w[go], c=checks(c, h, at[go], width), id=ids[c.lo + c.wd[at[go]]])
        yield from held.flush()

    def each(r, parts):
        hs, cs, lows, highs = [], [], [], []
        for n, (h, check, ids, kind, low, many, high) in parts:
            ids, low, kind = np.frombuffer(ids, np.int64), np.frombuffer(low, kind.decode()), kind.decode()
            top = low.copy()
            top[np.unpackbits(np.frombuffer(many, np.uint8), count=n).astype(bool)] = np.frombuffer(high, kind)
            hs.append(np.frombuffer(h, U)), cs.append(np.frombuffer(check, np.uint32)), lows.append(ids[low]), highs.append(ids[top])
        h, check, low, high = smallest(*map(np.concatenate, (hs, cs, lows, highs)))
        twice = low != high
        store.write_range(folder, r, h[twice], {"id": low[twice], "c": check[twice]})
        return {"windows": twice.sum()}

    store.run_ranges(docs.mapInArrow(run, store.PACKED_DDL), bits, each, ["windows"], [folder])


def remove_repeats(docs: DataFrame, width: int = 13, rounds: int = 2, with_text: bool = False) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_sha256, and the kept words if with_text."""
    spark = docs.sparkSession
    ship(spark)
    bits = store.range_bits(spark)
    keys, folder = store.new_folder(spark, "repeat-keys"), store.new_folder(spark, "repeat-windows")
    shared_keys(docs, rounds, bits, keys)
    narrow = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("id"), "text", "doc_id")
    repeated_windows(narrow.select("id", "text"), width, rounds, bits, keys, folder)

    def run(batches):
        first = store.Store(folder, bits, {"id": "i8", "c": "u4"})
        for batch in batches:
            ids = np.asarray(batch.column(0))
            for c in chunks(batch.column(1)):
                h = c.hashes()
                w, at = c.windows(h, width)
                hit, smallest = first_holders(first, w, checks(c, h, at, width))
                gone = at[hit & (smallest < ids[c.lo + c.wd[at]])] if len(w) else at
                cover = np.zeros(len(h) + 1, np.int32)
                np.add.at(cover, gone, 1)
                np.add.at(cover, np.minimum(gone + width, len(h)), -1)
                keep = np.cumsum(cover[:-1]) == 0
                raw = c.b.tobytes()
                texts = []
                for i in range(c.n):
                    words = raw[int(c.off[i]) : int(c.off[i + 1])].split()
                    k = keep[c.wo[i] : c.wo[i + 1]]
                    texts.append(b" ".join(words if k.all() else compress(words, k.tolist())))
                n = np.diff(c.wo)
                removed = n - np.bincount(c.wd[keep], minlength=c.n)
                cols = [batch.column(2).slice(c.lo, c.n), pa.array(n), pa.array(removed), pa.array([hashlib.sha256(t).hexdigest() for t in texts])]
                names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
                if with_text:
                    cols.append(pa.array([t.decode() for t in texts], pa.string()))
                    names.append("kept_text")
                yield pa.RecordBatch.from_arrays(cols, names)

    kind = dict(docs.dtypes)["doc_id"]
    return narrow.mapInArrow(run, f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * with_text)
