"""SentencePiece encoding and decoding in numpy batches.

Texts are cut into units that no piece spans (a run of spaces with the word after it; a line feed, where the
vocabulary proves that none contains it). Distinct units of equal length advance together: a table of all their
substrings of up to the longest piece is probed by hash against the sorted piece keys, then

* unigram models: Viterbi over the scores, vectorised maxima storing backpointers;
* BPE models: rounds that join, in every unit at once, the adjacent pair with the highest score, leftmost on ties.
  (The score sum's optimum is not what this library gives for such models, so Viterbi can't give their ids.)

Both give the library's ids. Characters without a piece become byte pieces, or the unknown piece.

A unit over LONG characters would take that many rounds over all of it; its pairs stand in a heap instead, so that each
join costs a logarithm.

Defined cases: an empty table gives no rows; null or empty text gives no ids and decodes to the empty text; the escape character U+2581 in a text
encodes as a space, as in the library, and so such a text does not round-trip; repeated rows are encoded each; extra
columns are dropped.
"""

from __future__ import annotations

import heapq
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from stripmatch.cluster import ship
from stripmatch.llm.textnp import U, Chunk, chunks, in_sorted, kept

MARK = "▁"
KEPT = 300_000
LONG = 256  # bytes; longer units are not kept, so the table's memory is bounded
LONG = 256  # characters


class Codec:
    def __init__(self, path: str | None = None, proto: bytes | None = None):
        from sentencepiece import sentencepiece_model_pb2 as pb

        m = pb.ModelProto()
        if proto is None:
            with open(path, "rb") as f:
                proto = f.read()
        m.ParseFromString(proto)
        if m.normalizer_spec.precompiled_charsmap or m.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only models with the identity normalizer are supported")
        self.dummy = m.normalizer_spec.add_dummy_prefix
        self.unigram = m.trainer_spec.model_type == 1
        kinds = [p.type for p in m.pieces]
        self.unk = kinds.index(2)
        normal = [i for i, k in enumerate(kinds) if k in (1, 4, 5)]
        strings = [m.pieces[i].piece for i in normal]
        if any(MARK in s.lstrip(MARK) for s in strings):
            raise ValueError("a piece spans a word start")
        self.longest = max(map(len, strings))
        self.cut = b"\n" if all("\n" not in s or s == "\n" for s in strings) else b""
        raw = [s.replace(MARK, " ").encode() for s in strings]
        keys = self._hash(raw)
        order = np.argsort(keys)
        self.keys, self.ids = keys[order], np.array(normal, np.int32)[order]
        self.scores = np.array([m.pieces[i].score for i in normal])[order]
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[self.keys >> U(44)] = True
        self.lowest = float(self.scores.min()) - 10.0
        self.byte = np.full(256, self.unk, np.int32)
        shown = [b""] * len(kinds)
        for i, p in enumerate(m.pieces):
            if p.type == 6:
                self.byte[int(p.piece[3:5], 16)] = i
                shown[i] = bytes([int(p.piece[3:5], 16)])
            elif p.type in (1, 4, 5):
                shown[i] = p.piece.replace(MARK, " ").encode()
            elif p.type == 2:
                shown[i] = m.trainer_spec.unk_surface.encode()
        self.fallback = bool((self.byte != self.unk).any())
        self.shown = np.frombuffer(b"".join(shown), np.uint8)
        self.shown_len = np.array([len(s) for s in shown], np.int64)
        self.shown_at = np.concatenate([[0], np.cumsum(self.shown_len)[:-1]])
        self.units = re.compile(rb"\n| *[^ \n]+| +" if self.cut else rb" *[^ ]+| +")
        self.known: dict[bytes, bytes] = {}
        self.before: dict[bytes, bytes] = {}

    @staticmethod
    def _hash(strings: list[bytes]) -> np.ndarray:
        off = np.concatenate([[0], np.cumsum([len(s) for s in strings])]).astype(np.int64)
        c = Chunk(np.frombuffer(b"".join(strings), np.uint8), off, 0)
        return c.spans_hash(off[:-1], off[1:])

    def _equal(self, units: list[bytes], length: int) -> list[bytes]:
        """The ids of units of length characters each, as packed int32."""
        n = len(units)
        b = np.frombuffer(b"".join(units), np.uint8)
        c = Chunk(b, np.array([0, len(b)]), 0)
        head = np.append(np.flatnonzero((b & 0xC0) != 0x80), len(b))
        at = np.minimum(np.arange(n)[:, None] * length + np.arange(length + 1), len(head) - 1)
        at = head[at]  # byte places of each unit's character bounds
        wide = min(self.longest, length)
        piece = np.full((n, length, wide + 1), -1, np.int32)
        for k in range(1, wide + 1):
            h = c.spans_hash(at[:, : length - k + 1].ravel(), at[:, k:].ravel())
            hit = np.flatnonzero(self.maybe[h >> U(44)])
            place, there = in_sorted(self.keys, h[hit])
            rows, cols = np.divmod(hit[there], length - k + 1)
            piece[rows, cols, k] = place[there]
        way = self._viterbi if self.unigram else self._joined if length <= LONG else self._joined_long
        bounds, done = way(piece, n, length, wide)
        out: list[bytes] = [b""] * n
        for rows, ends in zip(done, bounds):  # rows with equally many symbols
            width = ends[:, 1:] - ends[:, :-1]
            place = piece[rows[:, None], ends[:, :-1], np.minimum(width, wide)]
            place = np.where(width <= wide, place, -1)
            ids = np.where(place >= 0, self.ids[place], -1).astype(np.int32)
            plain = (ids >= 0).all(axis=1)
            for r, row, ok in zip(rows.tolist(), ids, plain.tolist()):
                if ok:
                    out[r] = row.tobytes()
                else:
                    got: list[int] = []
                    i = int(np.flatnonzero(rows == r)[0])
                    for j, v in enumerate(row.tolist()):
                        if v >= 0:
                            got.append(v)
                        elif self.fallback:
                            got += self.byte[b[at[r, ends[i, j]] : at[r, ends[i, j + 1]]]].tolist()
                        elif not got or got[-1] != self.unk or not self.unigram:
                            got.append(self.unk)
                    out[r] = np.array(got, np.int32).tobytes()
        return out

    def _joined(self, piece, n, length, wide):
        rows, ends = np.arange(n), np.tile(np.arange(length + 1), (n, 1))
        score = np.append(self.scores, -np.inf)
        bounds, done = [], []
        while len(rows):
            if ends.shape[1] < 3:
                bounds.append(ends), done.append(rows)
                break
            start, width = ends[:, :-2], ends[:, 2:] - ends[:, :-2]
            s = np.where(width <= wide, score[piece[rows[:, None], start, np.minimum(width, wide)]], -np.inf)
            best = s.argmax(axis=1)
            go = s[np.arange(len(rows)), best] > -np.inf
            bounds.append(ends[~go]), done.append(rows[~go])
            rows, ends, best = rows[go], ends[go], best[go]
            keep = np.ones(ends.shape, bool)
            keep[np.arange(len(rows)), best + 1] = False
            ends = ends[keep].reshape(len(rows), ends.shape[1] - 1)
        return bounds, done

    def _joined_long(self, piece, n, length, wide):
        score = np.append(self.scores, -np.inf)
        bounds = []
        for row in range(n):
            s = score[piece[row]]  # by start and width
            after, before = list(range(1, length + 1)), list(range(-1, length - 1))
            two = s[: length - 1, min(2, wide)] if wide > 1 else np.full(length - 1, -np.inf)
            heap = [(-two[i], i, i + 2) for i in np.flatnonzero(two > -np.inf).tolist()]
            heapq.heapify(heap)
            alive = bytearray(b"\1" * length)
            while heap:  # the best pair, leftmost on ties; those whose sides have changed are stale
                _, i, end = heapq.heappop(heap)
                j = after[i]
                if not alive[i] or j >= length or after[j] != end:
                    continue
                alive[j] = 0
                after[i] = end
                if end < length:
                    before[end] = i
                for start in (before[i], i):
                    if start >= 0 and after[start] < length:
                        stop = after[after[start]]
                        if stop - start <= wide and s[start, stop - start] > -np.inf:
                            heapq.heappush(heap, (-s[start, stop - start], start, stop))
            bounds.append(np.append(np.flatnonzero(np.frombuffer(alive, np.uint8)), length)[None, :])
        return bounds, [np.array([row]) for row in range(n)]

    def _viterbi(self, piece, n, length, wide):
        score = np.append(self.scores, -np.inf)
        best = np.full((n, length + 1), -np.inf)
        best[:, 0] = 0
        back = np.zeros((n, length + 1), np.int64)
        for e in range(1, length + 1):
            k = np.arange(1, min(wide, e) + 1)
            s = score[piece[:, e - k, k]]
            s[:, 0] = np.where(piece[:, e - 1, 1] < 0, self.lowest, s[:, 0])  # a character without a piece
            total = best[:, e - k] + s
            j = total[:, ::-1].argmax(axis=1)  # ties: the longer last piece
            j = len(k) - 1 - j
            best[:, e], back[:, e] = total[np.arange(n), j], k[j]
        steps = np.zeros((n, length + 1), bool)
        here = np.full(n, length)
        steps[:, length] = True
        while (here > 0).any():
            here = np.maximum(here - np.maximum(back[np.arange(n), here], here == 0), 0)
            steps[np.arange(n), here] = True
        many = steps.sum(axis=1)
        bounds, done = [], []
        for m in np.unique(many):
            rows = np.flatnonzero(many == m)
            bounds.append(np.nonzero(steps[rows])[1].reshape(len(rows), m)), done.append(rows)
        return bounds, done

    def learn(self, units: set[bytes]) -> None:
        if len(self.known) > KEPT:  # two generations: frequent units stay
            self.before, self.known = self.known, {}
        missing = units - self.known.keys()
        again = missing & self.before.keys()
        self.known.update((u, self.before[u]) for u in again)
        fresh = missing - again
        by: dict[int, list[bytes]] = {}
        for u in fresh:
            by.setdefault(len(u) if u.isascii() else len(u.decode()), []).append(u)
        for length, group in by.items():
            step = max(1, 400_000 // (length * min(length, self.longest) + 1))
            for i in range(0, len(group), step):
                part = group[i : i + step]
                self.known.update(zip(part, self._equal(part, length)))

    def encode_many(self, texts: list[bytes]) -> list[np.ndarray]:
        cut = []
        for t in texts:
            if not t:
                cut.append([])
                continue
            t = t.replace(MARK.encode(), b" ")
            cut.append(self.units.findall(b" " + t if self.dummy else t))
        wanted: set[bytes] = set()
        for u in cut:
            wanted.update(u)
        self.learn(wanted)
        get = self.known.__getitem__
        out = [np.frombuffer(b"".join(map(get, u)), np.int32) for u in cut]
        for u in wanted:
            if len(u) > LONG:
                del self.known[u]
        return out

    def decode(self, ids: np.ndarray) -> bytes:
        """The text of ids; a leading dummy space goes."""
        if not len(ids):
            return b""
        size = self.shown_len[ids]
        start = np.cumsum(size) - size
        raw = self.shown[np.repeat(self.shown_at[ids] - start, size) + np.arange(int(size.sum()))].tobytes()
        return raw[1:] if self.dummy and raw[:1] == b" " else raw


def codec(path: str) -> Codec:
    return kept(path, lambda: Codec(path))


def encode(docs: DataFrame, model_path: str) -> DataFrame:
    """One row per document: doc_id, ids array<int>, n_tokens long, round_trip boolean (the ids decode to the text)."""
    ship(docs.sparkSession)
    narrow = docs.select("doc_id", "text")

    def run(batches):
        of = codec(model_path)
        for batch in batches:
            for c in chunks(batch.column(1), 4 << 20):
                raw = c.b.tobytes()
                texts = [raw[s:e] for s, e in zip(c.off[:-1].tolist(), c.off[1:].tolist())]
                ids = of.encode_many(texts)
                same = [of.decode(i) == t for i, t in zip(ids, texts)]
                off = np.concatenate([[0], np.cumsum([len(i) for i in ids])])
                values = np.concatenate(ids) if ids else np.zeros(0, np.int32)
                col = pa.ListArray.from_arrays(pa.array(off, pa.int32()), pa.array(values, pa.int32()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c.lo, c.n), col, pa.array(np.diff(off)), pa.array(same)], ["doc_id", "ids", "n_tokens", "round_trip"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, ids array<int>, n_tokens long, round_trip boolean")


def decode(encoded: DataFrame, model_path: str) -> DataFrame:
    """doc_id and the text of its ids (null ids: the empty text)."""
    ship(encoded.sparkSession)
    narrow = encoded.select("doc_id", "ids")

    def run(batches):
        of = codec(model_path)
        for batch in batches:
            texts = [of.decode(np.array(i or [], np.int32)).decode("utf-8", "replace") for i in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, text string")
