"""Words, hashes and windows of many texts at once, as numpy operations on Arrow buffers.

A word is a maximal run of bytes other than space and 0x09-0x0D, which on UTF-8 is the pattern
``[^\\x20\\x09-\\x0D]+``. Every text is used whole; null counts as empty. A text of L bytes needs about 50 L
bytes of memory while it is worked on; texts are taken together only up to CHUNK bytes.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext

CHUNK = 1 << 20
U = np.uint64
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
_P = U(0x9E3779B97F4A7C15)
_PINV = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


_BYTE = mix(np.arange(1, 257, dtype=U) * _P) | U(1)
_FOLDED = _BYTE.copy()
_FOLDED[65:91] = _BYTE[97:123]
_MULT = mix(np.arange(1001, 1065, dtype=U) * _P) | U(1)
_tables: dict[str, np.ndarray] = {"pow": np.ones(1, U), "inv": np.ones(1, U)}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_tables["pow"]) < n:
        for name, base in (("pow", _P), ("inv", _PINV)):
            t = np.full(n, base, U)
            t[0] = 1
            _tables[name] = np.cumprod(t, dtype=U)
    return _tables["pow"], _tables["inv"]


class Chunk:
    """Some texts, one after the other: bytes b, text bounds off; words from ws to we, of text wd; wo: each text's first word."""

    def __init__(self, b: np.ndarray, off: np.ndarray, lo: int):
        self.b, self.off, self.lo, self.n = b, off.astype(np.int64), lo, len(off) - 1
        size = len(b)
        if size == 0:
            self.ws = self.we = self.wd = np.zeros(0, np.int64)
            self.wo = np.zeros(self.n + 1, np.int64)
            return
        word = ~SPACE[b]
        first, last = word.copy(), word.copy()
        edge = np.zeros(size + 1, bool)
        edge[self.off] = True
        first[1:] &= ~word[:-1] | edge[1:-1]
        last[:-1] &= ~word[1:] | edge[1:-1]
        self.ws, self.we = np.flatnonzero(first), np.flatnonzero(last) + 1
        self.wo = np.searchsorted(self.ws, self.off)
        self.wd = np.repeat(np.arange(self.n), np.diff(self.wo))

    def spans_hash(self, start: np.ndarray, end: np.ndarray, fold: bool = False) -> np.ndarray:
        """64-bit hashes of byte spans; fold takes A-Z as a-z."""
        if not len(start):
            return np.zeros(0, U)
        power, inverse = _powers(len(self.b) + 1)
        key = "_sums_f" if fold else "_sums"
        sums = getattr(self, key, None)
        if sums is None:
            sums = np.zeros(len(self.b) + 1, U)
            np.cumsum((_FOLDED if fold else _BYTE)[self.b] * power[: len(self.b)], out=sums[1:])
            setattr(self, key, sums)
        return mix((sums[end] - sums[start]) * inverse[start] + (end - start).astype(U) * _MULT[63])

    def hashes(self, fold: bool = False) -> np.ndarray:
        return self.spans_hash(self.ws, self.we, fold)

    def windows(self, h: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all k consecutive words within a text, and the index of each one's first word."""
        n = len(h) - k + 1
        if n <= 0:
            return np.zeros(0, U), np.zeros(0, np.int64)
        at = np.flatnonzero(self.wd[:n] == self.wd[k - 1 :])
        total = np.zeros(n, U)
        for j in range(k):
            total += h[j : j + n] * _MULT[j]
        return mix(total[at]), at

    def per_text(self, mask: np.ndarray) -> np.ndarray:
        """How many bytes of each text are set in mask."""
        total = np.zeros(len(self.b) + 1, np.int64)
        np.cumsum(mask, out=total[1:])
        return np.diff(total[self.off])


def chunks(texts: pa.Array, size: int = CHUNK, most: int = 1000) -> Iterator[Chunk]:
    """Consecutive texts of about size bytes, most texts at once; a longer text comes alone."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = pc.fill_null(texts, "")
    if not len(texts):
        return
    wide = pa.types.is_large_string(texts.type) or pa.types.is_large_binary(texts.type)
    off = np.frombuffer(texts.buffers()[1], np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    data = np.frombuffer(texts.buffers()[2], np.uint8) if texts.buffers()[2] is not None else np.zeros(0, np.uint8)
    lo = 0
    while lo < len(texts):
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + size, "right")) - 1)
        hi = min(hi, len(texts), lo + most)
        yield Chunk(data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], lo)
        lo = hi
    release()


_kept: dict[str, tuple[int, Any]] = {}


def _stage() -> int:
    task = TaskContext.get()
    return -1 if task is None else task.stageId()


def kept(name: str, make: Callable[[], Any]) -> Any:
    """What tasks of one stage share in a worker: made by the first of them, gone once a task of another stage calls release."""
    if name not in _kept or _kept[name][0] != _stage():
        _kept[name] = _stage(), make()
    return _kept[name][1]


def release() -> None:
    """Give freed memory back to the system: an executor's idle workers count towards its limit."""
    for name in [n for n, (stage, _) in _kept.items() if stage != _stage()]:
        del _kept[name]
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:  # another C library
        pass


def doc_mix(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Hashes that also tell the texts of a chunk apart."""
    return mix(h + doc.astype(U) * _MULT[62])


def in_sorted(keys: np.ndarray, probe: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each probe its place in sorted keys, and whether it is there."""
    if not len(keys):
        return np.zeros(len(probe), np.int64), np.zeros(len(probe), bool)
    at = np.minimum(np.searchsorted(keys, probe), len(keys) - 1)
    return at, keys[at] == probe


def join_hash(parts: list[np.ndarray], seed: int = 0) -> np.ndarray:
    """A hash of a sequence of equally long hash columns."""
    total = np.full(len(parts[0]), U(seed), U)
    for j, p in enumerate(parts):
        total = total + p * _MULT[j]
    return mix(total)


def unmix(x: np.ndarray) -> np.ndarray:
    """The inverse of mix."""
    x = x ^ (x >> U(31)) ^ (x >> U(62))
    x = x * U(pow(0x94D049BB133111EB, -1, 1 << 64))
    x = x ^ (x >> U(27)) ^ (x >> U(54))
    x = x * U(pow(0xBF58476D1CE4E5B9, -1, 1 << 64))
    return x ^ (x >> U(30)) ^ (x >> U(60))
