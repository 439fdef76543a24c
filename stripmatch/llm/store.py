"""Sorted hash arrays in the shared folder, memory-mapped by workers; and keys packed for few, large shuffle rows.

The space of 64-bit hashes is cut into 2^bits ranges. Map tasks sort and combine what they hold and send one packed
row per range (`Held`); the task of a range writes its sorted arrays as files (`put`), atomically and with the
same content on every attempt, so a lost executor costs only a repeat. When all ranges are written the driver writes
down which there are (`seal`): a reader that misses one of their files fails, it never takes them as empty. `Store`
maps the files and probes them range by range with sorted queries: memory holds no more than the pages in use.
"""

from __future__ import annotations

import mmap
import os
import uuid
from collections import OrderedDict
from collections.abc import Callable, Iterator
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import note, shared_dir, shuffle_parts
from stripmatch.llm.textnp import U, mix, release

HELD = 1_000_000


def range_bits(spark: SparkSession) -> int:
    """The ranges follow the shuffle partitions, which follow the input."""
    return max(2, (max(1, shuffle_parts(spark)) - 1).bit_length())


def new_folder(spark: SparkSession, what: str) -> str:
    return note(f"{shared_dir(spark)}/stripmatch/{what}-{uuid.uuid4().hex}")


def _local(uri: str) -> str | None:
    parsed = urlparse(uri)
    return parsed.path if parsed.scheme in ("", "file") else None


def put(folder: str, name: str, data: bytes) -> None:
    """Write a file under a name of its own, then rename it: readers see all of it or none."""
    path = _local(folder)
    temp = f".{name}-{uuid.uuid4().hex}"
    if path is not None:
        os.makedirs(path, exist_ok=True)
        with open(f"{path}/{temp}", "wb") as f:
            f.write(data)
        os.replace(f"{path}/{temp}", f"{path}/{name}")
        return
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(folder)
    system.create_dir(path, recursive=True)
    with system.open_output_stream(f"{path}/{temp}") as f:
        f.write(data)
    system.move(f"{path}/{temp}", f"{path}/{name}")


def mapped(folder: str, name: str) -> np.ndarray:
    """The bytes of a file of the shared folder: a read-only map, or a copy in memory where the store has no paths. An absent file is an error."""
    path = _local(folder)
    if path is None:
        from pyarrow import fs

        system, remote = fs.FileSystem.from_uri(folder)
        with system.open_input_stream(f"{remote}/{name}") as f:
            return np.frombuffer(f.read(), np.uint8)
    with open(f"{path}/{name}", "rb") as f:
        if not os.fstat(f.fileno()).st_size:
            return np.zeros(0, np.uint8)
        return np.frombuffer(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ), np.uint8)


def seal(folder: str, ranges: list[int]) -> None:
    """Say which ranges a folder holds: all others are empty."""
    put(folder, "ranges", np.array(sorted(ranges), "i8").tobytes())


class Files:
    """The arrays of a sealed folder, by range and column; the least recently used maps are closed."""

    MOST = 4096  # maps (a process may have some 65,000), and
    BYTES = 256 << 20  # bytes of what is no map

    def __init__(self, folder: str):
        self.folder, self.open, self.held = folder, OrderedDict(), 0
        self.ranges: set[int] | None = None

    def array(self, r: int, column: str, kind: str) -> np.ndarray:
        return self.named(f"{column}-{r}").view(kind) if r in self else np.zeros(0, kind)

    def __contains__(self, r: int) -> bool:
        if self.ranges is None:
            self.ranges = set(mapped(self.folder, "ranges").view("i8").tolist())
        return r in self.ranges

    def named(self, name: str) -> np.ndarray:
        if name in self.open:
            self.open.move_to_end(name)
            return self.open[name]
        found = self.open[name] = mapped(self.folder, name)
        self.held += len(found)
        while len(self.open) > 1 and (len(self.open) > self.MOST or (self.held > self.BYTES and _local(self.folder) is None)):
            self.held -= len(self.open.popitem(last=False)[1])
        return found


class Held:
    """Sorted key columns of a map task, packed by range whenever HELD entries have come together.

    pack(columns) turns what has come together (lists of arrays by name) into the rows to send.
    """

    def __init__(self, pack: Callable[[dict[str, np.ndarray]], list], names: list[str]):
        self.pack, self.names, self.n = pack, names, 0
        self.parts: dict[str, list] = {n: [] for n in names}

    def add(self, **columns: np.ndarray) -> Iterator[pa.RecordBatch]:
        for n in self.names:
            self.parts[n].append(columns[n])
        self.n += len(columns[self.names[0]])
        if self.n >= HELD:
            yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        if self.n:
            rows = self.pack({n: np.concatenate(v) for n, v in self.parts.items()})
            self.parts, self.n = {n: [] for n in self.names}, 0
            for i in range(0, len(rows), 64):
                yield packed_rows(rows[i : i + 64])
            del rows
            release()


class Store(Files):
    """Sorted 64-bit keys with fixed-width columns, one file per range and column."""

    def __init__(self, folder: str, bits: int, columns: dict[str, str] | None = None):
        super().__init__(folder)
        self.bits, self.columns = bits, columns or {}

    def find(self, probe: np.ndarray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
        """Which probes are keys, and their columns (0 where absent); `at`: the place within the range."""
        there = np.zeros(len(probe), bool)
        out = {c: np.zeros(len(probe), "i8" if k == SMALL else k) for c, k in self.columns.items()} | {"at": np.zeros(len(probe), np.int64)}
        if not len(probe):
            return there, out
        order = np.argsort(probe)
        q = probe[order]
        cut = np.searchsorted(q, np.arange(1 << self.bits, dtype=U) << U(64 - self.bits)) if self.bits else np.array([0])
        cut = np.append(cut, len(q))
        for r in np.flatnonzero(np.diff(cut)).tolist():
            keys = self.array(r, "key", "u8")
            if not len(keys):
                continue
            part, whom = q[cut[r] : cut[r + 1]], order[cut[r] : cut[r + 1]]
            at = np.minimum(np.searchsorted(keys, part), len(keys) - 1)
            ok = keys[at] == part
            whom, at = whom[ok], at[ok]
            there[whom] = True
            out["at"][whom] = at
            for c, k in self.columns.items():
                out[c][whom] = Small(self.array(r, c, "u1"))[at] if k == SMALL else self.array(r, c, k)[at]
        return there, out


SMALL = "small"


class Small:
    """Counts of which most are below 255: a byte each, with the others apart."""

    def __init__(self, raw: np.ndarray):
        n, k = raw[:16].view("i8").tolist() if len(raw) else (0, 0)
        end = 16 + n
        aside = end + -end % 8
        self.low, self.at, self.big = raw[16:end], raw[aside : aside + 8 * k].view("i8"), raw[aside + 8 * k :].view("i8")

    def __len__(self) -> int:
        return len(self.low)

    def __getitem__(self, at: np.ndarray) -> np.ndarray:
        out = self.low[at].astype(np.int64)
        high = np.flatnonzero(out == 255)
        if len(high):
            out[high] = self.big[np.searchsorted(self.at, at[high])]
        return out

    def all(self) -> np.ndarray:
        out = self.low.astype(np.int64)
        out[self.at] = self.big
        return out

    @staticmethod
    def packed(x: np.ndarray) -> bytes:
        high = np.flatnonzero(x > 254)
        head = np.array([len(x), len(high)], "i8").tobytes() + np.minimum(x, 255).astype("u1").tobytes()
        return head + b"\0" * (-len(head) % 8) + high.astype("i8").tobytes() + x[high].astype("i8").tobytes()


def write_range(folder: str, r: int, keys: np.ndarray, columns: dict[str, np.ndarray] | None = None) -> None:
    put(folder, f"key-{r}", keys.astype("u8").tobytes())
    for c, v in (columns or {}).items():
        put(folder, f"{c}-{r}", v if isinstance(v, bytes) else v.tobytes())


def short(keys: np.ndarray, bits: int, width: int) -> bytes:
    """The width bytes of each key after its range's bits."""
    return (keys << U(bits) >> U(64 - 8 * width)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def long(data: bytes, r: int, bits: int, width: int) -> np.ndarray:
    """Keys of a range from `short`; what was cut off is 0."""
    raw = np.zeros((len(data) // width, 8), np.uint8)
    raw[:, :width] = np.frombuffer(data, np.uint8).reshape(-1, width)
    tail = raw.view("<u8").ravel().astype(U)
    return (tail << U(64 - 8 * width) >> U(bits)) | (U(r) << U(64 - bits))


def trimmed(keys: np.ndarray, bits: int, width: int) -> np.ndarray:
    """Keys as `long` gives them back."""
    keep = min(64, bits + 8 * width)
    return keys >> U(64 - keep) << U(64 - keep)


def by_range(keys: np.ndarray, bits: int) -> Iterator[tuple[int, slice]]:
    """The slices of sorted keys in each range."""
    cut = np.append(np.searchsorted(keys, np.arange(1 << bits, dtype=U) << U(64 - bits)), len(keys))
    for r in np.flatnonzero(np.diff(cut)).tolist():
        yield r, slice(int(cut[r]), int(cut[r + 1]))


PACKED = pa.schema([("r", pa.int32()), ("n", pa.int64()), ("data", pa.list_(pa.binary()))])
PACKED_DDL = "r int, n long, data array<binary>"


def packed_rows(rows: list[tuple[int, int, list[bytes]]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([x[0] for x in rows], pa.int32()), pa.array([x[1] for x in rows], pa.int64()), pa.array([x[2] for x in rows], pa.list_(pa.binary()))], schema=PACKED)


def dealt(packed: DataFrame, bits: int, every: bool = False) -> DataFrame:
    """The rows by range; every: ranges without rows come too, as one without data."""
    if every:
        packed = packed.union(packed.sparkSession.range(1 << bits).select(F.col("id").cast("int"), F.lit(0).cast("long"), F.array().cast("array<binary>")))
    return packed.repartitionById(1 << bits, "r")  # a range a task: hashed numbers would put several into one


def ranges_of(batches: Iterator[pa.RecordBatch]) -> dict[int, list[tuple[int, list[bytes]]]]:
    """Everything that reached a task, by range. A task holds about one range of all, which follows the partitions."""
    out: dict[int, list] = {}
    for b in batches:
        for r, n, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
            parts = out.setdefault(r, [])
            if n:
                parts.append((n, data))
    return out


def run_ranges(packed: DataFrame, bits: int, each: Callable[[int, list], dict[str, float]], sums: list[str], folders: list[str]) -> list[dict[str, int]]:
    """Run each(r, parts) on every range in a task (it writes files to folders, which are then sealed).

    Back comes a row per range with what it returns: at most 2^bits rows.
    """
    def run(batches):
        for r, parts in sorted(ranges_of(batches).items()):
            got = each(r, parts)
            yield pa.RecordBatch.from_arrays([pa.array([int(x)], pa.int64()) for x in (r, *(got.get(s, 0) for s in sums))], ["r", *sums])
        release()

    rows = dealt(packed, bits).mapInArrow(run, ", ".join(f"{s} long" for s in ["r", *sums])).collect()
    for folder in folders:
        seal(folder, [row["r"] for row in rows])
    return [row.asDict() for row in rows]


def total(rows: list[dict[str, int]], name: str) -> int:
    return sum(row[name] for row in rows)


def write_lookup(rows: DataFrame, bits: int, folder: str, column: str | None = None) -> None:
    """A store of mixed ids (first column), with the second column's values if named."""

    def pack(cols):
        order = np.argsort(cols["key"], kind="stable")
        key, value = cols["key"][order], cols["value"][order]
        return [(r, s.stop - s.start, [key[s].tobytes(), value[s].tobytes()]) for r, s in by_range(key, bits)]

    def run(batches):
        held = Held(pack, ["key", "value"])
        for batch in batches:
            yield from held.add(key=mix(np.array(batch.column(0)).view(U)), value=np.array(batch.column(batch.num_columns - 1)))
        yield from held.flush()

    def each(r, parts):
        key, at = np.unique(np.concatenate([np.frombuffer(d[0], U) for _, d in parts]), return_index=True)
        value = np.concatenate([np.frombuffer(d[1], np.int64) for _, d in parts])[at]
        write_range(folder, r, key, {column: value} if column else None)
        return {"n": len(key)}

    run_ranges(rows.mapInArrow(run, PACKED_DDL), bits, each, ["n"], [folder])


def among(batches: Iterator[pa.RecordBatch], folder: str, bits: int) -> Iterator[pa.RecordBatch]:
    """The rows whose first column, a long, is in a store that write_lookup wrote: a semi-join without a shuffle.

    For use within a map of batches: a map of its own before another would give every core two Python workers.
    """
    asked = Store(folder, bits)
    for batch in batches:
        yield batch.filter(pa.array(_known(asked, batch.column(0))))


def without(rows: DataFrame, column: str, folder: str, bits: int) -> DataFrame:
    """The rows whose `column` is not in such a store (a null never is): an anti-join without a shuffle; all columns are kept."""
    at = rows.columns.index(column)

    def run(batches):
        asked = Store(folder, bits)
        for batch in batches:
            yield batch.filter(pa.array(~_known(asked, batch.column(at).cast(pa.int64()))))

    return rows.mapInArrow(run, rows.schema)


def _known(asked: Store, ids: pa.Array) -> np.ndarray:
    return asked.find(mix(np.array(ids.fill_null(0)).view(U)))[0] & ~np.asarray(ids.is_null())
