"""Binary tables of FITS files as a Spark data source: names and types come from the file's header.

One partition per extension and block of rows; only the asked columns' bytes become arrays. The format is big-endian,
in records of 2880 bytes, with 80-character header cards. Variable-length and bit columns are skipped.
"""

from __future__ import annotations

import glob
import os

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import BooleanType, DoubleType, FloatType, IntegerType, LongType, ShortType, StringType, StructField, StructType

RECORD, ROWS = 2880, 200_000
#: Type codes of binary-table columns.
CODES = {"L": ("S1", BooleanType()), "B": ("u1", ShortType()), "I": (">i2", ShortType()), "J": (">i4", IntegerType()), "K": (">i8", LongType()), "E": (">f4", FloatType()), "D": (">f8", DoubleType()), "A": ("S", StringType())}


def header(f) -> dict[str, str]:
    """The cards of the header unit at the file's place; the place moves to the data."""
    cards: dict[str, str] = {}
    while True:
        block = f.read(RECORD)
        if len(block) < RECORD:
            return cards
        for i in range(0, RECORD, 80):
            card = block[i : i + 80].decode("ascii", "replace")
            key = card[:8].strip()
            if key == "END":
                return cards
            if card[8:10] == "= ":
                value = card[10:].strip()
                cards[key] = value[1:].split("'")[0].rstrip() if value.startswith("'") else value.split("/")[0].strip()


def tables(path: str) -> list[dict]:
    """Each binary-table extension: its number, place, row size, rows and columns."""
    out, n = [], 0
    with open(path, "rb") as f:
        size = os.fstat(f.fileno()).st_size
        while f.tell() < size:
            h = header(f)
            if not h:
                break
            axes = [int(h[f"NAXIS{i + 1}"]) for i in range(int(h.get("NAXIS", "0")))]
            length = abs(int(h.get("BITPIX", "8"))) // 8 * int(np.prod(axes)) if axes else 0
            length = length + int(h.get("PCOUNT", "0"))
            if h.get("XTENSION") == "BINTABLE":
                columns, at = [], 0
                for i in range(1, int(h["TFIELDS"]) + 1):
                    form = h[f"TFORM{i}"].strip()
                    digits = "".join(c for c in form if c.isdigit())
                    code = form[len(digits)] if len(form) > len(digits) else ""
                    many = int(digits or 1)
                    width = {"L": 1, "B": 1, "A": 1, "I": 2, "J": 4, "K": 8, "E": 4, "D": 8, "P": 8, "Q": 16, "C": 8, "M": 16}.get(code, 0) * many if code != "X" else -(-many // 8)
                    columns.append({"name": h.get(f"TTYPE{i}", f"col{i}"), "code": code, "many": many, "at": at})
                    at += width
                out.append({"extension": n, "place": f.tell(), "row": axes[0], "rows": axes[1], "columns": columns})
            f.seek(-(-length // RECORD) * RECORD, 1)
            n += 1
    return out


class Block(InputPartition):
    def __init__(self, path: str, table: dict, first: int, rows: int):
        self.path, self.table, self.first, self.rows = path, table, first, rows


class FitsTableReader(DataSourceReader):
    def __init__(self, paths: list[str], schema: StructType, extensions: set[int]):
        self.paths, self.schema, self.extensions = paths, schema, extensions

    def partitions(self):
        return [Block(p, t, i, min(ROWS, t["rows"] - i)) for p in self.paths for t in tables(p) if not self.extensions or t["extension"] in self.extensions for i in range(0, t["rows"], ROWS)]

    def read(self, block: Block):
        t = block.table
        with open(block.path, "rb") as f:
            f.seek(t["place"] + block.first * t["row"])
            raw = f.read(block.rows * t["row"])
        by = {c["name"]: c for c in t["columns"]}
        cols = []
        for field in self.schema:
            if field.name == "extver":
                cols.append(pa.array(np.full(block.rows, t["extension"], np.int32)))
                continue
            c = by[field.name]
            kind = f"S{c['many']}" if c["code"] == "A" else CODES[c["code"]][0]
            v = np.ndarray((block.rows,), np.dtype(kind), raw, c["at"], (t["row"],))
            if c["code"] == "A":
                cols.append(pa.array([x.decode("ascii", "replace").rstrip("\0 ") for x in v.tolist()]))
            elif c["code"] == "L":
                cols.append(pa.array(v == b"T"))
            else:
                v = v.astype(v.dtype.newbyteorder("="))
                cols.append(pa.array(v.astype(np.int16) if c["code"] == "B" else v))
        yield pa.RecordBatch.from_arrays(cols, [f.name for f in self.schema])


class FitsTableSource(DataSource):
    """spark.read.format("fits_table").option("extensions", "1,2").load(path): local or shared paths, globs allowed."""

    @classmethod
    def name(cls) -> str:
        return "fits_table"

    def _paths(self) -> list[str]:
        return sorted(glob.glob(self.options["path"].removeprefix("file://")))

    def schema(self) -> StructType:
        for p in self._paths():
            for t in tables(p):
                return StructType([StructField(c["name"], CODES[c["code"]][1]) for c in t["columns"] if c["code"] in CODES and (c["many"] == 1 or c["code"] == "A")] + [StructField("extver", IntegerType())])
        raise ValueError("no binary table found")

    def reader(self, schema: StructType) -> DataSourceReader:
        chosen = {int(x) for x in self.options.get("extensions", "").split(",") if x.strip()}
        return FitsTableReader(self._paths(), schema, chosen)


def write_table(path: str, extensions: list[dict[str, np.ndarray]]) -> None:
    """Write tables of numbers and byte strings: for round trips."""

    def cards(pairs):
        text = "".join(f"{k:<8}= {v:>20}".ljust(80) if not isinstance(v, str) or not v.startswith("'") else f"{k:<8}= {v}".ljust(80) for k, v in pairs) + "END".ljust(80)
        return text.ljust(-(-len(text) // RECORD) * RECORD).encode()

    codes = {"i2": "I", "i4": "J", "i8": "K", "f4": "E", "f8": "D"}
    with open(path, "wb") as f:
        f.write(cards([("SIMPLE", "T"), ("BITPIX", 8), ("NAXIS", 0)]))
        for ext in extensions:
            forms = {k: f"{v.dtype.itemsize}A" if v.dtype.kind == "S" else codes[v.dtype.str[1:]] for k, v in ext.items()}
            kind = np.dtype([(k, v.dtype if v.dtype.kind == "S" else v.dtype.newbyteorder(">")) for k, v in ext.items()])
            rows = np.zeros(len(next(iter(ext.values()))), kind)
            for k, v in ext.items():
                rows[k] = v
            head = [("XTENSION", "'BINTABLE'"), ("BITPIX", 8), ("NAXIS", 2), ("NAXIS1", kind.itemsize), ("NAXIS2", len(rows)), ("PCOUNT", 0), ("GCOUNT", 1), ("TFIELDS", len(ext))]
            for i, (k, form) in enumerate(forms.items(), 1):
                head += [(f"TTYPE{i}", f"'{k}'"), (f"TFORM{i}", f"'{form}'")]
            data = rows.tobytes()
            f.write(cards(head) + data.ljust(-(-len(data) // RECORD) * RECORD, b"\0"))
