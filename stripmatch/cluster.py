"""Session-level plumbing: shipping the package, shared folders, narrow written tables."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_PACKAGE = Path(__file__).resolve().parent
_shipped: set[str] = set()
_scratch: list[list[str]] = []


def ship(spark: SparkSession) -> None:
    """Make this package importable by the Python workers of every executor (once per application)."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    target = os.path.join(tempfile.mkdtemp(prefix="stripmatch-"), "stripmatch_pkg.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in _PACKAGE.rglob("*.py"):
            z.write(p, f"{_PACKAGE.name}/{p.relative_to(_PACKAGE)}")
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a local one where it is unset (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir is not set: a folder that driver and executors share is needed")
    local = "file:///tmp/checkpoints/stripmatch"
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(local)
    return local


def note(path: str) -> str:
    """Remember a folder that belongs to the scratch in force, if any."""
    for s in _scratch[-1:]:
        s.append(path)
    return path


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """What operators write to the shared folder within it goes at its end. Nothing lazy that reads it may be used later."""
    _scratch.append([])
    try:
        yield
    finally:
        jvm = spark._jvm
        for path in _scratch.pop():
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def written(df: DataFrame, what: str, by: str | None = None) -> DataFrame:
    """Cut the lineage of df: write it as Parquet into the shared folder and read it back.

    Unlike a local checkpoint it outlives any executor. The folder is unique to the call. by: a column with a directory
    for each of its values, so that a reader of one value reads no other.
    """
    spark = df.sparkSession
    path = note(f"{shared_dir(spark)}/stripmatch/{what}-{uuid.uuid4().hex}")
    (df.write if by is None else df.repartition(by).write.partitionBy(by)).parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    return back if by is None else back.select(df.columns)  # reading puts that column last


def clean(spark: SparkSession, keep: tuple[str, ...] = ("catalog",)) -> int:
    """Remove what operators have written to the shared folder, but for names that begin with one of `keep`; call it between runs. Back comes how many went."""
    jvm = spark._jvm
    root = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/stripmatch")
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    gone = [s.getPath() for s in (fs.listStatus(root) if fs.exists(root) else []) if not s.getPath().getName().startswith(keep)]
    return sum(bool(fs.delete(p, True)) for p in gone)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
