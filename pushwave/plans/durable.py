"""Lineage cuts in the folder that all executors share.

A cut is a Parquet table below ``spark.checkpoint.dir``: it is computed once (an RDD
checkpoint computes its input twice), it is compressed, later reads prune its columns,
and it outlives any executor.
"""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CONF = "spark.checkpoint.dir"


def shared_dir(spark: SparkSession) -> str:
    """The session's shared folder. Where none is set a local master gets a folder of this machine; on a
    cluster that would lose data, so there it is an error."""
    named = spark.sparkContext.getConf().get(CONF, None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError(f"set {CONF} to a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="pushwave-")
        spark.sparkContext.setCheckpointDir(named)
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str = "cut", **options: str) -> DataFrame:
    """Write df once and go on from the written table; options: of the Parquet writer."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, column: str, name: str = "bucketed") -> DataFrame:
    """Write df in sorted buckets of a column, as many as shuffle partitions: joins and aggregations on it
    read the table without an exchange."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    called = f"pushwave_{name}_{uuid.uuid4().hex}"
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    df.repartition(buckets, column).write.bucketBy(buckets, column).sortBy(column).option("path", path).saveAsTable(called)
    return spark.table(called)


def local_path(spark: SparkSession, named: str) -> str | None:
    """The path by which every machine opens a file of the shared folder, or None where only Hadoop's readers do."""
    path = spark._jvm.org.apache.hadoop.fs.Path(named)
    return path.toUri().getPath() if path.getFileSystem(spark._jsc.hadoopConfiguration()).getScheme() == "file" else None


def drop(*tables: DataFrame) -> None:
    """Delete cuts that nothing reads any more, and what exchanges without a reader have left."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path
        fs = path(shared_dir(spark)).getFileSystem(spark._jsc.hadoopConfiguration())
        root = fs.makeQualified(path(shared_dir(spark))).toString()
        for folder in {path(f).getParent().toString() for f in df.inputFiles()}:
            if folder.startswith(root + "/"):
                fs.delete(path(folder), True)
    if tables:
        tables[0].sparkSession._jvm.System.gc()  # Spark deletes the files of exchanges that the driver has forgotten


#: Arrays of at most so many bytes are read instead of mapped.
SMALL = 1 << 16


class Mapped:
    """Arrays in files that tasks map, so the workers of an executor share their pages, and neither the driver
    nor a worker holds them in its own memory. They lie in the shared folder, once, where that is opened by
    path; else Spark copies them to every executor once."""

    def __init__(self, names: list[str]):
        self.names = names

    @property
    def value(self) -> tuple[np.ndarray, ...]:
        return tuple(self._open(n if os.path.isabs(n) else SparkFiles.get(n)) for n in self.names)

    @staticmethod
    def _open(path: str) -> np.ndarray:
        return np.asarray(np.load(path, mmap_mode="r" if os.path.getsize(path) > SMALL else None))

    def drop(self) -> None:
        """Delete the files of the shared folder."""
        for n in self.names:
            if os.path.isabs(n):
                os.unlink(n)


class ArrayFile:
    """A file for an array that is still to be filled; shared: in the shared folder, where tasks write into it."""

    def __init__(self, spark: SparkSession, dtype, size: int):
        folder = local_path(spark, shared_dir(spark))
        self.shared = folder is not None
        if self.shared:
            os.makedirs(folder, exist_ok=True)
        self.path = os.path.join(folder if self.shared else os.path.realpath(tempfile.mkdtemp(prefix="pushwave-")), f"array-{uuid.uuid4().hex}.npy")
        self.width = np.dtype(dtype).itemsize
        if size:
            np.lib.format.open_memmap(self.path, "w+", dtype, (size,))
        else:
            np.save(self.path, np.empty(0, dtype))
        self.begin = os.path.getsize(self.path) - size * self.width


def mapped(spark: SparkSession, *arrays: np.ndarray | ArrayFile) -> Mapped:
    """Hand arrays, or files that have been filled, to all executors."""
    names = []
    for a in arrays:
        if not isinstance(a, ArrayFile):
            a, values = ArrayFile(spark, a.dtype, len(a)), a
            put(a.path, a.begin, a.width, [(0, np.ascontiguousarray(values).data)])
        if not a.shared:
            spark.sparkContext.addFile(a.path)
        names.append(a.path if a.shared else os.path.basename(a.path))
    return Mapped(names)


def runs_of(at: np.ndarray, values: np.ndarray) -> list[tuple[int, bytes]]:
    """(first place, bytes) of values whose places follow one another."""
    border = np.concatenate([[0], np.flatnonzero(np.diff(at) != 1) + 1, [len(at)]])
    return [(int(at[i]), values[i:j].tobytes()) for i, j in zip(border[:-1], border[1:], strict=True) if i < j]


def put(path: str, begin: int, width: int, runs) -> None:
    """Write runs (place, bytes) into an array's file."""
    with open(path, "r+b") as f:
        for at, run in runs:
            f.seek(begin + at * width)
            f.write(run)


def fill(rows: DataFrame, runs: Callable, out: ArrayFile) -> None:
    """Put what runs makes of rows (batches of at, run: bytes of out's type) into out: by the tasks where they can
    open it (one that is tried again writes the same bytes), else by the driver, a partition at a time."""
    path, begin, width = out.path, out.begin, out.width
    if not out.shared:
        put(path, begin, width, rows.mapInArrow(runs, "at long, run binary").toLocalIterator(prefetchPartitions=True))
        return

    def write(batches):
        for b in runs(batches):
            put(path, begin, width, zip(*(c.to_pylist() for c in b.columns), strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows], pa.int64())], names=["n"])

    rows.mapInArrow(write, "n long").agg(F.sum("n")).collect()  # one row


def ship(spark: SparkSession) -> None:
    """Make this package importable in the Python workers of executors that lack it."""
    sc = spark.sparkContext
    if getattr(sc, "_pushwave_shipped", False):
        return
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    target = os.path.join(os.path.realpath(tempfile.mkdtemp(prefix="pushwave-")), "pushwave_src.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(os.path.join(root, "pushwave")):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.relpath(full, root))
    sc.addPyFile(target)
    sc._pushwave_shipped = True
