"""Pieces that the corpus operators share."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from contextlib import suppress

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pushwave.plans.durable import ship

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: Rows and bytes in an Arrow batch: whole texts are long, so batches are kept short.
BATCH_ROWS, BATCH_BYTES = 2048, 16 << 20
#: Translates UTF-8 so that words are digits, lower-cased letters and all beyond ASCII; the rest are blanks.
WORD_BYTES = bytes(b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))


def prepare(spark: SparkSession) -> SparkSession:
    """Ship the package to the workers and bound the Arrow batches (a run-time setting)."""
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return spark


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    df = prepare(spark).read.parquet(f"{sf_dir}/documents.parquet")
    return df.select(*(columns or ("doc_id", "text")))


def crc_mod(column: str, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % F.lit(n)


def raw(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    """A string column as UTF-8 bytes."""
    return batch.column(name).cast(pa.binary()).to_pylist()


def table(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, each with underscores before it until df has no column of that name."""
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


Batches = Iterator[pa.RecordBatch]


def give_back() -> None:
    """Return freed memory of this process to the system."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """run; after it a worker gives back what it freed. Workers outlive tasks, so that would count beside all later stages' memory."""

    def after(batches: Batches) -> Batches:
        try:
            yield from run(batches)
        finally:
            give_back()

    return after
