"""Lexical retrieval packing of documents into fixed windows (operator 10).

Documents are tokenized once into a written table. The seeds are the documents whose id is divisible
by 100. A BM25 index over blocks of seeds scores every document of the corpus against every seed,
with document frequencies and mean length of all documents (see bm25). Each seed gets its best
neighbours; a document that several seeds want goes to the seed it ranks best for, and one that no
seed lists goes to the seed that scores it best. So no document is used twice. A seed and its
neighbours, best first, fill one window after the other; the last document of a window is cut where
the window ends. What is ordered and summed are ids and lengths alone, so windows have no gaps and
only the last of all is padded; the tokens move once, to meet their places.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pushwave.llm import bm25
from pushwave.llm.common import Batches, raw, table, tidy
from pushwave.llm.wordpieces import codec
from pushwave.plans.durable import cut

WINDOW = 4096
#: Ids divisible by this are seeds; neighbours that a seed lists.
SEED_EVERY, NEIGHBOURS = 100, 8
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_ARROW = pa.schema([(c.split()[0], pa.int64()) for c in PIECES.split(", ")])
_TOKENS = "key long, doc_id long, n long, ids binary, terms binary, times binary"


def tokenized(docs: DataFrame, vocabulary: str, end_id: int) -> DataFrame:
    """A written table of every row of docs: key (own number), doc_id, n, ids, terms, times."""

    def run(batches: Batches) -> Batches:
        from pyspark import TaskContext

        schema = pa.schema([("key", pa.int64()), ("doc_id", pa.int64()), ("n", pa.int64()), ("ids", pa.binary()), ("terms", pa.binary()), ("times", pa.binary())])
        ids, key = codec(vocabulary), TaskContext.get().partitionId() << 33
        end = np.array([end_id], ids.dtype).tobytes()
        for b in batches:
            found = [d + end for d in ids.encode(raw(b, "text"))]
            yield table(schema, np.arange(key, key + len(found)), b.column("doc_id"), [len(d) // ids.dtype.itemsize for d in found], found, *bm25.term_rows(found, ids.dtype))
            key += len(found)
        ids.forget()

    return cut(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(run), _TOKENS), "tokens", compression="zstd")


def neighbours(docs: DataFrame, vocabulary: str, k: int, every: int = SEED_EVERY, end_id: int = 2) -> DataFrame:
    """(doc_id, rk, neighbour, score): the k best other documents of every seed, by exact BM25 over all rows."""
    tokens = tokenized(docs, vocabulary, end_id)
    _, lists = _searched(tokens, vocabulary, k, every)
    names = tokens.select("key", "doc_id")
    named = lists.join(names.withColumnRenamed("doc_id", "neighbour"), "key").drop("key")
    return named.join(names.withColumnRenamed("key", "seed"), "seed").select("doc_id", "rk", "neighbour", "score")


def _searched(tokens: DataFrame, vocabulary: str, k: int, every: int) -> tuple[DataFrame, DataFrame]:
    ids = codec(vocabulary)
    return bm25.search(tokens, _seeds(every), k, ids.tokenizer.get_vocab_size(), ids.dtype.str)


def _seeds(every: int) -> Column:
    return F.coalesce(F.col("doc_id") % every == 0, F.lit(False))


def _places(homes: DataFrame, lists: DataFrame, tokens: DataFrame, every: int) -> DataFrame:
    """(key, at): tokens before each document when all are laid end to end, group after group."""
    claim = lists.groupBy("key").agg(F.min(F.struct("rk", (-F.col("score")).alias("s"), "seed")).alias("claim"))
    short = tokens.select("key", "n", _seeds(every).alias("is_seed"))
    own = short.join(homes, "key").join(claim, "key", "left")
    group = F.when(F.col("is_seed"), F.col("key")).otherwise(F.coalesce("claim.seed", "home"))
    turn = F.when(F.col("is_seed"), 0).when(F.col("claim").isNotNull(), F.col("claim.rk")).otherwise(F.lit(2**31 - 1))
    keyed = own.select("key", "n", group.alias("g"), turn.alias("turn"), F.when(F.col("claim").isNull(), -F.col("score")).otherwise(0.0).alias("s"))
    order = ["g", "turn", "s", "key"]
    laid = cut(keyed.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "order")
    # One row a partition, so this window over all of them is bounded by the number of tasks.
    sums = laid.groupBy("part").agg(F.sum("n").alias("n"))
    before = sums.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    run = laid.select("key", "part", F.coalesce(F.sum("n").over(inside), F.lit(0)).alias("inside"))
    return run.join(F.broadcast(before), "part").select("key", (F.col("before") + F.col("inside")).alias("at"))


def pack(docs: DataFrame, vocabulary: str, end_id: int = 2, window: int = WINDOW, every: int = SEED_EVERY, k: int = NEIGHBOURS) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Null and empty texts are documents of the end id alone. Rows with equal ids, or wholly equal
    rows, are packed each for itself. Null ids stay null and are no seeds. Where there is no seed,
    or none that shares a term with a document, documents follow each other in the order of the
    rows read. An empty table gives no piece. Other columns are not read. Long texts fill several
    windows.
    """
    tokens = tokenized(docs, vocabulary, end_id)
    homes, lists = _searched(tokens, vocabulary, k, every)
    dtype = codec(vocabulary).dtype

    def run(batches: Batches) -> Batches:
        for b in batches:
            rows = []
            for doc_id, data, at in zip(b.column("doc_id").to_pylist(), b.column("ids").to_pylist(), b.column("at").to_pylist(), strict=True):
                found, start = np.frombuffer(data, dtype).astype("<u4"), 0
                while start < len(found):
                    offset = (at + start) % window
                    end = min(len(found), start + window - offset)
                    rows.append((doc_id, start, end - start, zlib.crc32(found[start:end].tobytes()), len(found), (at + start) // window, offset))
                    start = end
            if rows:
                yield table(_ARROW, *zip(*rows, strict=True))

    placed = tokens.select("key", "doc_id", "ids").join(_places(homes, lists, tokens, every), "key")
    return placed.select("doc_id", "ids", "at").mapInArrow(tidy(run), PIECES)
