"""Token-id shards with a shared zstandard dictionary (operator 4).

A store is a folder: one dictionary file, named by its SHA-256, and shards. A shard is

    header   magic, bytes an id, SHA-256 of the dictionary
    frames   one zstandard frame a document, ascending doc_id, each readable by itself
    index    doc_id, token count and frame offset of each document, as little-endian int64 arrays
    footer   offset of the index, number of documents, tokens in all, magic

so that one short document costs one index look-up and one small read. Documents are dealt by
doc_id ranges; a shard's tokens before it come from the manifest, one row a shard. A task that
runs again writes a file of another name, and readers open only what the manifest names.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard as zstd
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pushwave.llm.common import Batches, raw, table, tidy
from pushwave.llm.wordpieces import codec
from pushwave.plans.durable import cut, new_folder

MAGIC = b"PWZIDS1\n"
#: Layouts of header and footer.
HEADER, FOOTER = "<8sB32s", "<QQQ8s"
#: The dictionary: its size, and the bounded sample it is trained on (documents and code points of each).
DICT_BYTES, SAMPLE_DOCS, SAMPLE_CHARS = 65_536, 512, 16_384
#: Compressed bytes after which a task goes on with another shard.
SHARD_BYTES = 64 << 20
LEVEL = 3
NO_ID = -(2**63)


def train_dictionary(samples: list[bytes]) -> bytes:
    """A zstandard dictionary; where the samples are too few to train one, their raw content."""
    samples = [s for s in samples if len(s) >= 8]
    try:
        return zstd.train_dictionary(DICT_BYTES, samples).as_bytes()
    except zstd.ZstdError:
        return b"".join(samples)[-DICT_BYTES:]


def _dict(data: bytes) -> zstd.ZstdCompressionDict | None:
    return zstd.ZstdCompressionDict(data) if data else None


def _open(folder: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(folder)


@dataclass(frozen=True)
class Store:
    folder: str
    dictionary: bytes
    width: int
    #: shard long, file string, n_docs long, n_tokens long, first_start long
    manifest: DataFrame


def _writer(folder: str, dictionary: bytes, vocabulary: str, end_id: int):
    def write(batches: Batches) -> Batches:
        from pyspark import TaskContext

        task = TaskContext.get().partitionId()
        filesystem, base = _open(folder)
        ids = codec(vocabulary)
        end = np.array([end_id], ids.dtype).tobytes()
        press = zstd.ZstdCompressor(level=LEVEL, dict_data=_dict(dictionary), write_content_size=True)
        schema = pa.schema([("shard", pa.int64()), ("file", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())])
        out, n_shards = None, 0

        def close():
            where = out.tell()
            for column in index:
                out.write(np.asarray(column, "<i8").tobytes())
            out.write(struct.pack(FOOTER, where, len(index[0]), sum(index[1]), MAGIC))
            out.close()
            return table(schema, [(task << 20) + n_shards], [name], [len(index[0])], [sum(index[1])])

        for batch in batches:
            for doc_id, data in zip(batch.column("doc_id").to_pylist(), ids.encode(raw(batch, "text")), strict=True):
                if out is None:
                    name, index = f"part-{task:06d}-{uuid.uuid4().hex}.zids", ([], [], [])
                    out = filesystem.open_output_stream(f"{base}/{name}")
                    out.write(struct.pack(HEADER, MAGIC, ids.dtype.itemsize, hashlib.sha256(dictionary).digest()))
                data += end
                for column, value in zip(index, (NO_ID if doc_id is None else doc_id, len(data) // ids.dtype.itemsize, out.tell()), strict=True):
                    column.append(value)
                out.write(press.compress(data))
                if out.tell() > SHARD_BYTES:
                    yield close()
                    out, n_shards = None, n_shards + 1
        if out is not None:
            yield close()
        ids.forget()

    return tidy(write)


def _sample(docs: DataFrame) -> list[bytes]:
    """SAMPLE_DOCS texts at most, in hash order: ids are chosen first, and the texts of those alone are fetched."""
    short = docs.filter(F.char_length("text").between(1, SAMPLE_CHARS)).select("doc_id", "text", F.xxhash64("text").alias("_tid"))
    chosen = short.select("doc_id", "_tid").orderBy(F.xxhash64("doc_id"), "doc_id", "_tid").limit(SAMPLE_DOCS).distinct().collect()
    if not chosen:
        return []
    few = docs.sparkSession.createDataFrame(chosen, "_id long, _t long")
    met = short.join(F.broadcast(few), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_tid") == F.col("_t"))).groupBy("doc_id", "_tid").agg(F.min("text").alias("text"))
    return [r["text"].encode() for r in sorted(met.collect(), key=lambda r: (r["doc_id"] is None, r["doc_id"] or 0, r["text"]))]


def write_store(docs: DataFrame, vocabulary: str, end_id: int = 1, folder: str | None = None) -> Store:
    """Encode docs (doc_id, text) and write them in ascending doc_id order; ties by text, null ids first.

    Null and empty texts are documents of the end id alone; an empty table gives a store without
    shards. Other columns are not read.
    """
    spark = docs.sparkSession
    folder = folder or new_folder(spark, "tokens")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    ids = codec(vocabulary)
    dictionary = train_dictionary(ids.encode(_sample(docs)))
    filesystem, base = _open(folder)
    filesystem.create_dir(base, recursive=True)
    with filesystem.open_output_stream(f"{base}/{hashlib.sha256(dictionary).hexdigest()}.zdict") as f:
        f.write(dictionary)
    ordered = docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    shards = cut(ordered.mapInArrow(_writer(folder, dictionary, vocabulary, end_id), "shard long, file string, n_docs long, n_tokens long"), "manifest")
    # One row a shard, so this window over all of them is bounded by the number of files.
    before = F.sum("n_tokens").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    return Store(folder, dictionary, ids.dtype.itemsize, cut(shards.withColumn("first_start", F.coalesce(before, F.lit(0))), "manifest"))


class Shard:
    """Random access to one shard file."""

    def __init__(self, folder: str, file: str, dictionary: bytes):
        filesystem, base = _open(folder)
        self.file = filesystem.open_input_file(f"{base}/{file}")
        size = self.file.size()
        head = struct.unpack(HEADER, self.file.read_at(struct.calcsize(HEADER), 0))
        where, n, self.n_tokens, magic = struct.unpack(FOOTER, self.file.read_at(struct.calcsize(FOOTER), size - struct.calcsize(FOOTER)))
        if head[0] != MAGIC or magic != MAGIC:
            raise ValueError(f"{file} is not a shard")
        if head[2] != hashlib.sha256(dictionary).digest():
            raise ValueError(f"{file} was written with another dictionary")
        self.dtype = np.dtype(f"<u{head[1]}")
        flat = np.frombuffer(self.file.read_at(24 * n, where), "<i8").reshape(3, n)
        self.ids, self.counts, self.offsets = flat
        self.ends = np.append(self.offsets[1:], where)
        self.press = zstd.ZstdDecompressor(dict_data=_dict(dictionary))

    def tokens(self, i: int) -> np.ndarray:
        frame = self.file.read_at(int(self.ends[i] - self.offsets[i]), int(self.offsets[i]))
        return np.frombuffer(self.press.decompress(frame), self.dtype)

    def find(self, doc_id: int) -> np.ndarray:
        """Places of a document in this shard."""
        return np.arange(*np.searchsorted(self.ids, [doc_id, doc_id + 1]))


def read_document(store: Store, doc_id: int) -> list[np.ndarray]:
    """The ids of one document (several if its id repeats), by index, without reading other frames."""
    out = []
    for row in store.manifest.orderBy("shard").collect():  # one row a shard
        shard = Shard(store.folder, row["file"], store.dictionary)
        out += [shard.tokens(int(i)) for i in shard.find(doc_id)]
    return out


def read_store(store: Store, spark: SparkSession) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files."""
    folder, dictionary = store.folder, store.dictionary
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def read(batches: Batches) -> Batches:
        for b in batches:
            for file, start in zip(b.column("file").to_pylist(), b.column("first_start").to_pylist(), strict=True):
                shard = Shard(folder, file, dictionary)
                starts = start + np.cumsum(shard.counts) - shard.counts
                for s in range(0, len(shard.ids), 10_000):
                    e = min(s + 10_000, len(shard.ids))
                    sums, counts = [], []
                    for i in range(s, e):
                        ids = shard.tokens(i)
                        counts.append(len(ids))
                        sums.append(zlib.crc32(ids.astype("<u4").tobytes()))
                    names = [None if x == NO_ID else x for x in shard.ids[s:e].tolist()]
                    yield table(schema, names, starts[s:e], counts, sums)

    n = max(1, store.manifest.count())
    return store.manifest.repartition(n).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")
