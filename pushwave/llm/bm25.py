"""Corpus-wide BM25 search of a stated set of seed documents against every document.

Terms are token ids, so statistics over all documents are arrays of the vocabulary's size. Seeds lie
in blocks in a written table. Each task holds an inverted index over one block of seeds at a time
and runs every document of its split through it: terms that many seeds hold are columns of a dense
product, the others are postings. Scores are exact; nothing is pruned by an estimate.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs as pafs
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pushwave.llm.common import Batches, table, tidy
from pushwave.plans.durable import cut, new_folder

K1, B = 1.2, 0.75
#: Seeds of a block; documents scored at a time; seed blocks a task keeps between batches.
SEEDS, DOCS, KEPT = 2048, 512, 8
#: Share of a block's seeds that hold a term from which on it is a dense column.
DENSE = 0.04
#: Ids of documents that are sorted together.
TOGETHER = 1 << 20
#: Documents of one in this many, by hash, tighten the floors before all are searched.
PROBE = 10


@dataclass(frozen=True)
class Statistics:
    """Of all documents: how many, their mean length, the document frequency of every term, and the
    type of a term."""

    n: int
    mean: float
    df: np.ndarray
    term: str

    def idf(self) -> np.ndarray:
        return np.log1p((self.n - self.df + 0.5) / (self.df + 0.5)).astype(np.float32)

    def weights(self, idf: np.ndarray, terms: np.ndarray, times: np.ndarray, length: np.ndarray) -> np.ndarray:
        """BM25 weight of each posting: its term, how often the document holds it, and the document's length."""
        norm = K1 * (1 - B + B * length / max(1.0, self.mean))
        return (idf[terms] * times * (K1 + 1) / (times + norm)).astype(np.float32)


def term_rows(docs: list[bytes], dtype: np.dtype) -> tuple[list[bytes], list[bytes]]:
    """(terms, times) of documents (packed ids, none empty), packed: terms as ids are, times in 2 bytes each or,
    if one of the document may need more, in 4. Documents are sorted together, about TOGETHER ids at a time."""
    sizes = np.fromiter(map(len, docs), np.int64, len(docs)) // dtype.itemsize
    border, terms, times, s = np.cumsum(sizes), [], [], 0
    while s < len(docs):
        e = max(s + 1, int(np.searchsorted(border, (border[s - 1] if s else 0) + TOGETHER, side="right")))
        bits = 8 * dtype.itemsize
        e = min(e, s + (1 << bits))
        wide = np.uint32 if bits == 16 else np.uint64  # document, then id
        key = np.repeat(np.arange(e - s, dtype=wide) << wide(bits), sizes[s:e])
        key |= np.frombuffer(b"".join(docs[s:e]), dtype)
        key.sort()
        new = np.ones(len(key), bool)
        np.not_equal(key[1:], key[:-1], out=new[1:])
        first = np.flatnonzero(new)
        count = np.diff(first, append=len(key))
        at = np.searchsorted(first, np.append(0, border[s:e] - border[s] + sizes[s])).tolist()
        ids, short, long_ = key[first].astype(dtype).tobytes(), count.astype("<u2").tobytes(), None
        for lo, hi, n in zip(at, at[1:], sizes[s:e].tolist(), strict=False):
            terms.append(ids[lo * dtype.itemsize : hi * dtype.itemsize])
            if n < 65536:
                times.append(short[2 * lo : 2 * hi])
            else:
                long_ = count.astype("<u4").tobytes() if long_ is None else long_
                times.append(long_[4 * lo : 4 * hi])
        s = e
    return terms, times


def unpack_times(times: list[bytes], sizes: np.ndarray) -> np.ndarray:
    """How often each term occurs, of all documents in turn."""
    if all(len(t) == 2 * n for t, n in zip(times, sizes.tolist(), strict=True)):
        return np.frombuffer(b"".join(times), "<u2")
    return np.concatenate([np.frombuffer(t, "<u2" if len(t) == 2 * n else "<u4").astype(np.int64) for t, n in zip(times, sizes.tolist(), strict=True)])


def statistics(docs: DataFrame, vocabulary: int, term: str) -> Statistics:
    """docs: n (length), terms. Counts are summed by task, then by term; the vocabulary bounds what is collected."""

    def count(batches: Batches) -> Batches:
        df = np.zeros(vocabulary, np.int64)
        for b in batches:
            flat = np.frombuffer(b"".join(b.column("terms").to_pylist()), term)
            df += np.bincount(flat, minlength=vocabulary)
        used = np.flatnonzero(df)
        yield table(pa.schema([("term", pa.int32()), ("df", pa.int64())]), used, df[used])

    n, mean = docs.agg(F.count(F.lit(1)), F.avg("n")).first()
    found = docs.select("terms").mapInArrow(count, "term int, df long").groupBy("term").agg(F.sum("df").alias("df")).collect()
    df = np.zeros(vocabulary, np.int64)
    for r in found:
        df[r["term"]] = r["df"]
    return Statistics(int(n), float(mean or 1.0), df, term)


class SeedIndex:
    """Inverted index over one block of seeds; a query is the set of a seed's terms."""

    def __init__(self, keys: np.ndarray, floors: np.ndarray, selves: np.ndarray, terms: list[np.ndarray], vocabulary: int):
        self.keys, self.floors, self.selves = keys, floors, selves
        flat = np.concatenate(terms) if terms else np.zeros(0, np.int64)
        seed = np.repeat(np.arange(len(terms)), [len(t) for t in terms])
        held = np.bincount(flat, minlength=vocabulary)
        common = np.flatnonzero(held > DENSE * len(terms))
        self.slot = np.full(vocabulary, -1)
        self.slot[common] = np.arange(len(common))
        self.dense = np.zeros((len(common), len(terms)), np.float32)
        at = self.slot[flat]
        self.dense[at[at >= 0], seed[at >= 0]] = 1
        rare, owner = flat[at < 0], seed[at < 0]
        self.seed = owner[np.argsort(rare, kind="stable")]
        self.held = np.bincount(rare, minlength=vocabulary)
        self.first = np.cumsum(self.held) - self.held

    def scores(self, owner: np.ndarray, terms: np.ndarray, weights: np.ndarray, n: int) -> np.ndarray:
        """[n documents, seeds] from postings (document place, term, weight)."""
        slot = self.slot[terms]
        wide = np.zeros((n, len(self.dense)), np.float32)
        dense = slot >= 0
        wide[owner[dense], slot[dense]] = weights[dense]
        out = wide @ self.dense
        owner, terms, weights = owner[~dense], terms[~dense], weights[~dense]
        held = self.held[terms]
        total = int(held.sum())
        if total:
            rows = np.repeat(self.first[terms] - np.cumsum(held) + held, held) + np.arange(total)
            cell = np.repeat(owner * len(self.keys), held) + self.seed[rows]
            out += np.bincount(cell, np.repeat(weights, held), out.size).reshape(out.shape)
        return out


def _blocks(files: list[str], stats: Statistics, kept: dict) -> Iterator[SeedIndex]:
    """The seed blocks of some files, read one at a time; the first few stay in memory."""
    for uri in files:
        index = kept.get(uri)
        if index is None:
            filesystem, path = pafs.FileSystem.from_uri(uri)
            t = pq.read_table(path, filesystem=filesystem)
            t = t.sort_by("key")
            index = SeedIndex(t.column("key").to_numpy(), t.column("floor").to_numpy(), t.column("self").to_numpy(), [np.frombuffer(x, stats.term) for x in t.column("terms").to_pylist()], len(stats.df))
            if len(kept) < KEPT:
                kept[uri] = index
        yield index


def _best_of_each(seed: np.ndarray, doc: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of every seed; ties by document."""
    order = np.lexsort((doc, -score, seed))
    s = seed[order]
    first = np.searchsorted(s, s)
    return order[np.arange(len(s)) - first < k]


def _search(docs: DataFrame, files: list[str], stats: Statistics, k: int) -> DataFrame:
    """Rows of two kinds from documents (key, n, terms, times): seed null: (key, home, score) of every
    document; else one of the k best documents of a seed inside a batch, if it reaches the seed's floor."""
    schema = pa.schema([("seed", pa.int64()), ("key", pa.int64()), ("home", pa.int64()), ("score", pa.float64())])

    def run(batches: Batches) -> Batches:
        idf, kept = stats.idf(), {}
        for b in batches:
            keys, n = b.column("key").to_numpy(), b.column("n").to_numpy()
            terms = b.column("terms").to_pylist()
            size = np.fromiter(map(len, terms), np.int64, len(terms)) // np.dtype(stats.term).itemsize
            flat = np.frombuffer(b"".join(terms), stats.term)
            times = unpack_times(b.column("times").to_pylist(), size)
            weights = stats.weights(idf, flat, times, np.repeat(n, size))
            border = np.concatenate([[0], np.cumsum(size)])
            home, best = np.full(len(keys), -1), np.zeros(len(keys))
            for index in _blocks(files, stats, kept):
                root = 1 / np.sqrt(np.maximum(index.selves, 1e-9)).astype(np.float32)
                rows = []
                for s in range(0, len(keys), DOCS):
                    e = min(s + DOCS, len(keys))
                    own = slice(border[s], border[e])
                    score = index.scores(np.repeat(np.arange(e - s), size[s:e]), flat[own], weights[own], e - s)
                    if k:
                        d, q = np.nonzero((score >= index.floors[None, :]) & (score > 0))
                        other = keys[s + d] != index.keys[q]
                        rows.append((q[other], keys[s + d[other]], score[d[other], q[other]]))
                    score *= root
                    at = score.argmax(axis=1)
                    top = score[np.arange(e - s), at].astype(np.float64)
                    ahead = (top > best[s:e]) | ((top == best[s:e]) & (top > 0) & (index.keys[at] < home[s:e]))
                    home[s:e] = np.where(ahead, index.keys[at], home[s:e])
                    best[s:e] = np.where(ahead, top, best[s:e])
                if rows:
                    q, d, x = (np.concatenate(c) for c in zip(*rows, strict=True))
                    use = _best_of_each(q, d, x, k)
                    yield table(schema, index.keys[q[use]], d[use], np.full(len(use), -1), x[use].astype(np.float64))
            yield table(schema, pa.nulls(len(keys), pa.int64()), keys, home, best)

    return docs.select("key", "n", "terms", "times").mapInArrow(tidy(run), "seed long, key long, home long, score double")


def _write_seeds(seeds: DataFrame, count: int) -> list[str]:
    path = new_folder(seeds.sparkSession, "seeds")
    parts = -(-count // SEEDS)
    seeds.repartition(parts, "key").write.option("maxRecordsPerFile", SEEDS).parquet(path)
    return seeds.sparkSession.read.parquet(path).inputFiles()


def _first(found: DataFrame, k: int) -> DataFrame:
    """(seed, rk, key, score): the k best of every seed, ties by document."""
    w = Window.partitionBy("seed").orderBy(F.col("score").desc(), "key")
    return found.filter("seed is not null").select("seed", "key", "score").withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k)


def search(docs: DataFrame, is_seed: Column, k: int, vocabulary: int, term: str) -> tuple[DataFrame, DataFrame]:
    """(homes, lists) of a written table of documents (key, n, terms, times).

    homes (key, home, score): the seed whose query scores a document best, over the root of the
    seed's own score, so that long seeds don't draw everything; -1 where no seed shares a term.
    lists (seed, rk, key, score): the k best other documents of every seed among all documents.
    Without seeds all homes are -1 and there are no lists.
    """
    spark = docs.sparkSession
    stats = statistics(docs, vocabulary, term)
    seeds = docs.filter(is_seed)
    count = seeds.count()
    if not count:
        return docs.select("key", F.lit(-1).cast("long").alias("home"), F.lit(0.0).alias("score")), spark.createDataFrame([], "seed long, rk int, key long, score double")

    def worth(batches: Batches) -> Batches:
        schema = pa.schema([("key", pa.int64()), ("n", pa.int64()), ("terms", pa.binary()), ("times", pa.binary()), ("self", pa.float64())])
        idf = stats.idf()
        for b in batches:
            selves = []
            for n, t, c in zip(*(b.column(x).to_pylist() for x in ("n", "terms", "times")), strict=True):
                terms = np.frombuffer(t, stats.term)
                selves.append(float(stats.weights(idf, terms, unpack_times([c], np.array([len(terms)])), np.float32(n)).sum()))
            yield table(schema, b.column("key"), b.column("n"), b.column("terms"), b.column("times"), selves)

    seeds = cut(seeds.select("key", "n", "terms", "times").mapInArrow(worth, "key long, n long, terms binary, times binary, self double"), "seeds")
    # The k-th best among a part of the documents bounds the k-th best of all from below. Ever larger
    # parts (the seeds, one document in PROBE, all) keep what leaves the tasks to about PROBE * k rows a seed.
    files = _write_seeds(seeds.select("key", "terms", "self", F.lit(0.0).alias("floor")), count)
    for part in (seeds, docs.filter(F.pmod(F.xxhash64("key"), F.lit(PROBE)) == 0)):
        among = _first(_search(part, files, stats, k), k).filter(F.col("rk") == k).select(F.col("seed").alias("key_of"), (F.col("score") * (1 - 1e-5)).alias("floor"))
        floored = seeds.join(among, F.col("key") == F.col("key_of"), "left")
        files = _write_seeds(floored.select("key", "terms", "self", F.coalesce("floor", F.lit(0.0)).alias("floor")), count)
    found = cut(_search(docs, files, stats, k), "found")
    return found.filter("seed is null").select("key", "home", "score"), _first(found, k)
