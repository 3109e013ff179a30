"""Benchmark decontamination by latent semantic retrieval (operator 2).

Passages and benchmark items are TF-IDF vectors over the benchmark's words; document frequencies
count every document. A randomised SVD gives the latent space: all tasks sum, over their passages,
the products of a random test matrix with the counts of every document, and the benchmark's items join
with a weight; one pass is enough, since the sketch of a Gram matrix yields its leading
eigenvectors. Then every window of every document is projected and compared with every item
by cosine. So that no verbatim copy hangs on the latent space, windows that hold the rarest run of
four words of a passage's half are candidates too. Candidates are settled by the longest common
subsequence of words, bit-parallel, and by whether the item's last words (its answer) turn up, which
lets a looser paraphrase count.

The benchmark comes to the driver by blocks of passages. Each block has a vocabulary and a latent space
of its own, so what is broadcast is bounded by the block (or by one item that is longer than a block),
and a pass over the documents takes several blocks. A benchmark of any size is compared in full.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.llm.common import WORD_BYTES, Batches, raw, table, tidy
from pushwave.plans.durable import cut

#: Words of a block; blocks of a window; blocks between windows; words of an item passage at most.
BLOCK, WIDE, STEP, PASSAGE = 8, 8, 3, 40
#: Least and most latent directions of a block, passages for one direction, columns of the sketch beyond them.
RANK, MOST_RANK, PER_RANK, SPARE, SEED = 64, 128, 4, 48, 5
#: Passages that a task adds to the sketch at a time.
TOGETHER = 128
#: Least cosine of a candidate, and least part of the passage's latent energy that the window holds; least share of the item in common; the same if its answer (last words)
#: is there; least share of the item's idf that its words near the window bring together.
COSINE, HOLDS, SHARE, SHARE_WITH_ANSWER, ANSWER, RARE_SHARE = 0.4, 0.4, 0.6, 0.5, 4, 0.5
#: Least share of a passage's idf in a candidate window; largest passage-by-word table that is dense.
COVER, DENSE = 0.4, 1 << 26
#: Weight of the benchmark's passages against the corpus in the fit.
ITEM_WEIGHT = 3.0
#: Passages from which a block of the benchmark is full; blocks that one pass over the documents compares.
BLOCK_PASSAGES, PASS_BLOCKS = 512, 4
#: Words of one stretch of a long document that is projected at a time.
STRETCH = 1 << 16


def words_of(text: bytes | None) -> list[bytes]:
    return (text or b"").translate(WORD_BYTES).split()


@dataclass(frozen=True)
class Benchmark:
    """Item passages as vocabulary ids; owner: place of each passage's item."""

    names: list
    vocabulary: dict[bytes, int]
    passages: list[np.ndarray]
    owner: np.ndarray
    items: list[np.ndarray]


def _block(rows: list) -> Benchmark:
    vocabulary: dict[bytes, int] = {}
    names, items, passages, owner = [], [], [], []
    for name, words in rows:
        ids = np.fromiter((vocabulary.setdefault(w, len(vocabulary)) for w in words), np.int64, len(words))
        for part in np.array_split(ids, -(-len(ids) // PASSAGE)):
            passages.append(part)
            owner.append(len(items))
        names.append(name)
        items.append(ids)
    return Benchmark(names, vocabulary, passages, np.asarray(owner, np.int64), items)


def blocks_of(benchmark: DataFrame) -> Iterator[Benchmark]:
    """The benchmark's items in order of their ids, in blocks; the driver holds one partition of it at a time."""
    rows, size = [], 0
    for r in benchmark.select("item_id", "text").orderBy("item_id", "text").toLocalIterator():
        words = words_of((r["text"] or "").encode())
        if len(words) < ANSWER:
            continue  # nothing to recognize
        rows.append((r["item_id"], words))
        size += -(-len(words) // PASSAGE)
        if size >= BLOCK_PASSAGES:
            yield _block(rows)
            rows, size = [], 0
    if rows:
        yield _block(rows)


def rank_of(n_passages: int) -> int:
    """Latent directions for a block of so many passages."""
    return min(MOST_RANK, max(RANK, n_passages // PER_RANK))


def _codes(words: list[bytes], vocabulary: dict[bytes, int]) -> np.ndarray:
    return np.array(list(map(vocabulary.get, words, repeat(-1))), np.int64)


def _test_matrix(n: int, sketch: int) -> np.ndarray:
    return np.random.default_rng(SEED).standard_normal((n, sketch))


def _sketch(ids: np.ndarray, passage: np.ndarray, test: np.ndarray, out: np.ndarray, weight: float = 1.0) -> None:
    """out += weight * (counts^T counts) test, for words ids that lie in ascending passages."""
    if len(ids):
        _, first, at = np.unique(passage, return_index=True, return_inverse=True)
        products = np.add.reduceat(test[ids], first, axis=0)
        np.add.at(out, ids, weight * products[at])


class CorpusSketch:
    """The sketch of many passages. The counts of TOGETHER passages meet the test matrix as a dense table of the
    words that they hold, so a word costs no row of its own."""

    def __init__(self, n: int, sketch: int):
        self.n = n
        self.test, self.gram = _test_matrix(n, sketch).astype(np.float32), np.zeros((n, sketch))
        self.column, self.used = np.zeros(n, np.int64), np.zeros(n, bool)
        self.held: list[tuple[np.ndarray, np.ndarray]] = []
        self.waiting, self.n_passages = 0, 0

    def add(self, ids: np.ndarray, passage: np.ndarray, n_passages: int) -> None:
        """Words ids in ascending passages of a text's n_passages, some perhaps without a word."""
        self.held.append((ids, passage + self.waiting))
        self.waiting += n_passages
        self.n_passages += n_passages
        if self.waiting >= TOGETHER:
            self.flush()

    def flush(self) -> None:
        if not self.held:
            return
        ids, passage = (np.concatenate(x) for x in zip(*self.held, strict=True))
        self.held, self.waiting, low = [], 0, 0
        while low < len(ids):
            begin = int(passage[low])
            high = int(np.searchsorted(passage, begin + TOGETHER))
            some, rows = ids[low:high], passage[low:high] - begin
            self.used[some] = True
            words = np.flatnonzero(self.used)
            self.used[words], self.column[words] = False, np.arange(len(words))
            counts = np.zeros((int(rows[-1]) + 1, len(words)), np.float32)
            np.add.at(counts.reshape(-1), rows * len(words) + self.column[some], np.float32(1))
            self.gram[words] += counts.T @ (counts @ self.test[words])
            low = high


@dataclass(frozen=True)
class Space:
    """word: latent row of each vocabulary word, idf included; passages: their latent vectors; idf of each word."""

    idf: np.ndarray
    word: np.ndarray
    passages: np.ndarray


def latent_space(frequency: np.ndarray, n_docs: int, gram: np.ndarray, n_passages: int, bench: Benchmark) -> Space:
    """From document frequencies and the sketch of the corpus to the leading latent directions."""
    n = len(frequency)
    sketch = gram.shape[1]
    test = _test_matrix(n, sketch)
    y = gram / max(1, n_passages)
    flat = np.concatenate(bench.passages)
    where = np.repeat(np.arange(len(bench.passages)), [len(p) for p in bench.passages])
    idf = np.log((n_docs + 1) / (frequency + 1)) + 0.05
    energy = np.bincount(where, idf[flat] ** 2)  # short items count as much as long ones
    scale = float((idf**2 * np.maximum(0, np.einsum("ij,ij->i", test, y) / sketch)).sum()) or 1.0  # about the corpus's mean energy
    weights = ITEM_WEIGHT * scale / energy / len(bench.passages)
    for i in range(len(bench.passages)):
        own = bench.passages[i]
        _sketch(own, np.zeros(len(own), np.int64), test, y, float(weights[i]))
    core = test.T @ y
    core = (core + core.T) / 2
    value, vector = np.linalg.eigh(core)
    use = value > value.max() * 1e-10
    factor = (idf[:, None] * y) @ (vector[:, use] / np.sqrt(value[use]))
    left, _, _ = np.linalg.svd(factor, full_matrices=False)
    word = (idf[:, None] * left[:, : sketch - SPARE]).astype(np.float32)
    passages = np.stack([word[p].sum(axis=0) for p in bench.passages])
    return Space(idf, word, passages)


def common_words(item: np.ndarray, stretch: np.ndarray) -> int:
    """Length of the longest common subsequence."""
    masks: dict[int, int] = {}
    for i, w in enumerate(item.tolist()):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(item)) - 1
    row, get = full, masks.get
    for w in stretch.tolist():
        m = get(w)
        if m:
            u = row & m
            row = ((row + u) | (row - u)) & full
    return len(item) - row.bit_count()


def fit(docs: DataFrame, bench: Benchmark, n_docs: int) -> Space:
    """Frequencies and the sketch over all documents."""
    spark = docs.sparkSession
    sketch = rank_of(len(bench.passages)) + SPARE
    shared = spark.sparkContext.broadcast(bench.vocabulary)

    def run(batches: Batches) -> Batches:
        vocabulary = shared.value
        n = len(vocabulary)
        corpus, frequency = CorpusSketch(n, sketch), np.zeros(n, np.int64)
        for b in batches:
            for text in raw(b, "text"):
                words = words_of(text)
                held = np.zeros(0, np.int64)
                for s in range(0, len(words), STRETCH):
                    ids = _codes(words[s : s + STRETCH], vocabulary)
                    at = np.flatnonzero(ids >= 0)
                    corpus.add(ids[at], at // (BLOCK * WIDE), -(-len(ids) // (BLOCK * WIDE)))
                    held = np.unique(np.concatenate([held, ids[at]]))
                frequency[held] += 1
        corpus.flush()
        gram, n_passages = corpus.gram, corpus.n_passages
        schema = pa.schema([("word", pa.int32()), ("n", pa.int64()), ("row", pa.list_(pa.float64()))])
        used = np.flatnonzero(frequency)
        yield table(schema, [-1, *used], [n_passages, *frequency[used]], [[]] * (len(used) + 1))
        used = np.flatnonzero(gram.any(axis=1))  # none in a task without a word of the benchmark
        if len(used):
            yield table(schema, used, np.zeros(len(used), np.int64), gram[used].tolist())

    parts = docs.select("text").mapInArrow(tidy(run), "word int, n long, row array<double>")
    entries = parts.select("word", "n", F.posexplode_outer("row").alias("i", "x"))
    summed = entries.groupBy("word", "i").agg(F.sum("x").alias("x"), F.sum("n").alias("n"))
    got = summed.toArrow()  # bounded by the block's words times the sketch; columns, not row objects
    word, i, n = (got.column(c).fill_null(-1).to_numpy() for c in ("word", "i", "n"))
    x = got.column("x").fill_null(0.0).to_numpy()
    frequency, gram = np.zeros(len(bench.vocabulary), np.int64), np.zeros((len(bench.vocabulary), sketch))
    gram[word[i >= 0], i[i >= 0]] = x[i >= 0]
    counts = (i < 0) & (word >= 0)
    frequency[word[counts]] = n[counts]
    n_passages = int(n[word < 0].sum())
    return latent_space(frequency, n_docs, gram, n_passages, bench)


class Retriever:
    """Finds the items that a document contains."""

    def __init__(self, bench: Benchmark, space: Space):
        self.bench, self.space = bench, space
        sizes = [len(np.unique(p)) for p in bench.passages]
        self.worth = np.array([space.idf[np.unique(p)].sum() for p in bench.passages])
        self.dense = len(sizes) * (len(space.idf) + 1) <= DENSE
        if self.dense:
            self.table = np.zeros((len(sizes), len(space.idf) + 1), np.float32)
            for i, p in enumerate(bench.passages):
                self.table[i, p] = space.idf[p]
        else:  # sorted (passage, word) pairs
            self.pairs = np.concatenate([i * len(space.idf) + np.unique(p) for i, p in enumerate(bench.passages)])
        self.overlap = max(BLOCK * WIDE * 2, 2 * max(map(len, bench.items)) + BLOCK * WIDE)
        self.stretch = max(STRETCH, self.overlap)
        self._choose_anchors()

    def _runs(self, codes: np.ndarray) -> np.ndarray:
        """A number of every run of ANSWER words, equal for equal runs; only for runs of known words."""
        n = np.uint64(len(self.space.idf) + 1)
        key = codes[: len(codes) - ANSWER + 1].astype(np.uint64)
        for i in range(1, ANSWER):
            key = key * n + codes[i : len(codes) - ANSWER + 1 + i].astype(np.uint64)
        return key

    def _choose_anchors(self) -> None:
        """Of each half of each passage the run that the fewest passages hold, the rarest words first."""
        runs = [self._runs(p) for p in self.bench.passages]
        values, held = np.unique(np.concatenate([np.unique(r) for r in runs]), return_counts=True)
        key, passage = [], []
        for i, r in enumerate(runs):
            rarity = np.convolve(self.space.idf[self.bench.passages[i]], np.ones(ANSWER), "valid")
            shared = held[np.searchsorted(values, r)]
            order = np.lexsort((-rarity, shared))
            half = len(r) // 2
            for part in (order[order < half], order[order >= half]):
                if len(part):
                    key.append(r[part[0]])
                    passage.append(i)
        order = np.argsort(np.array(key), kind="stable")
        self.anchor, self.anchored = np.array(key)[order], np.array(passage)[order]

    def _exact(self, codes: list[np.ndarray]):
        """(document, first block, passage, cosine) of the windows that hold a passage's anchor."""
        apart = np.full(ANSWER, -1, np.int64)
        flat = np.concatenate([x for c in codes for x in (c, apart)])
        begin = np.cumsum([0, *(len(c) + ANSWER for c in codes)])
        known = flat >= 0
        for i in range(1, ANSWER):
            known[:-i] &= flat[i:] >= 0
        at = np.flatnonzero(known[: len(flat) - ANSWER + 1])
        run = self._runs(flat)[at]
        low, high = np.searchsorted(self.anchor, run), np.searchsorted(self.anchor, run, "right")
        hit = np.flatnonzero(high > low)
        n = (high - low)[hit]
        passage = self.anchored[np.repeat(low[hit] - np.cumsum(n) + n, n) + np.arange(int(n.sum()))]
        of = np.searchsorted(begin, at[hit], "right") - 1
        block = (at[hit] - begin[of]) // (BLOCK * WIDE) * WIDE
        found = np.unique(np.stack([np.repeat(of, n), np.repeat(block, n), passage]), axis=1).T.tolist()
        for d, b, p in found:
            near = codes[d][b * BLOCK : (b + WIDE) * BLOCK]
            vector, own = self.space.word[near[near >= 0]].sum(axis=0), self.space.passages[p]
            yield d, b, p, float(vector @ own / (np.linalg.norm(vector) * np.linalg.norm(own) + 1e-9))

    def _covered(self, passage: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """Whether a window's words hold enough of a passage's idf (repeats count, so none is missed)."""
        none = len(self.space.idf)
        if self.dense:
            got = self.table[passage[:, None], cells].sum(axis=1)
        else:
            key = passage[:, None] * none + cells
            at = np.minimum(np.searchsorted(self.pairs, key), len(self.pairs) - 1)
            idf = np.append(self.space.idf, 0.0)
            got = np.where((self.pairs[at] == key) & (cells < none), idf[cells], 0.0).sum(axis=1)
        return got >= COVER * self.worth[passage]

    def _windows(self, codes: list[np.ndarray]):
        """(document, first block, passage, cosine) of the candidates among the windows of some stretches."""
        word, passages = self.space.word, self.space.passages
        blocks = np.array([-(-len(c) // BLOCK) for c in codes])
        first = np.cumsum(blocks + WIDE - 1) - blocks - (WIDE - 1)
        total = int(first[-1] + blocks[-1] + WIDE - 1)
        cells = np.full((total + WIDE) * BLOCK, len(word), np.int64)  # a row of zeros stands for other words
        for c, f in zip(codes, first.tolist(), strict=True):
            cells[f * BLOCK : f * BLOCK + len(c)] = np.where(c < 0, len(word), c)
        cells = cells.reshape(-1, BLOCK)
        rows = np.concatenate([word, np.zeros((1, word.shape[1]), np.float32)])
        sums = rows[cells[:, 0]]
        for j in range(1, BLOCK):
            sums += rows[cells[:, j]]
        span = 1
        while span < WIDE:
            sums = sums[:-span] + sums[span:]
            span *= 2
        n = -(-blocks // STEP)
        of = np.repeat(np.arange(len(codes)), n)
        start = (np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)) * STEP
        windows = sums[first[of] + start]
        norm = np.sqrt(np.einsum("ij,ij->i", windows, windows)) + 1e-9
        size = np.sqrt(np.einsum("ij,ij->i", passages, passages)) + 1e-9
        along = windows @ (passages / size[:, None]).T.astype(np.float32)  # length of the window along each passage
        w, p = np.nonzero((along >= COSINE * norm[:, None]) & (along >= (HOLDS * size)[None, :]))
        cosine, at = along[w, p] / norm[w], first[of[w]] + start[w]
        keep = [np.zeros(0, np.int64)]
        for s in range(0, len(w), 100_000):
            e = s + 100_000
            near = cells[at[s:e, None] + np.arange(WIDE)].reshape(-1, WIDE * BLOCK)
            keep.append(s + np.flatnonzero(self._covered(p[s:e], near)))
        k = np.concatenate(keep)
        return of[w[k]].tolist(), start[w[k]].tolist(), p[k].tolist(), cosine[k].tolist()

    def _settle(self, code: np.ndarray, item: int, begin: int) -> tuple[float, bool, int]:
        """(share in common, whether the answer is there, first word looked at) near a window."""
        ids = self.bench.items[item]
        margin = len(ids)
        low, high = max(0, begin - margin), min(len(code), begin + BLOCK * WIDE + margin)
        near = code[low:high]
        idf, seen = self.space.idf, set(near.tolist())
        if idf[[i for i in ids.tolist() if i in seen]].sum() < RARE_SHARE * idf[ids].sum():
            return 0.0, False, low
        share = common_words(ids, near) / len(ids)
        answer = share >= SHARE_WITH_ANSWER and common_words(ids[-ANSWER:], near) == ANSWER
        return share, answer, low

    def leaks(self, texts: list[bytes | None]) -> list[list[tuple]]:
        """For each text: (item place, cosine, share, answer there, first word) of each item found."""
        out: list[list[tuple]] = [[] for _ in texts]
        if not self.bench.items:
            return out
        batch, owners, begins, size = [], [], [], 0

        def settle():
            nonlocal batch, owners, begins, size
            if not batch:
                return
            best: dict[tuple[int, int], tuple] = {}
            for local, start, p, cosine in chain(zip(*self._windows(batch), strict=True), self._exact(batch)):
                item = int(self.bench.owner[p])
                key = (owners[local], item)
                if best.get(key, (0, 0, 0.0))[2] >= 0.999:
                    continue
                share, answer, low = self._settle(batch[local], item, start * BLOCK)
                if (share >= SHARE or answer) and share > best.get(key, (0, 0, 0.0))[2]:
                    best[key] = (item, cosine, share, answer, begins[local] + low)
            for (d, item), found in best.items():
                same = [i for i, x in enumerate(out[d]) if x[0] == item]
                if not same:
                    out[d].append(found)
                elif out[d][same[0]][2] < found[2]:
                    out[d][same[0]] = found
            batch, owners, begins, size = [], [], [], 0

        for d, text in enumerate(texts):
            words = words_of(text)
            for s in range(0, len(words), self.stretch):
                lead = min(s, self.overlap)
                code = _codes(words[s - lead : s + self.stretch], self.bench.vocabulary)
                batch.append(code)
                owners.append(d)
                begins.append(s - lead)
                size += len(code)
                if size >= STRETCH * 2:
                    settle()
        settle()
        return out


def _retrievers(docs: DataFrame, benchmark: DataFrame) -> list[list]:
    """Broadcast retrievers of all blocks, by the pass that uses them."""
    n_docs = docs.count()
    shared = [docs.sparkSession.sparkContext.broadcast(Retriever(bench, fit(docs, bench, n_docs))) for bench in blocks_of(benchmark)]
    return [shared[s : s + PASS_BLOCKS] for s in range(0, len(shared), PASS_BLOCKS)] or [[]]


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, cosine, common, answer, near_word) of every item found in a document.

    Null, empty and wordless texts contain nothing; items of under four words, null texts among
    them, can't be found; an empty benchmark or table gives no rows. Repeated rows and items repeat.
    Only doc_id and text, and item_id and text of the benchmark, are read.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("cosine", pa.float64()), ("common", pa.float64()), ("answer", pa.bool_()), ("near_word", pa.int64())])

    def search(shared: list):
        def run(batches: Batches) -> Batches:
            for b in batches:
                ids, texts = b.column("doc_id").to_pylist(), raw(b, "text")
                for own in (x.value for x in shared):
                    rows = [(d, own.bench.names[i], *rest) for d, found in zip(ids, own.leaks(texts), strict=True) for i, *rest in sorted(found)]
                    if rows:
                        yield table(schema, *zip(*rows, strict=True))

        return run

    wanted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    parts = [wanted.mapInArrow(tidy(search(shared)), "doc_id long, item_id long, cosine double, common double, answer boolean, near_word long") for shared in _retrievers(docs, benchmark)]
    return reduce(DataFrame.unionAll, parts)


def drop_leaky(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs in which no item is found, whole; the same cases as find_leaks."""

    def keep(shared: list):
        def run(batches: Batches) -> Batches:
            for b in batches:
                for own in (x.value for x in shared):
                    b = b.filter(pa.array([not found for found in own.leaks(raw(b, "text"))], pa.bool_()))
                yield b

        return run

    first, *more = _retrievers(docs, benchmark)  # all fitted on the documents as they come
    kept = docs.mapInArrow(tidy(keep(first)), docs.schema)
    for shared in more:
        kept = cut(kept, "clean").mapInArrow(tidy(keep(shared)), docs.schema)
    return kept
