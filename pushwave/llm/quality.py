"""Quality classifier on supervised subword embeddings (operator 7).

A document's vector is the mean over its words plus the mean over its word pairs. A word's vector is
half the learned vector of its hashed whole and half the mean of those of its shape and its character
3- to 5-grams; a pair's is half that of its hashed words and half that of its kind, a word twice or two
words. A softmax over two classes reads the document's vector. Vectors and softmax are learned together by numpy stochastic gradient descent
on a bounded sample. At scoring a vector only matters through its product with the softmax, one
number, so each distinct word costs one look-up and each pair one hash.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pushwave.llm.common import Batches, crc_mod, fresh, raw, tidy
from pushwave.llm.subwords import Buffer, by_word, in_parts

#: Labelled documents the classifier is fitted on at most, and the longest text among them.
SAMPLE_DOCS, SAMPLE_CHARS = 3000, 12_000
#: Address bits of the character n-grams', the whole words' and the pairs' rows, which follow one another in one table.
GRAM_BITS, WORD_BITS, PAIR_BITS = 16, 18, 18
DIM, EPOCHS, BATCH, RATE = 8, 6, 16, 0.35
#: Words that a worker remembers at most, and bytes of text that are split into words at a time.
MOST, CHUNK = 150_000, 2 << 20

_SHAPE = bytes(0x41 if 0x41 <= b <= 0x5A else 0x61 if 0x61 <= b <= 0x7A else 0x30 if 0x30 <= b <= 0x39 else b if b < 0x80 else 0x61 for b in range(256))
_MIX = np.uint64(0x9E3779B97F4A7C15)
#: Row of the pairs of two words; the row of the pairs of a word with itself follows.
_KIND = (1 << GRAM_BITS) + (1 << WORD_BITS) + (1 << PAIR_BITS)
_ROWS = _KIND + 2


def _inner(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    spelled = Buffer(words)
    shaped = Buffer([w.translate(_SHAPE) for w in words])
    return by_word([shaped.whole(2, GRAM_BITS), *(spelled.grams(n, 2 + n, GRAM_BITS) for n in (3, 4, 5))], len(words))


def _whole(words: list[bytes]) -> np.ndarray:
    """A 62-bit number of each word; in parts, for a buffer's powers stay in memory."""
    return np.concatenate([Buffer(words[s : s + 20_000]).whole(1, 62)[1] for s in range(0, len(words), 20_000)])


def _word_rows(whole: np.ndarray) -> np.ndarray:
    return (1 << GRAM_BITS) + (whole >> (62 - WORD_BITS))


def _pair_rows(whole: np.ndarray) -> np.ndarray:
    """Row of each pair of neighbours in a sequence of words' numbers."""
    h = whole.astype(np.uint64)
    h = (h[:-1] * _MIX + h[1:]) * _MIX
    h = (h ^ (h >> np.uint64(31))) * _MIX
    return ((1 << GRAM_BITS) + (1 << WORD_BITS) + (h >> np.uint64(64 - PAIR_BITS))).astype(np.int64)


@dataclass
class QualityModel:
    """Per row of the table one number, and the bias."""

    number: np.ndarray
    bias: float
    prior: float
    cache: dict[bytes, int] = field(default_factory=dict)
    worth: np.ndarray = field(default_factory=lambda: np.zeros(0))
    whole: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))

    def __getstate__(self):
        return (self.number, self.bias, self.prior)

    def __setstate__(self, state):
        self.__init__(*state)

    def _learn(self, words: list[bytes]) -> None:
        inner, first = in_parts(_inner, words)
        whole = _whole(words)
        own = np.add.reduceat(self.number[inner].astype(np.float64), first) / np.diff(np.append(first, len(inner)))
        self.cache.update(zip(words, range(len(self.cache), len(self.cache) + len(words)), strict=True))
        self.worth = np.append(self.worth, (own + self.number[_word_rows(whole)]) / 2)
        self.whole = np.append(self.whole, whole)

    def _some(self, texts: list[bytes | None]) -> list[float]:
        split = [(t or b"").split() for t in texts]
        if len(self.cache) > MOST:
            self.cache, self.worth, self.whole = {}, np.zeros(0), np.zeros(0, np.int64)
        if new := [w for w in set().union(*split) if w not in self.cache]:
            self._learn(new)
        get, out = self.cache.__getitem__, []
        for words in split:
            if not words:
                out.append(self.prior)
                continue
            at = np.fromiter(map(get, words), np.int64, len(words))
            logit = float(self.worth[at].mean()) + self.bias
            if len(words) > 1:
                again = float(np.mean(at[1:] == at[:-1]))
                logit += float(self.number[_pair_rows(self.whole[at])].mean(dtype=np.float64)) / 2
                logit += float(self.number[_KIND] * (1 - again) + self.number[_KIND + 1] * again) / 2
            out.append(1 / (1 + np.exp(-max(-30.0, min(30.0, logit)))))
        return out

    def scores(self, texts: list[bytes | None]) -> list[float]:
        """Probability of label 1; texts without words have the training share of label 1."""
        out, part, size = [], [], 0
        for t in texts:
            part.append(t)
            size += len(t or b"")
            if size >= CHUNK:
                out += self._some(part)
                part, size = [], 0
        return out + self._some(part)


def train(texts: list[bytes | None], labels: list[int], seed: int = 7) -> QualityModel:
    """Fit by stochastic gradient descent with per-coordinate rates."""
    labels_ = np.asarray(labels, np.float64)
    prior = float(labels_.mean()) if len(labels_) else 0.5
    if not len(labels_) or prior in (0.0, 1.0):
        return QualityModel(np.zeros(_ROWS, np.float32), float(np.log((prior + 1e-3) / (1 - prior + 1e-3))), prior)
    vocab: dict[bytes, int] = {}
    sequences = [np.fromiter((vocab.setdefault(w, len(vocab)) for w in (t or b"").split()), np.int64) for t in texts]
    words = list(vocab)
    inner, first = in_parts(_inner, words)
    size = np.diff(np.append(first, len(inner)))
    whole = _whole(words)
    word_row = _word_rows(whole)
    rows, shares = [], []  # of each document: rows of the table and their share of its vector
    for sequence in sequences:
        ids, n = np.unique(sequence, return_counts=True)
        w, per = 0.5 * n / max(1, len(sequence)), size[ids]
        at = np.repeat(first[ids] - np.cumsum(per) + per, per) + np.arange(int(per.sum()))
        pairs = _pair_rows(whole[sequence])
        kinds = _KIND + (sequence[1:] == sequence[:-1])
        r = np.concatenate([inner[at], word_row[ids], pairs, kinds])
        s = np.concatenate([np.repeat(w / per, per), w, np.full(2 * len(pairs), 0.5 / max(1, len(pairs)))])
        u, back = np.unique(r, return_inverse=True)
        rows.append(u.astype(np.int32))
        shares.append(np.bincount(back, s, len(u)).astype(np.float32))
    del vocab, words, inner, sequences
    rng = np.random.default_rng(seed)
    table_ = rng.standard_normal((_ROWS, DIM), np.float32) * np.float32(0.1)
    seen = np.zeros(_ROWS, bool)
    for r in rows:
        seen[r] = True
    table_[~seen] = 0.0  # what the sample doesn't hold says nothing
    square = np.full(_ROWS, 1e-3, np.float32)
    out, bias = rng.normal(0, 0.5, DIM), float(np.log(prior / (1 - prior)))
    out_square, bias_square = np.full(DIM, 1e-2), 1e-2
    balance = np.where(labels_ == 1, 0.5 / prior, 0.5 / (1 - prior)) ** 0.5
    for epoch in range(EPOCHS):
        rate = RATE * (1 - epoch / EPOCHS) + 0.02
        for chunk in np.array_split(rng.permutation(len(rows)), max(1, len(rows) // BATCH)):
            chunk = [i for i in chunk.tolist() if len(rows[i])]
            if not chunk:
                continue
            vectors = np.stack([shares[i] @ table_[rows[i]] for i in chunk])
            slope = (1 / (1 + np.exp(-(vectors @ out + bias))) - labels_[chunk]) * balance[chunk]
            for i, g, v in zip(chunk, slope.tolist(), vectors, strict=True):
                step = (g * shares[i])[:, None] * out[None, :].astype(np.float32)
                square[rows[i]] += (step * step).mean(axis=1)
                table_[rows[i]] -= rate * step / np.sqrt(square[rows[i]])[:, None]
                g_out = g * v
                out_square += g_out * g_out
                out = out - rate * 0.3 * g_out / np.sqrt(out_square)
                bias_square += g * g
                bias -= rate * 0.1 * g / np.sqrt(bias_square)
    return QualityModel((table_ @ out).astype(np.float32), float(bias), prior)


def fit(docs: DataFrame, labels: DataFrame) -> QualityModel:
    """From labelled rows whose crc32(doc_id as text) mod 3 is not 1, at most SAMPLE_DOCS, in hash order."""
    marked = labels.filter(F.col("quality").isin(0, 1)).filter(crc_mod("doc_id", 3) != 1).groupBy(F.col("doc_id").alias("_id")).agg(F.min("quality").alias("quality"))
    chosen = marked.orderBy(F.xxhash64("_id"), "_id").limit(2 * SAMPLE_DOCS)  # bounded: ids and labels alone
    text = docs.select("doc_id", "text").filter(F.char_length("text").between(1, SAMPLE_CHARS))
    rows = text.join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).orderBy(F.xxhash64("_id"), "_id", "text").limit(SAMPLE_DOCS).select("text", "quality").collect()
    return train([r["text"].encode() for r in rows], [r["quality"] for r in rows])


def score(docs: DataFrame, model: QualityModel, column: str = "score") -> DataFrame:
    """docs with a column of probabilities; all rows and columns stay, null and empty texts included."""
    names = docs.columns
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Batches) -> Batches:
        own = shared.value
        for b in batches:
            got = own.scores(raw(b, "text"))
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in names), pa.array(got, pa.float64())], names=[*names, column])

    schema = T.StructType([*docs.schema.fields, T.StructField(column, T.DoubleType())])
    return docs.mapInArrow(tidy(run), schema)


def keep_good(docs: DataFrame, labels: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows of docs that score least or more, with their columns; the same cases as quality_scores."""
    (column,) = fresh(docs, "_score")
    return score(docs, fit(docs, labels), column).filter(F.col(column) >= least).drop(column)


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of docs.

    Without a usable label every score is the prior 0.5. Null, empty and blank texts get the
    training share of label 1. Null ids are never held out and never in training. Equal texts have
    equal scores. Other columns are never inputs.
    """
    scored = score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), fit(docs, labels))
    return scored.select("doc_id", F.coalesce(crc_mod("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))

