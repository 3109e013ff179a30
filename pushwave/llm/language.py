"""Language identification by a linear-chain conditional random field over words (operator 6).

Every word has affix, n-gram and lexicon features, hashed; their learned weights make its emission
scores, one a language. Learned transitions join neighbours, so a code-switched text gets its
languages word by word. Forward-backward runs on blocks of words of equal length side by side; a
document's language is the one with most posterior mass. Training sequences mix segments of
documents of different languages, so that transitions see switches.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pushwave.llm.common import Batches, crc_mod, raw
from pushwave.llm.subwords import Buffer, by_word, in_parts

#: Documents of known language that are fitted on at most, the least share of them that a language may
#: count on (as far as it has documents), and the longest text among them.
SAMPLE_DOCS, LANGUAGES, SAMPLE_CHARS = 1600, 64, 12_000
BITS, STEPS, SEQUENCES, LENGTH, RATE = 17, 500, 64, 32, 0.25
#: Words of a piece of a chain: pieces of all texts run side by side, and what lies before and after a
#: piece reaches it as a vector, so a text is one chain whatever its length.
CHAIN = 64
MOST = 300_000
UNDETERMINED = "und"
_ASCII_LETTER = re.compile(rb"[A-Za-z]")


def has_letter(text: bytes | None) -> bool:
    if not text:
        return False
    return bool(_ASCII_LETTER.search(text)) or any(map(str.isalpha, text.decode("utf-8", "replace")))


def _features(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Lexicon entry, affixes of 1 to 3 bytes, and bigrams to 4-grams of the lower-cased words."""
    b = Buffer(words)
    return by_word([b.whole(1, BITS), *(b.affixes(n, 2 * n, BITS) for n in (1, 2, 3)), *(b.grams(n, 10 + n, BITS) for n in (2, 3, 4))], len(words))


def _sums(weights: np.ndarray, bucket: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Mean of the feature weights of each word, scaled so that long words don't outshout others."""
    size = np.diff(np.append(first, len(bucket)))
    return np.add.reduceat(weights[bucket], first, axis=0) / np.sqrt(size)[:, None]


def forward_backward(emission: np.ndarray, transition: np.ndarray, start: np.ndarray, valid: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Posteriors of [sequence, time, label], expected transitions, and expected first labels.

    emission: scores of [sequence, time, label]; valid: number of real words of each sequence;
    posteriors beyond it are zero.
    """
    n, length, k = emission.shape
    e = np.exp(emission - emission.max(axis=2, keepdims=True))
    t, s = np.exp(transition), np.exp(start)
    live = np.arange(length)[None, :] < valid[:, None]
    e[~live] = 1.0
    alpha, beta = np.empty_like(e), np.empty_like(e)
    alpha[:, 0] = s * e[:, 0]
    alpha[:, 0] /= alpha[:, 0].sum(axis=1, keepdims=True)
    for i in range(1, length):
        a = (alpha[:, i - 1] @ t) * e[:, i]
        alpha[:, i] = a / a.sum(axis=1, keepdims=True)
    beta[:, -1] = 1.0
    for i in range(length - 2, -1, -1):
        b = (e[:, i + 1] * beta[:, i + 1]) @ t.T
        b[~live[:, i + 1]] = 1.0
        beta[:, i] = b / b.sum(axis=1, keepdims=True)
    post = alpha * beta
    post /= post.sum(axis=2, keepdims=True)
    post[~live] = 0.0
    pair = np.zeros((k, k))
    if length > 1:
        both = alpha[:, :-1, :, None] * t[None, None] * (e[:, 1:] * beta[:, 1:])[:, :, None, :]
        both /= both.sum(axis=(2, 3), keepdims=True)
        pair = both[live[:, 1:]].sum(axis=0)
    return post, pair, post[:, 0].sum(axis=0)


def _through(e: np.ndarray, move: np.ndarray, live: np.ndarray) -> np.ndarray:
    """[piece, from, to]: the product of a piece's transitions and emissions, scaled.

    e: exponentials of the emissions [time, piece, label]; times beyond a piece's words change nothing.
    """
    length, n, k = e.shape
    out = np.broadcast_to(np.eye(k, dtype=np.float32), (n, k, k)).copy()
    for i in range(length):
        step = (out @ move) * e[i][:, None, :]
        step *= 1 / step.max(axis=(1, 2), keepdims=True)
        out = np.where(live[i][:, None, None], step, out)
    return out


def _carry(e: np.ndarray, move: np.ndarray, start: np.ndarray, live: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(forward vector at the end of the piece before, backward vector at the end of the piece itself) of every
    piece; the pieces of a text follow each other. One step serves the i-th pieces of all texts."""
    n, k = e.shape[1:]
    first = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]]))
    size = np.diff(first, append=n)
    enter, behind = np.ones((n, k), np.float32), np.ones((n, k), np.float32)
    long = first[size > 1]
    if not len(long):
        return enter, behind
    a = start * e[0, long]
    for i in range(1, len(e)):
        a = (a @ move) * e[i, long]
        a *= 1 / a.sum(axis=1, keepdims=True)
    enter[long + 1] = a
    later = np.repeat(size > 1, size)
    later[first] = False
    later = np.flatnonzero(later)
    through = np.empty((n, k, k), np.float32)
    through[later] = _through(e[:, later], move, live[:, later])
    for i in range(2, int(size.max())):
        at = first[size > i] + i
        v = np.einsum("nk,nkj->nj", enter[at - 1], through[at - 1])
        enter[at] = v / v.sum(axis=1, keepdims=True)
    for i in range(1, int(size.max())):
        at = (first + size)[size > i] - 1 - i
        v = np.einsum("nkj,nj->nk", through[at + 1], behind[at + 1])
        behind[at] = v / v.sum(axis=1, keepdims=True)
    return enter, behind


def posteriors(emission: np.ndarray, transition: np.ndarray, start: np.ndarray, valid: np.ndarray, text: np.ndarray | None = None) -> np.ndarray:
    """Posteriors alone, in single precision, time first: [time, piece, label].

    text: the text of each piece, ascending; all pieces of a text but its last are full. Without it every
    piece is a text of its own.
    """
    length, n, k = emission.shape
    text = np.arange(n) if text is None else text
    e = np.exp(emission - emission.max(axis=2, keepdims=True))
    t, s = np.exp(transition).astype(np.float32), np.exp(start).astype(np.float32)
    live = np.arange(length)[:, None] < valid[None, :]
    enter, behind = _carry(e, t, s, live, text)
    opens = np.concatenate([[True], text[1:] != text[:-1]])
    alpha = np.empty_like(e)
    a = np.where(opens[:, None], s[None, :], enter @ t) * e[0]
    alpha[0] = a = a / a.sum(axis=1, keepdims=True)
    for i in range(1, length):
        a = (a @ t) * e[i]
        a *= 1 / a.sum(axis=1, keepdims=True)
        alpha[i] = a
    b = behind
    for i in range(length - 1, -1, -1):
        if i < length - 1:
            back = (e[i + 1] * b) @ t.T
            back *= 1 / back.sum(axis=1, keepdims=True)
            b = np.where(live[i + 1][:, None], back, behind)
        alpha[i] *= b
    alpha /= alpha.sum(axis=2, keepdims=True)
    return alpha


@dataclass
class LanguageModel:
    languages: list[str]
    weights: np.ndarray
    transition: np.ndarray
    start: np.ndarray
    cache: dict[bytes, int] = field(default_factory=dict)
    scores: list = field(default_factory=list)

    def __getstate__(self):
        return (self.languages, self.weights, self.transition, self.start)

    def __setstate__(self, state):
        self.__init__(*state)

    def _codes(self, split: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray]:
        if len(self.cache) > MOST:
            self.cache, self.scores = {}, []
        cache = self.cache
        new = [w for w in set().union(*split) if w not in cache]
        for s in range(0, len(new), 50_000):
            part = new[s : s + 50_000]
            self.scores.append(_sums(self.weights, *_features(part)).astype(np.float32))
            for w in part:
                cache[w] = len(cache)
        if len(self.scores) > 1:
            self.scores = [np.concatenate(self.scores)]
        get = cache.__getitem__
        return np.fromiter((get(w) for words in split for w in words), np.int64, sum(map(len, split))), self.scores[0]

    def word_posteriors(self, texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
        """(posterior of every word, first word of each text and the number of all)."""
        split = [(t or b"").lower().split() for t in texts]
        sizes = np.fromiter(map(len, split), np.int64, len(split))
        border = np.concatenate([[0], np.cumsum(sizes)])
        k = len(self.languages)
        if not border[-1]:
            return np.zeros((0, k), np.float32), border
        codes, scores = self._codes(split)
        chains = -(-sizes // CHAIN)
        chain_text = np.repeat(np.arange(len(split)), chains)
        within = np.arange(len(chain_text)) - np.repeat(np.cumsum(chains) - chains, chains)
        at = border[chain_text] + within * CHAIN
        valid = np.minimum(CHAIN, border[chain_text + 1] - at)
        out = np.empty((border[-1], k), np.float32)
        place = at[None, :] + np.arange(CHAIN)[:, None]
        live = np.arange(CHAIN)[:, None] < valid[None, :]
        emission = np.where(live[:, :, None], scores[codes[np.minimum(place, border[-1] - 1)]], np.float32(0))
        post = posteriors(emission, self.transition, self.start, valid, chain_text)
        out[place[live]] = post[live]
        return out, border

    def predict(self, texts: list[bytes | None]) -> list[tuple[str, float]]:
        """(language, its share of the posterior mass); und and 0 for a text without a letter."""
        out: list[tuple[str, float]] = []
        s = 0
        while s < len(texts):  # by about 2 MB of text, for bounded memory
            e, size = s, 0
            while e < len(texts) and (e == s or size < 2_000_000):
                size += len(texts[e] or b"")
                e += 1
            part = texts[s:e]
            post, border = self.word_posteriors(part) if self.languages else (None, None)
            for i, text in enumerate(part):
                if not self.languages or not has_letter(text):
                    out.append((UNDETERMINED, 0.0))
                    continue
                mass = post[border[i] : border[i + 1]].sum(axis=0, dtype=np.float64)
                best = int(mass.argmax())
                out.append((self.languages[best], float(min(1.0, mass[best] / mass.sum()))))
            s = e
        return out


def train(texts: list[bytes], langs: list[str], seed: int = 11) -> LanguageModel:
    """Gradient ascent on the conditional likelihood of mixed-language sequences."""
    names = sorted(set(langs))
    k = len(names)
    streams: list[list[int]] = [[] for _ in names]
    vocab: dict[bytes, int] = {}
    for text, lang in zip(texts, langs, strict=True):
        streams[names.index(lang)] += [vocab.setdefault(w, len(vocab)) for w in text.lower().split()]
    filled = [i for i in range(k) if streams[i]]
    weights, transition, start = np.zeros((2**BITS, k)), np.zeros((k, k)), np.zeros(k)
    if not filled:
        return LanguageModel(names, weights.astype(np.float32), transition, start)
    flat = [np.asarray(s, np.int64) for s in streams]
    bucket, first = in_parts(_features, list(vocab))
    size = np.diff(np.append(first, len(bucket)))
    rng = np.random.default_rng(seed)
    square, t_square, s_square = np.full(2**BITS, 1e-2), np.full((k, k), 1.0), np.full(k, 1.0)
    valid = np.full(SEQUENCES, LENGTH)
    for step in range(STEPS):
        words, labels = np.empty((SEQUENCES, LENGTH), np.int64), np.empty((SEQUENCES, LENGTH), np.int64)
        for row in range(SEQUENCES):  # two or three segments, mostly of different languages
            cuts = [0, *sorted(rng.integers(1, LENGTH, rng.integers(0, 3)).tolist()), LENGTH]
            for a, b in zip(cuts, cuts[1:], strict=False):
                lang = filled[rng.integers(len(filled))]
                at = int(rng.integers(len(flat[lang])))
                words[row, a:b] = flat[lang].take(np.arange(at, at + b - a), mode="wrap")
                labels[row, a:b] = lang
        used, back = np.unique(words, return_inverse=True)
        per = size[used]
        place = np.repeat(first[used] - np.cumsum(per) + per, per) + np.arange(int(per.sum()))
        own = bucket[place]
        begin = np.cumsum(per) - per
        scores = np.add.reduceat(weights[own], begin, axis=0) / np.sqrt(per)[:, None]
        post, pair, head = forward_backward(scores[back.reshape(words.shape)], transition, start, valid)
        gap = -post
        np.put_along_axis(gap, labels[:, :, None], np.take_along_axis(gap, labels[:, :, None], 2) + 1, 2)
        of_word = np.stack([np.bincount(back.ravel(), gap[:, :, j].ravel(), len(used)) for j in range(k)], axis=1)
        spread = np.repeat(of_word / np.sqrt(per)[:, None], per, axis=0)
        rows, inverse = np.unique(own, return_inverse=True)
        gradient = np.stack([np.bincount(inverse, spread[:, j], len(rows)) for j in range(k)], axis=1) / SEQUENCES
        square[rows] += (gradient * gradient).mean(axis=1)
        weights[rows] += RATE * (gradient / np.sqrt(square[rows])[:, None] - 1e-3 * weights[rows])
        seen = np.zeros((k, k))
        np.add.at(seen, (labels[:, :-1].ravel(), labels[:, 1:].ravel()), 1)
        move = (seen - pair) / SEQUENCES
        t_square += move * move
        transition += RATE * move / np.sqrt(t_square)
        push = (np.bincount(labels[:, 0], minlength=k) - head) / SEQUENCES
        s_square += push * push
        start += RATE * push / np.sqrt(s_square)
    return LanguageModel(names, weights.astype(np.float32), transition, start)


def fit(docs: DataFrame) -> LanguageModel:
    """From rows with text and lang whose crc32(doc_id as text) mod 4 is not 2.

    At most SAMPLE_DOCS, in hash order, of which every language (the LANGUAGES most frequent ones) gets an
    equal share as far as it has documents. Ids are chosen first; texts of chosen ids alone reach the driver.
    """
    rows = docs.select("doc_id", "text", "lang").filter("text is not null and lang is not null").filter(F.coalesce(crc_mod("doc_id", 4) != 2, F.lit(False))).filter(F.char_length("text").between(1, SAMPLE_CHARS))
    order = [F.xxhash64("doc_id", F.lit(3)), F.col("doc_id"), F.xxhash64("text")]
    ids = rows.select("doc_id", "lang", F.xxhash64("text").alias("tid"), F.row_number().over(Window.partitionBy("lang").orderBy(*order)).alias("turn")).filter(F.col("turn") <= SAMPLE_DOCS)
    langs = rows.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(LANGUAGES).select(F.col("lang").alias("_lang"))
    chosen = ids.join(F.broadcast(langs), F.col("lang") == F.col("_lang")).orderBy("turn", "lang").limit(SAMPLE_DOCS).select(F.col("doc_id").alias("_id"), F.col("tid").alias("_tid"), F.col("lang").alias("_own")).distinct().collect()
    if not chosen:
        return train([], [])
    few = docs.sparkSession.createDataFrame(chosen, "_id long, _tid long, _own string")  # SAMPLE_DOCS rows
    picked = rows.join(F.broadcast(few), (F.col("doc_id") == F.col("_id")) & (F.xxhash64("text") == F.col("_tid")) & (F.col("lang") == F.col("_own"))).groupBy("doc_id", "lang").agg(F.min("text").alias("text")).collect()
    picked.sort(key=lambda r: (r["doc_id"], r["lang"], r["text"]))
    return train([r["text"].encode() for r in picked], [r["lang"] for r in picked])


def predict(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """docs with lang_pred and score; all rows and columns stay."""
    names = docs.columns
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Batches) -> Batches:
        own = shared.value
        for b in batches:
            got = own.predict(raw(b, "text"))
            more = [pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in names), *more], names=[*names, "lang_pred", "score"])

    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return docs.mapInArrow(run, schema)


def language_predictions(docs: DataFrame) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every row of docs (doc_id, text, lang).

    Null texts and texts without a letter, and every text where there is nothing to learn from,
    get und and 0. Null ids are neither held out nor learned from. Equal texts get equal results.
    lang, source and doc_id are never inputs of a prediction. Empty tables give empty tables.
    """
    guessed = predict(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), fit(docs))
    return guessed.select("doc_id", F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")
