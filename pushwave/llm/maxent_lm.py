"""Hashed maximum-entropy language model (operator 8).

Every word is in a class: the most frequent training words (the end mark among them) in classes of
equal size by frequency, all others in classes by a hash of their ending. P(word | history) =
P(class | history) * P(word | class, history). The first factor, and the second inside a class of
frequent words, are softmaxes over summed rows of hashed weight tables: previous word, the word before
it (skip), and the pair for the class; class with previous word for the word. Inside a class by
ending, a word has its share of the class's training tokens, less a discount. What the discounts free
is the probability of words never seen in training; it is spread over all strings that are not
training words by a byte-pair model of the words seen once. So the probabilities of all words, seen or
not, sum to one after every history.

Counts cover every training document. Weights come from gradient steps that all tasks take from
the same start on all positions of all training documents; rows are averaged by how often a task
touched them, so they depend a little on how files are split into tasks. Scoring works on arrays of
a few thousand positions. Counts of the most frequent words travel as a broadcast of a fixed number
of entries; the other words of a document are joined to the count table.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import chain, compress, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.llm.common import Batches, crc_mod, raw, table
from pushwave.plans.durable import cut

#: Classes of frequent words and words in each; classes of the other words by their ending.
CLASSES, SLOTS, ENDINGS = 24, 64, 16
VOCABULARY, ALL = CLASSES * SLOTS, CLASSES + ENDINGS
CLASS_ROWS, WORD_ROWS = 2**15, 2**14
#: Words whose counts are broadcast at most.
HEAD = 131_072
#: Rate of a gradient step, and positions that take one together.
RATE, CHUNK = 0.35, 8192
#: Words a task counts before it hands them on.
FLUSH = 200_000
END = b""
LOG10 = float(np.log(10))


def tokens(text: bytes | None) -> list[bytes]:
    """Words between blanks, A-Z lower-cased, then the end mark (an empty string)."""
    out = (text or b"").lower().split()
    out.append(END)
    return out


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, c, c_all): occurrences in training documents and in all; docs: text, learn."""

    def count(batches: Batches) -> Batches:
        schema = pa.schema([("word", pa.binary()), ("c", pa.int64()), ("c_all", pa.int64())])
        sums: list[Counter] = [Counter(), Counter()]

        def flush():
            learned, rest = sums
            words = list(learned.keys() | rest.keys())
            out = table(schema, words, [learned[w] for w in words], [learned[w] + rest[w] for w in words])
            learned.clear()
            rest.clear()
            return out

        for b in batches:
            for text, learn in zip(raw(b, "text"), b.column("learn").to_pylist(), strict=True):
                sums[not learn].update(tokens(text))
                if len(sums[0]) + len(sums[1]) > FLUSH:
                    yield flush()
        if sums[0] or sums[1]:
            yield flush()

    parts = docs.select("text", "learn").mapInArrow(count, "word binary, c long, c_all long")
    return parts.groupBy("word").agg(F.sum("c").alias("c"), F.sum("c_all").alias("c_all"))


#: Spreads the values of two bytes over the classes by ending.
SPREAD = 40503


def ending_column(word: str):
    """Class of a word by its last two bytes, from 0, as ending_classes has it."""
    value = F.coalesce(F.conv(F.hex(F.substring(word, -2, 2)), 16, 10).cast("long"), F.lit(0))
    return (F.floor(value * SPREAD / 256).cast("long") % ENDINGS).cast("int")


def _bounds(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(all bytes, end of each word)."""
    return np.frombuffer(b"".join(words), np.uint8), np.cumsum(np.fromiter(map(len, words), np.int64, len(words)))


def ending_classes(words: list[bytes]) -> np.ndarray:
    flat, end = _bounds(words)
    size = np.diff(end, prepend=0)
    value = np.zeros(len(words), np.int64)
    value[size > 0] = flat[end[size > 0] - 1]
    value[size > 1] += 256 * flat[end[size > 1] - 2].astype(np.int64)
    return value * SPREAD // 256 % ENDINGS


@dataclass(frozen=True)
class Spelling:
    """log10 of a byte after another; 256 stands for the begin of a word as the first and the end as the
    second. A distribution over all words: no blanks, no A-Z, not empty."""

    table: np.ndarray

    @classmethod
    def of(cls, pairs: np.ndarray) -> Spelling:
        """From counts of byte pairs [257, 257]."""
        p = pairs + 0.01
        p[:, [*range(9, 14), 32, *range(65, 91)]] = 0
        p[256, 256] = 0
        with np.errstate(divide="ignore"):
            return cls(np.log10(p / p.sum(axis=1, keepdims=True)))

    def log10(self, words: list[bytes]) -> np.ndarray:
        """Of words that are not empty."""
        if not words:
            return np.zeros(0)
        first, second, start = byte_pairs(words)
        return np.add.reduceat(self.table[first, second], start)


def byte_pairs(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first, second, first pair of each word) of words that are not empty, borders included."""
    flat, end = _bounds(words)
    size = np.diff(end, prepend=0)
    start = np.cumsum(size + 1) - size - 1
    first, second = np.full(len(flat) + len(words), 256), np.full(len(flat) + len(words), 256)
    inner = np.ones(len(first), bool)
    inner[start + size] = False
    second[inner] = flat
    inner[:] = True
    inner[start] = False
    first[inner] = flat
    return first, second, start


@dataclass(frozen=True)
class Lexicon:
    """What the count table says: totals, and the words whose counts are broadcast."""

    total: int  # N
    kinds: int  # V
    head: dict[bytes, int]
    counts: np.ndarray  # training count of each head word
    word_id: np.ndarray  # vocabulary id of each head word; beyond it: VOCABULARY plus the class by ending
    frequency: np.ndarray  # training count of each vocabulary id
    class_tokens: np.ndarray  # training tokens of each class by ending
    class_kinds: np.ndarray  # training words of each class by ending
    discount: float
    spelling: Spelling
    spelled: float  # what the spelling gives to training words, all together

    def base_log10(self, c):
        return np.log10((np.asarray(c) + 0.5) / (self.total + 0.5 * (self.kinds + 1)))

    def share_log10(self, c, ending):
        """log10 of a training word's part of its class by ending; c > 0."""
        return np.log10(np.maximum(c, 1) - self.discount) - np.log10(np.maximum(1, self.class_tokens[ending]))

    def freed(self) -> np.ndarray:
        """Part of each class by ending that words never seen share; all of it where the class has none."""
        return np.where(self.class_tokens > 0, self.discount * self.class_kinds / np.maximum(1, self.class_tokens), 1.0)

    def new_log10(self, words: list[bytes]) -> np.ndarray:
        """log10 of a word never seen, among all words never seen."""
        return self.spelling.log10(words) - np.log10(max(1e-12, 1 - self.spelled))


def _spelling(counts: DataFrame) -> tuple[Spelling, float]:
    """The byte pairs of the words seen once (all training words if there are none), and their sum over all training words."""

    def pairs(batches: Batches) -> Batches:
        sums = np.zeros(257 * 257, np.int64)
        for b in batches:
            words = [w for w in b.column("word").to_pylist() if w]
            first, second, _ = byte_pairs(words)
            sums += np.bincount(first * 257 + second, minlength=len(sums))
        used = np.flatnonzero(sums)
        yield table(pa.schema([("pair", pa.int32()), ("n", pa.int64())]), used, sums[used])

    table_ = np.zeros(257 * 257)
    for some in ("c = 1", "c > 0"):
        for r in counts.filter(some).select("word").mapInArrow(pairs, "pair int, n long").groupBy("pair").agg(F.sum("n").alias("n")).collect():  # 257 * 257 rows at most
            table_[r["pair"]] = r["n"]
        if table_.any():
            break
    spelling = Spelling.of(table_.reshape(257, 257))

    def mass(batches: Batches) -> Batches:
        total = 0.0
        for b in batches:
            total += float((10 ** spelling.log10([w for w in b.column("word").to_pylist() if w])).sum())
        yield table(pa.schema([("mass", pa.float64())]), [total])

    return spelling, float(counts.filter("c > 0").select("word").mapInArrow(mass, "mass double").agg(F.sum("mass")).first()[0] or 0.0)


def lexicon(counts: DataFrame) -> Lexicon:
    octave = F.floor(F.log2("c_all") * 16).cast("int")
    steps = counts.groupBy(octave.alias("o"), ending_column("word").alias("e")).agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("c"), F.sum((F.col("c") > 0).cast("long")).alias("v"), F.sum((F.col("c") == 1).cast("long")).alias("n1"), F.sum((F.col("c") == 2).cast("long")).alias("n2")).orderBy(F.desc("o")).collect()  # under 1000 octaves of counts
    sizes: dict[int, int] = {}
    for r in steps:
        sizes[r["o"]] = sizes.get(r["o"], 0) + r["n"]
    taken, least = 0, 10**9
    for o, n in sizes.items():
        if taken + n > HEAD:
            break
        taken, least = taken + n, o
    rows = counts.filter((octave >= F.lit(least)) | (F.col("word") == F.lit(END))).collect()  # HEAD and the end mark at most
    rows.sort(key=lambda r: (-r["c"], bytes(r["word"]) != END, r["word"]))
    names = [bytes(r["word"]) for r in rows]
    c = np.array([r["c"] for r in rows], np.int64)
    known = int((c[:VOCABULARY] > 0).sum()) or min(1, len(rows))  # the end mark, where nothing is learned from
    word_id = VOCABULARY + ending_classes(names)
    tokens_, kinds_ = np.zeros(ENDINGS, np.int64), np.zeros(ENDINGS, np.int64)
    for r in steps:
        tokens_[r["e"]] += r["c"]
        kinds_[r["e"]] += r["v"]
    np.subtract.at(tokens_, word_id[:known] - VOCABULARY, c[:known])
    np.subtract.at(kinds_, word_id[:known] - VOCABULARY, (c[:known] > 0).astype(np.int64))
    word_id[:known] = np.arange(known)
    frequency = np.zeros(VOCABULARY, np.int64)
    frequency[:known] = np.maximum(1, c[:known])
    total, kinds = sum(r["c"] for r in steps), sum(r["v"] for r in steps)
    n1, n2 = sum(r["n1"] for r in steps), sum(r["n2"] for r in steps)
    discount = min(0.9, max(0.1, n1 / (n1 + 2 * n2))) if n1 + n2 else 0.5
    return Lexicon(total, kinds, {w: i for i, w in enumerate(names)}, c, word_id, frequency, tokens_, kinds_, discount, *_spelling(counts))


@dataclass
class Weights:
    """Rows of hashed features for the class and for the word inside it, and their biases."""

    class_rows: np.ndarray
    word_rows: np.ndarray
    class_bias: np.ndarray
    word_bias: np.ndarray


def begin(words: Lexicon) -> Weights:
    """No features yet: biases from the counts, so the start is the unigram model."""
    f = words.frequency.reshape(CLASSES, SLOTS).astype(np.float64)
    per_class = np.append(f.sum(axis=1), words.class_tokens) + 0.5
    word_bias = np.where(f > 0, np.log(f + 0.5), -np.inf)
    word_bias[~np.isfinite(word_bias).any(axis=1)] = 0.0
    return Weights(np.zeros((CLASS_ROWS, ALL), np.float32), np.zeros((WORD_ROWS, SLOTS), np.float32), np.log(per_class).astype(np.float32), word_bias.astype(np.float32))


def classes_of(ids: np.ndarray) -> np.ndarray:
    return np.where(ids < VOCABULARY, ids // SLOTS, ids - VOCABULARY + CLASSES)


def _mix(*parts: np.ndarray, rows: int) -> np.ndarray:
    h = np.zeros(len(parts[-1]), np.uint64)
    for p in parts:
        h = (h ^ np.asarray(p, np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return (h % np.uint64(rows)).astype(np.int64)


def _class_features(w1: np.ndarray, w2: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    one = np.uint64(1)
    return _mix(one, w1, rows=CLASS_ROWS), _mix(one + one, w2, rows=CLASS_ROWS), _mix(one + one + one, w1, w2, rows=CLASS_ROWS)


class Coder:
    """Documents to arrays of vocabulary ids and head places."""

    def __init__(self, words: Lexicon):
        self.words = words
        self.word_id = np.append(words.word_id, VOCABULARY)  # place -1: not in the head, by ending below

    def encode(self, texts: list[bytes | None]):
        """Head place of every token, its id, previous id, the one before; sizes and first tokens of the
        texts; places of the tokens that are not in the head, and those words."""
        split = [tokens(t) for t in texts]
        sizes = np.fromiter(map(len, split), np.int64, len(split))
        get = self.words.head.get
        place = np.fromiter((p for t in split for p in map(get, t, repeat(-1))), np.int64, int(sizes.sum()))
        ids = self.word_id[place]
        far = np.flatnonzero(place < 0)
        words = list(compress(chain.from_iterable(split), (place < 0).tolist()))
        ids[far] += ending_classes(words)
        first = np.cumsum(sizes) - sizes
        w1 = np.empty_like(ids)
        w1[1:] = ids[:-1]
        w1[first] = VOCABULARY + ENDINGS
        w2 = np.empty_like(ids)
        w2[1:] = w1[:-1]
        w2[first] = VOCABULARY + ENDINGS + 1
        return place, ids, w1, w2, sizes, first, far, words


def _parts(texts: list, most: int = 1_500_000):
    """Runs of texts of bounded size."""
    s = 0
    while s < len(texts):
        e, size = s, 0
        while e < len(texts) and (e == s or size < most):
            size += len(texts[e] or b"")
            e += 1
        yield s, e
        s = e


class Trainer:
    """Gradient steps on copies of the weights; remembers how often each row was touched."""

    def __init__(self, start: Weights):
        self.w = Weights(start.class_rows.copy(), start.word_rows.copy(), start.class_bias, start.word_bias)
        self.class_seen, self.word_seen = np.zeros(CLASS_ROWS), np.zeros(WORD_ROWS)
        self.class_square, self.word_square = np.full(CLASS_ROWS, 1.0), np.full(WORD_ROWS, 1.0)

    @staticmethod
    def _apply(rows, seen, square, at, gradient):
        """Of rows at, several runs as long as gradient, each with all of it."""
        order = np.argsort(at.astype(np.uint16), kind="stable")  # numbers of 16 bits are sorted by their digits
        at = at[order]
        first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        used, n = at[first], np.diff(first, append=len(at))
        step = np.add.reduceat(gradient[order % len(gradient)], first, axis=0)
        square[used] += (step * step).sum(axis=1)
        seen[used] += n
        step *= (RATE / np.sqrt(square[used]))[:, None].astype(np.float32)
        rows[used] -= step

    @staticmethod
    def _probabilities(logits: np.ndarray) -> np.ndarray:
        """The softmax of rows, in their place."""
        logits -= logits.max(axis=1, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(axis=1, keepdims=True)
        return logits

    def learn(self, ids, w1, w2) -> None:
        for s in range(0, len(ids), CHUNK):
            i, a, b = ids[s : s + CHUNK], w1[s : s + CHUNK], w2[s : s + CHUNK]
            f = _class_features(a, b)
            cls = classes_of(i)
            logits = self.w.class_rows[f[0]]
            logits += self.w.class_bias
            logits += self.w.class_rows[f[1]]
            logits += self.w.class_rows[f[2]]
            p = self._probabilities(logits)
            p[np.arange(len(i)), cls] -= 1
            self._apply(self.w.class_rows, self.class_seen, self.class_square, np.concatenate(f), p)
            inside = np.flatnonzero(i < VOCABULARY)
            if len(inside):
                c, slot = cls[inside], i[inside] % SLOTS
                g = _mix(c, a[inside], rows=WORD_ROWS)
                logits = self.w.word_rows[g]
                logits += self.w.word_bias[c]
                p = self._probabilities(logits)
                p[np.arange(len(c)), slot] -= 1
                self._apply(self.w.word_rows, self.word_seen, self.word_square, g, p)


def train(docs: DataFrame, words: Lexicon) -> Weights:
    """One round over all training documents; docs: doc_id, text of those alone."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(words)

    def learn(batches: Batches) -> Batches:
        schema = pa.schema([("row", pa.int32()), ("n", pa.float64()), ("step", pa.binary())])
        start = begin(shared.value)
        own, coder, any_ = Trainer(start), Coder(shared.value), False
        for b in batches:
            texts = raw(b, "text")
            for s, e in _parts(texts):
                _, ids, w1, w2, *_ = coder.encode(texts[s:e])
                own.learn(ids, w1, w2)
                any_ = True
        if any_:
            for offset, rows, seen in ((0, own.w.class_rows, own.class_seen), (CLASS_ROWS, own.w.word_rows, own.word_seen)):
                used = np.flatnonzero(seen)
                for s in range(0, len(used), 4096):
                    part = used[s : s + 4096]
                    yield table(schema, part + offset, seen[part], [(rows[r] * np.float32(seen[r])).astype(np.float32).tobytes() for r in part])

    def merge(batches: Batches) -> Batches:
        """Sums of sorted runs of rows, in constant memory."""
        schema = pa.schema([("row", pa.int32()), ("step", pa.binary())])
        row, total, n = None, None, 0.0
        for b in batches:
            done = []
            for r, m, step in zip(b.column("row").to_pylist(), b.column("n").to_pylist(), b.column("step").to_pylist(), strict=True):
                vector = np.frombuffer(step, np.float32)
                if r != row:
                    if row is not None:
                        done.append((row, (total / n).astype(np.float32).tobytes()))
                    row, total, n = r, np.zeros(len(vector)), 0.0
                total += vector
                n += m
            if done:
                yield table(schema, *zip(*done, strict=True))
        if row is not None:
            yield table(schema, [row], [(total / n).astype(np.float32).tobytes()])

    steps = docs.select("text").mapInArrow(learn, "row int, n double, step binary")
    merged = steps.repartition("row").sortWithinPartitions("row").mapInArrow(merge, "row int, step binary").collect()  # one vector a row of the tables
    out = begin(words)
    for r in merged:
        vector = np.frombuffer(r["step"], np.float32)
        if r["row"] < CLASS_ROWS:
            out.class_rows[r["row"]] = vector
        else:
            out.word_rows[r["row"] - CLASS_ROWS] = vector
    return out


def log10_probabilities(w: Weights, freed: np.ndarray, ids: np.ndarray, w1: np.ndarray, w2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(log10 P(id | history), log10 P(a word never seen | history)); beyond the vocabulary the first is of the class alone."""
    out, new = np.empty(len(ids), np.float32), np.empty(len(ids), np.float32)
    freed = freed.astype(np.float32)
    for s in range(0, len(ids), CHUNK):
        i, a, b = ids[s : s + CHUNK], w1[s : s + CHUNK], w2[s : s + CHUNK]
        cls = classes_of(i)
        f = _class_features(a, b)
        logits = w.class_rows[f[0]]
        logits += w.class_rows[f[1]]
        logits += w.class_rows[f[2]]
        logits += w.class_bias
        at = logits[np.arange(len(i)), cls]
        np.exp(logits, out=logits)
        norm = np.log(logits.sum(axis=1))
        got = at - norm
        new[s : s + CHUNK] = np.log(logits[:, CLASSES:] @ freed + 1e-30) - norm
        inside = np.flatnonzero(i < VOCABULARY)
        if len(inside):
            c = cls[inside]
            own = w.word_rows[_mix(c, a[inside], rows=WORD_ROWS)]
            own += w.word_bias[c]
            got[inside] += own[np.arange(len(c)), i[inside] % SLOTS] - np.log(np.exp(own).sum(axis=1))
        out[s : s + CHUNK] = got
    return out / np.float32(LOG10), new / np.float32(LOG10)


def _scores(docs: DataFrame, words: Lexicon, weights: Weights) -> DataFrame:
    """(key, doc_id, held_out, n_tokens, n_known, base, score, rest): rest are the words to be joined, each
    with its score if training has it (but for its own count) and if not."""
    sc = docs.sparkSession.sparkContext
    shared = sc.broadcast((words, weights))

    def run(batches: Batches) -> Batches:
        from pyspark import TaskContext

        item = pa.struct([("word", pa.binary()), ("old", pa.float32()), ("new", pa.float32())])
        schema = pa.schema([("key", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base", pa.float64()), ("score", pa.float64()), ("rest", pa.list_(item))])
        lex, w = shared.value
        w.class_bias = w.class_bias - np.log(np.exp(w.class_bias.astype(np.float64)).sum()).astype(np.float32)
        w.word_bias = w.word_bias - np.log(np.exp(w.word_bias.astype(np.float64)).sum(axis=1, keepdims=True)).astype(np.float32)
        coder, key = Coder(lex), TaskContext.get().partitionId() << 40
        base_of, known_of = np.append(lex.base_log10(lex.counts), 0.0), np.append(lex.counts > 0, False)
        names = np.array(list(lex.head), object)
        ending = np.maximum(0, lex.word_id - VOCABULARY)
        share_of = np.append(np.where(lex.word_id < VOCABULARY, 0.0, lex.share_log10(lex.counts, ending)), 0.0)
        spelled = np.zeros(len(lex.counts) + 1)
        unseen = np.flatnonzero((lex.counts == 0) & (lex.word_id >= VOCABULARY))
        spelled[unseen] = lex.new_log10(names[unseen].tolist())
        is_new = np.zeros(len(spelled), bool)
        is_new[unseen] = True
        log_tokens, freed = np.log10(np.maximum(1, lex.class_tokens)), lex.freed()
        for b in batches:
            texts, doc_ids, held = raw(b, "text"), b.column("doc_id").to_pylist(), b.column("held_out").to_pylist()
            for s, e in _parts(texts):
                place, ids, w1, w2, sizes, first, far, far_words = coder.encode(texts[s:e])
                known, new = log10_probabilities(w, freed, ids, w1, w2)
                score = np.where(is_new[place], new + spelled[place], known + share_of[place])
                old = known[far] - log_tokens[ids[far] - VOCABULARY]
                score[far] = 0.0
                border = np.searchsorted(far, np.append(first, len(place)))
                rest = pa.ListArray.from_arrays(pa.array(border, pa.int32()), pa.StructArray.from_arrays([pa.array(far_words, pa.binary()), pa.array(old, pa.float32()), pa.array(new[far] + lex.new_log10(far_words), pa.float32())], fields=list(item)))
                columns = [np.arange(key, key + e - s), doc_ids[s:e], held[s:e], sizes, np.add.reduceat(known_of[place].astype(np.int64), first), np.add.reduceat(base_of[place], first), np.add.reduceat(score, first)]
                yield pa.RecordBatch.from_arrays([*(pa.array(c, f.type) for c, f in zip(columns, schema, strict=False)), rest.cast(schema.field("rest").type)], schema=schema)
                key += e - s

    fields = "key long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, score double, rest array<struct<word binary, old float, new float>>"
    return docs.mapInArrow(run, fields)


def score_documents(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of docs.

    Learns from rows whose crc32(doc_id as text) mod 5 is not 1. Null and empty texts are the end
    mark alone. Null ids are not held out and learned from. Without training rows N, V and all
    counts are 0 and the score is what unigram smoothing alone gives. Repeated rows are documents
    of their own; an empty table gives an empty table. Other columns are not read. Words of any length
    are spelled whole.
    """
    held = F.coalesce(crc_mod("doc_id", 5) == 1, F.lit(False))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("held_out", held)
    counts = cut(word_counts(rows.select("text", (~F.col("held_out")).alias("learn"))), "word-counts")
    words = lexicon(counts)
    weights = train(rows.filter(~F.col("held_out")), words)
    scored = cut(_scores(rows, words, weights), "lm-scores")
    far = scored.select("key", F.explode("rest").alias("r")).select("key", "r.word", "r.old", "r.new")
    joined = far.join(counts.select("word", "c"), "word", "left").withColumn("c", F.coalesce("c", F.lit(0)))
    base = F.log10((F.col("c") + 0.5) / F.lit(words.total + 0.5 * (words.kinds + 1)))
    own = F.when(F.col("c") > 0, F.col("old").cast("double") + F.log10(F.col("c") - F.lit(words.discount))).otherwise(F.col("new").cast("double"))
    per_doc = joined.groupBy("key").agg(F.sum(base).alias("more_base"), F.sum(own).alias("more_score"), F.sum((F.col("c") > 0).cast("long")).alias("more_known"))
    out = scored.drop("rest").join(per_doc, "key", "left")
    zero = F.lit(0.0)
    return out.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(words.total).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("more_base", zero)).alias("base_score"), (F.col("score") + F.coalesce("more_score", zero)).alias("score"),
    )
