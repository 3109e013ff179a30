"""Near-dedup against brute force: all pairs whose five-word shingle sets have a Jaccard similarity of 0.8."""

from itertools import combinations

import numpy as np

import corpus_pipeline
from pushwave.llm import simhash
from pushwave.llm.common import prepare


def _shingles(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def _kept(rows):
    """The least id of each class of the brute-force links."""
    sets = {i: _shingles(t) for i, t in rows}
    root = {i: i for i in sets}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in combinations(sorted(sets), 2):
        if sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            low, high = sorted((top(a), top(b)))
            root[high] = low
    return {i for i in root if root[i] == i}


def test_near_duplicates_equal_brute_force(spark):
    prepare(spark)
    rng = np.random.default_rng(3)
    docs = []
    for _ in range(12):  # edited copies on both sides of 0.8, some behind the same opening
        words = ["the", "same", "opening", "of", "six", "words"] + [f"w{int(x)}" for x in rng.integers(0, 4000, 120)]
        docs.append(words)
        for edits in (1, 2, 3, 4, 6):
            other = list(words)
            for at in rng.choice(len(words), edits, replace=False):
                other[int(at)] = f"x{int(rng.integers(0, 9999))}"
            docs.append(other)
    rows = [(i, " ".join(w)) for i, w in enumerate(docs)]
    rows += [(900, None), (901, "  "), (902, "one two"), (903, "One  two"), (904, "one two three four"), (905, "a b c d e"), (906, "a b c d e f")]
    got = {r["doc_id"] for r in simhash.keep_one_similar(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == _kept(rows)
    assert len(got) < 60


def test_near_duplicates_of_the_small_table(spark):
    prepare(spark)
    table = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    rows = [(r["doc_id"], r["text"]) for r in table.collect()]
    stage = dict(corpus_pipeline.STAGES)["SimHash near-dedup"]
    assert {r["doc_id"] for r in stage(spark, table, "").collect()} == _kept(rows)


def test_a_large_group_of_edited_copies_equals_brute_force(spark):
    prepare(spark)
    rng = np.random.default_rng(8)
    first = [f"w{int(x)}" for x in rng.integers(0, 4000, 150)]
    rows = []
    for i in range(160):  # up to six edits, so that some reach the others by one link alone and some by none
        words = list(first)
        for at in rng.choice(len(words), i % 7, replace=False):
            words[int(at)] = f"x{int(rng.integers(0, 99999))}"
        rows.append((1000 - i, " ".join(words)))
    got = {r["doc_id"] for r in simhash.keep_one_similar(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == _kept(rows)
    assert 1 < len(got) < 160


def test_parities_differ_in_no_more_bits_than_sets_in_shingles():
    rng = np.random.default_rng(4)
    for size in (0, 1, 5, 200, 5000):
        both = rng.integers(0, 2**63, size).astype(np.uint64)
        own = rng.integers(0, 2**63, 2 + size // 9).astype(np.uint64)
        changed = simhash._parities(both) ^ simhash._parities(np.unique(np.concatenate([both, own])))
        assert int(np.bitwise_count(changed.view(np.uint64)).sum()) <= len(own)
