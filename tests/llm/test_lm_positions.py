"""Every position of a training document takes a gradient step."""

import numpy as np

from pushwave.llm import maxent_lm
from pushwave.llm.common import prepare


def test_every_position_is_learned(spark):
    prepare(spark)
    texts = [" ".join(f"p{d}x{j}" for j in range(37)) for d in range(5)]
    docs = spark.createDataFrame([(t, True) for t in texts], "text string, learn boolean")
    words = maxent_lm.lexicon(maxent_lm.word_counts(docs))
    weights = maxent_lm.train(docs, words)
    _, ids, w1, w2, *_ = maxent_lm.Coder(words).encode([t.encode() for t in texts])
    assert (ids < maxent_lm.VOCABULARY).all()
    for f in maxent_lm._class_features(w1, w2):
        assert weights.class_rows[f].any(axis=1).all()
    inside = maxent_lm._mix(ids // maxent_lm.SLOTS, w1, rows=maxent_lm.WORD_ROWS)
    assert np.abs(weights.word_rows[inside]).sum(axis=1).all()


def test_probabilities_sum_to_one_over_all_words(spark):
    """Vocabulary, other training words, and words never seen, after some histories, with any weights."""
    prepare(spark)
    rng = np.random.default_rng(3)
    some = ["".join(rng.choice(list("abcé"), rng.integers(1, 9))) for _ in range(9000)]
    docs = spark.createDataFrame([(" ".join(some[i : i + 30]), True) for i in range(0, 9000, 30)] + [("zzz never trained", False)], "text string, learn boolean")
    counts = maxent_lm.word_counts(docs)
    words = maxent_lm.lexicon(counts)
    w = maxent_lm.begin(words)
    w.class_rows[:] = rng.normal(size=w.class_rows.shape)
    w.word_rows[:] = rng.normal(size=w.word_rows.shape)
    table = {bytes(r["word"]): r["c"] for r in counts.collect() if r["c"] > 0}
    assert len(table) > maxent_lm.VOCABULARY
    names = list(table)
    for history in ((7, 3), (maxent_lm.VOCABULARY + 2, 0)):
        ids = np.array([words.word_id[words.head[x]] for x in names])
        log10, new = maxent_lm.log10_probabilities(w, words.freed(), ids, np.full(len(ids), history[0]), np.full(len(ids), history[1]))
        far = ids >= maxent_lm.VOCABULARY
        ending = maxent_lm.ending_classes(names)
        log10 = log10 + np.where(far, words.share_log10(np.array([table[x] for x in names]), ending), 0.0)
        assert np.ptp(new) < 1e-5
        assert abs((10.0**log10).sum() + 10.0 ** new[0] - 1) < 1e-3
    p = 10**words.spelling.table
    assert np.allclose(p.sum(axis=1), 1) and p[256, 256] == 0 and not p[:, [32, *range(65, 91)]].any()
    direct = {x: sum(words.spelling.table[a, b] for a, b in zip([256, *x], [*x, 256])) for x in (b"ab", "é".encode(), b"cabbage")}
    assert all(abs(words.spelling.log10([x])[0] - s) < 1e-9 for x, s in direct.items())
    assert abs(words.spelled - (10 ** words.spelling.log10([x for x in names if x])).sum()) < 1e-9
    # the classes by ending are the same in SQL
    got = counts.select("word", maxent_lm.ending_column("word").alias("e")).collect()
    assert [r["e"] for r in got] == maxent_lm.ending_classes([bytes(r["word"]) for r in got]).tolist()
    assert words.kinds == len(table) and words.total == sum(table.values())
