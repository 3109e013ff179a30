"""That operators fit on every document, link by the method that they are named for, and pack what they count."""

import numpy as np

import corpus_pipeline
from pushwave.llm import bm25, decontaminate, simhash
from pushwave.llm.common import prepare
from pushwave.llm.wordpieces import codec, vocabulary_path


def test_the_latent_space_is_fitted_on_every_document(spark, monkeypatch):
    prepare(spark)
    rng = np.random.default_rng(2)
    bench = decontaminate._block([(i, [b"w%d" % x for x in rng.integers(0, 50, 30)]) for i in range(5)])
    texts = [" ".join(f"w{int(x)}" for x in rng.integers(0, 70, n)) for n in (*rng.integers(0, 400, 40), 20_000)]
    seen = []
    monkeypatch.setattr(decontaminate, "latent_space", lambda *a: seen.append(a))
    n_docs = 1_000_000  # as if these were documents of a large table: none may be left out for that
    decontaminate.fit(spark.createDataFrame([(t,) for t in texts] + [(None,)], "text string"), bench, n_docs)
    (frequency, _, gram, n_passages, _), n = seen[0], len(bench.vocabulary)
    want, often, passages = np.zeros((n, n)), np.zeros(n, np.int64), 0
    for t in texts:
        words = t.encode().split()
        for s in range(0, len(words), 64):
            counts = np.zeros(n)
            for w in words[s : s + 64]:
                if w in bench.vocabulary:
                    counts[bench.vocabulary[w]] += 1
            want += np.outer(counts, counts)
            passages += 1
        for w in set(words) & bench.vocabulary.keys():
            often[bench.vocabulary[w]] += 1
    assert n_passages == passages and (frequency == often).all()
    want = want @ decontaminate._test_matrix(n, gram.shape[1])
    assert np.allclose(gram, want, rtol=0, atol=1e-5 * np.abs(want).max())


def test_near_dedup_links_by_fingerprints(spark):
    """Two texts of one refrain have one fingerprint, though few of their different shingles are the same."""
    prepare(spark)
    rng = np.random.default_rng(5)
    own = lambda: " ".join(f"v{int(x)}" for x in rng.integers(0, 9999, 60))
    rows = [(7, "row the boat " * 400 + own()), (8, "row the boat " * 400 + own()), (9, own()), (10, None), (11, own())]
    rows.append((12, "at first " + rows[2][1] + " the end"))  # similar to 9, and its fingerprint is further off
    marks = [simhash.fingerprint((t or "").encode()) for _, t in rows]
    assert (marks[0] ^ marks[1]).bit_count() <= 2 < (marks[2] ^ marks[5]).bit_count()
    sets = [set(simhash.shingle_set(t.encode()).tolist()) for _, t in rows[:2]]
    assert 5 * len(sets[0] & sets[1]) < 4 * len(sets[0] | sets[1])
    df = spark.createDataFrame(rows, "doc_id long, text string")
    stage = dict(corpus_pipeline.STAGES)["SimHash near-dedup"]
    assert {r["doc_id"] for r in stage(spark, df, "").collect()} == {7, 9, 10, 11}


def test_terms_of_many_documents(monkeypatch):
    monkeypatch.setattr(bm25, "TOGETHER", 500)
    rng = np.random.default_rng(6)
    for dtype in (np.dtype("<u2"), np.dtype("<u4")):
        docs = [rng.integers(0, 900, n).astype(dtype) for n in (1, 70_000, *rng.integers(1, 300, 50), 70_000, 3)]
        for d, t, c in zip(docs, *bm25.term_rows([d.tobytes() for d in docs], dtype), strict=True):
            terms, times = np.unique(d, return_counts=True)
            assert t == terms.tobytes() and c == times.astype("<u2" if len(d) < 65536 else "<u4").tobytes()


def test_chunks_learned_together_are_the_librarys():
    marks = "a \u00c9t\u00e9! Stra\u00dfe, \u0130x \u212aelvin \u00aa \u00b5m 3rd it's don't... ??? e\u0301 \u4e2d\u6587 A.b \u2028x \u0085y \U0001f600"
    own = codec(vocabulary_path())
    for text in (marks, "", "\r\x0b\x1c a\x1cb", "Word " * 10 + "word. WORD"):
        want = own.tokenizer.encode(text, add_special_tokens=False).ids
        assert np.frombuffer(own.encode([text.encode()])[0], own.dtype).tolist() == want


def test_parts_are_merged_together_as_the_library_does(monkeypatch):
    from tokenizers import Tokenizer

    from pushwave.llm import wordpieces

    rng = np.random.default_rng(3)
    t = Tokenizer.from_file(vocabulary_path())
    letters = list("aaeinorst") + ["é", "ß", "Ñ", "x"]
    words = ["".join(rng.choice(letters, n)) + "".join(rng.choice(list(".!-;"), n % 3)) for n in rng.integers(1, 70, 3000).tolist()]
    texts = ["", None, " \t\v\f\r\n", "\x1c", *(sep.join(words[i : i + 40]) for i, sep in enumerate([" ", "\n\n", "\t ", "\f", "\v\r"] * 60))]
    c, alone = wordpieces.ChunkCodec(vocabulary_path()), []
    merge = c._merge
    monkeypatch.setattr(wordpieces, "MOST", 500)  # generations change
    monkeypatch.setattr(wordpieces, "TOGETHER", 5000)
    monkeypatch.setattr(c, "_merge", lambda part: alone.append(part) or merge(part))
    found = c.encode([None if x is None else x.encode() for x in texts])
    assert [np.frombuffer(f, c.dtype).tolist() for f in found] == [t.encode(x or "", add_special_tokens=False).ids for x in texts]
    assert alone and all(len(p) > wordpieces.Merges.WIDE for p in alone)  # no other part goes to the model by itself


def test_workers_hold_no_chunks_after_a_task(spark):
    import pyarrow as pa

    from pushwave.llm import packing

    prepare(spark)
    path = vocabulary_path()
    docs = spark.createDataFrame([(i, f"words of text number{i} follow") for i in range(400)], "doc_id long, text string").repartition(4)
    assert packing.tokenized(docs, path, 2).count() == 400

    def held(batches):
        for _ in batches:
            pass
        own = codec(path)
        yield pa.RecordBatch.from_arrays([pa.array([len(own.known) + len(own.before)])], names=["n"])

    assert [r["n"] for r in docs.mapInArrow(held, "n long").collect()] == [0] * 4
