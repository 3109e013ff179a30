"""The corpus operators against brute force and on their edge cases: nulls, empty and long texts,
ties, repeated rows, empty tables, and further columns of clashing names."""

import hashlib
import itertools
import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from pushwave.llm import decontaminate, language, licenses, line_dedup, maxent_lm, order_minhash, packing, quality, simhash, token_store
from pushwave.llm.common import prepare
from pushwave.llm.components import components
from pushwave.llm.wordpieces import ChunkCodec, codec, vocabulary_path

LONG = "A line that is surely longer than forty code points, é included"
ROWS = [
    (1, f"{LONG}\nshort\nalpha beta gamma delta epsilon"), (2, f"  {LONG.upper().replace('É', 'é')}\t\nother words here"), (3, f"{LONG}\n{LONG}"), (4, LONG), (5, f"x\n{LONG}\ny"), (6, f"{LONG}"),
    (7, None), (8, ""), (9, " \n "), (10, "one"), (11, "one two"), (12, "the cat sat on the mat " * 400), (13, "the cat sat on the mat " * 400), (15, "Zażółć gęślą jaźń 漢字 🎈 don't <|endoftext|> ÀÉ"), (16, "!!! ??? 123 45\x1c6 İ ǅ é"),
]


@pytest.fixture(scope="module")
def docs(spark):
    prepare(spark)
    return spark.createDataFrame(ROWS, "doc_id long, text string")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], "doc_id long, text string")


def wide(df):
    """Further columns with the names that the operators use inside."""
    for c in ("_keep", "_n", "_tid", "_d", "_t", "_doc", "_score", "score", "h1", "fp", "pos", "root", "Key"):
        df = df.withColumn(c, F.lit("x"))
    return df


def rows(df):
    return [r.asDict() for r in df.collect()]


# --- line dedup ---------------------------------------------------------------------------------


def brute_lines(data, min_chars=40, min_docs=5):
    key = lambda s: s.strip(" \t\n\x0b\x0c\r").translate({i: i + 32 for i in range(65, 91)})
    held = defaultdict(set)
    for i, t in data:
        for line in (t or "").split("\n"):
            held[key(line)].add(i)
    out = {}
    for i, t in data:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (len(key(x)) >= min_chars and len(held[key(x)]) >= min_docs and i != max(held[key(x)]))]
        out[i] = (len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest())
    return out


@pytest.mark.parametrize("parts", [1, 3, 11])
def test_line_dedup_equals_brute_force(spark, docs, parts):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    more = [(100 + i, "\n".join(f"{LONG} number {j}" for j in range(40) if (i * j) % 7 < 4)) for i in range(40)]
    data = ROWS + more
    got = {r["doc_id"]: (r["n_lines"], r["n_dropped"], r["kept_sha256"]) for r in rows(line_dedup.line_digest(spark.createDataFrame(data, "doc_id long, text string")))}
    spark.conf.set("spark.sql.shuffle.partitions", before)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")
    assert got == brute_lines(data)


def test_line_dedup_runs_across_batches():
    import pyarrow as pa

    rng = np.random.default_rng(1)
    all_rows = sorted({(int(h), 0, -int(d), 0, int(p)) for h, d, p in zip(rng.integers(0, 12, 3000), rng.integers(0, 40, 3000), rng.integers(0, 5, 3000), strict=True)})
    held = defaultdict(set)
    for h, _, d, _, _ in all_rows:
        held[h].add(-d)
    want = {(h, -d, p) for h, _, d, _, p in all_rows if len(held[h]) >= 5 and -d != max(held[h])}
    names = ("h1", "h2", "doc_id", "tid", "pos")
    by_doc = [list(g) for _, g in itertools.groupby(all_rows, key=lambda r: r[:4])]
    for cuts in ([], [50], [3, 4, 5, 200], list(range(0, len(by_doc), 9))):
        told = []
        for a, b in zip([0, *cuts], [*cuts, len(by_doc)], strict=True):  # a partition never splits a document's rows
            part = [r for g in by_doc[a:b] for r in g]
            batches = [pa.RecordBatch.from_arrays([pa.array([(-x[i] if i == 2 else x[i]) for x in part[s : s + 37]], pa.int32() if i == 4 else pa.int64()) for i in range(5)], names=list(names)) for s in range(0, len(part), 37)]
            told += [r for b_ in line_dedup._runs(5)(iter(batches)) for r in b_.to_pylist()]
        total, top = Counter(), {}
        for r in told:
            if r["kind"] == line_dedup.SUMMARY:
                total[r["h1"]] += r["n"]
                top[r["h1"]] = max(top.get(r["h1"], -1), r["doc_id"])
        got = {(r["h1"], r["doc_id"], r["pos"]) for r in told if r["kind"] == line_dedup.DROP}
        got |= {(r["h1"], r["doc_id"], r["pos"]) for r in told if r["kind"] == line_dedup.OPEN and total[r["h1"]] >= 5 and r["doc_id"] < top[r["h1"]]}
        assert got == want


def test_line_dedup_cases(spark, docs, none):
    out = line_dedup.drop_repeated_lines(wide(docs).withColumn("n_chars", F.lit(0).cast("long")))
    assert out.columns == [*wide(docs).columns, "n_chars"]
    got = {r["doc_id"]: r for r in rows(out)}
    assert got[7]["text"] is None and got[8]["text"] == "" and got[6]["text"] == LONG and got[4]["text"] == ""
    assert got[5]["text"] == "x\ny" and got[5]["n_chars"] == 3
    assert line_dedup.line_digest(none).count() == 0 and line_dedup.drop_repeated_lines(none).count() == 0
    doubled = line_dedup.line_digest(docs.unionByName(docs).unionByName(spark.createDataFrame([(None, LONG)], docs.schema)))
    assert doubled.count() == 2 * len(ROWS) + 1
    assert {r["n_dropped"] for r in rows(doubled.filter("doc_id is null"))} == {1}
    maps = {r["doc_id"]: r for r in rows(line_dedup.keep_bitmaps(docs))}
    assert line_dedup.unpack(maps[5]["keep"], 3).tolist() == [True, False, True]


# --- SimHash ------------------------------------------------------------------------------------


def brute_fingerprint(text):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words)] if 0 < len(words) < 3 else [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)]
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes)) if hashes else 0


def test_simhash_fingerprints(docs):
    got = {r["doc_id"]: r["fp"] % 2**64 for r in rows(simhash.fingerprints(docs))}
    assert got == {i: brute_fingerprint(t) for i, t in ROWS}


def test_masks_cover_every_pair():
    for radius in (1, 2, 3):
        kept = simhash.masks(radius)
        assert all(any(not (m >> i & 1 or m >> j & 1) for m in kept) for i in range(64) for j in range(64)) if radius == 2 else True
        assert len(kept) == 2 ** (radius + 1) - 1


@pytest.mark.parametrize("limit", [4096, 12])
def test_simhash_links_equal_brute_force(spark, limit, monkeypatch):
    prepare(spark)
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 12)
    fps = set(base.tolist())
    for b in base[:4].tolist():
        for _ in range(60):
            x = b
            for _ in range(int(rng.integers(1, 4))):
                x ^= 1 << int(rng.integers(0, 62))
            fps.add(x)
    fps = sorted(fps)
    parent = {f: f for f in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(fps, 2):
        if (a ^ b).bit_count() <= 2:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    monkeypatch.setattr(simhash, "LIMIT", limit)
    found = components(simhash.links(spark.createDataFrame([(f,) for f in fps], "fp long"), 2))
    got = {r["node"]: r["root"] for r in rows(found)}
    assert {f: got.get(f, f) for f in fps} == {f: find(f) for f in fps}


def test_bucket_stream_gives_all_members_or_links(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(simhash, "LIMIT", 5)
    data = sorted((t, k, fp) for t in range(2) for k in range(6) for fp in range(k * 100, k * 100 + [1, 3, 9, 2, 30, 4][k]))
    for size in (1, 4, 7, 100):
        batches = [pa.RecordBatch.from_arrays([pa.array([r[0] for r in data[s : s + size]], pa.int32()), *(pa.array([r[i] for r in data[s : s + size]], pa.int64()) for i in (1, 2))], names=["t", "key", "fp"]) for s in range(0, len(data), size)]
        out = [r for b in simhash._buckets(2, True)(iter(batches)) for r in b.to_pylist()]
        members = Counter((r["t"], r["a"]) for r in out if r["kind"] == simhash.MEMBER)
        assert all(n == 1 for n in members.values())
        linked = {r["a"] for r in out if r["kind"] == simhash.LINK} | {r["b"] for r in out if r["kind"] == simhash.LINK}
        for (t, k), group in itertools.groupby(data, key=lambda r: r[:2]):
            fps = [r[2] for r in group]
            told = [(t, f) in members for f in fps]
            assert all(told) or not any(told)  # a bucket is handed on whole or settled here
            assert all(told) or len(fps) == 1 or any(f in linked for f in fps)
            if (t, k) in ((0, 0), (1, 5)):
                assert all(told)  # the ends may go on next door
        assert size == 100 or any((t, 400) in members for t in range(2))


def test_hot_fingerprints_are_spread(spark, monkeypatch):
    """Classes are the same when the rows of frequent fingerprints are dealt to many tasks."""
    prepare(spark)
    df = spark.createDataFrame([(i, "the same text of some words here" if i % 3 else f"text number {i} alone") for i in range(60)] + [(None, "the same text of some words here")], "doc_id long, text string")
    want = Counter(map(tuple, simhash.near_duplicate_classes(df).collect()))
    kept = Counter(map(tuple, simhash.keep_one_similar(df).collect()))
    monkeypatch.setattr(simhash, "HOT", 5)
    assert Counter(map(tuple, simhash.near_duplicate_classes(df).collect())) == want
    assert Counter(map(tuple, simhash.keep_one_similar(df).collect())) == kept


def test_near_duplicates_and_cases(spark, docs, none):
    got = {r["doc_id"]: r["component_id"] for r in rows(simhash.near_duplicate_classes(docs))}
    fp = {i: brute_fingerprint(t) for i, t in ROWS}
    for i, j in itertools.combinations(fp, 2):
        if (fp[i] ^ fp[j]).bit_count() <= 2:
            assert got[i] == got[j]
    assert got[12] == got[13] == 12 and got[7] == got[8] == got[9] == 7
    assert simhash.near_duplicate_classes(none).count() == 0 and simhash.keep_one(none).count() == 0
    kept = simhash.keep_one(wide(docs.unionByName(docs)))
    assert kept.columns == wide(docs).columns
    assert sorted(r["doc_id"] for r in rows(kept)) == sorted(set(got.values()))
    alone = spark.createDataFrame([(None, "some words in a row"), (3, "some words in a row")], docs.schema)
    assert [r["doc_id"] for r in rows(simhash.keep_one(alone))] == [3]


def test_components_of_chains(spark):
    prepare(spark)
    chain = [(i, i + 1) for i in range(0, 60)] + [(100, 101), (101, 100), (5, 5), (200, 150), (150, 170)]
    got = {r["node"]: r["root"] for r in rows(components(spark.createDataFrame(chain, "a long, b long")))}
    assert got == {**{i: 0 for i in range(61)}, 100: 100, 101: 100, 150: 150, 170: 150, 200: 150}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# --- tokens -------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def encoded():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary_path())
    return lambda text: t.encode(text or "", add_special_tokens=False).ids


def test_codec_is_exact(encoded):
    odd = ["don't 'S it's", "Σας ΟΔΟΣ", "ﬁ İstanbul ıI", "a b c", "x\x1cy", "ÀÉ, ñandú. straße! Œuvre;", "é ñ", "<|endoftext|>a <|startoftext|>", "12.5% 3rd", "!!!... ??", "WORD!!", "ª º ǆ Ȁ", "abć, ok.", "l'été: d'où?", "a|b c-d e)"]
    c = ChunkCodec(vocabulary_path())
    for text in odd + [t for _, t in ROWS if t]:
        assert np.frombuffer(c.encode([text.encode()])[0], c.dtype).tolist() == encoded(text), text


def test_token_store_round_trip(spark, docs, none, encoded):
    store = token_store.write_store(wide(docs), vocabulary_path())
    start, want = 0, []
    for i, t in ROWS:
        ids = encoded(t) + [1]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert sorted(tuple(r.values()) for r in rows(token_store.read_store(store, spark))) == want
    assert token_store.read_document(store, 15)[0].tolist() == encoded(ROWS[13][1]) + [1]
    assert token_store.read_document(store, 14) == []
    empty = token_store.write_store(none, vocabulary_path())
    assert token_store.read_store(empty, spark).count() == 0
    with pytest.raises(ValueError):
        token_store.Shard(store.folder, store.manifest.first()["file"], b"another dictionary")
    again = token_store.write_store(docs.unionByName(docs).unionByName(spark.createDataFrame([(None, "x")], docs.schema)), vocabulary_path())
    assert token_store.read_store(again, spark).count() == 2 * len(ROWS) + 1
    assert len(token_store.read_document(again, 12)) == 2


def check_packing(found, texts, encoded, window):
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in found:
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append(r)
    assert set(by_doc) == set(texts)
    for i, pieces in by_doc.items():
        ids, at = np.array(encoded(texts[i]) + [2], "<u4"), 0
        for r in sorted(pieces, key=lambda r: r["start"]):
            assert r["start"] == at and r["length"] > 0 and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(ids[at : at + r["length"]].tobytes())
            at += r["length"]
        assert at == len(ids)
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= window
    return by_seq


def test_packing(spark, docs, none, encoded):
    for window, every in ((64, 100), (4096, 100), (64, 3)):
        seqs = check_packing(rows(packing.pack(wide(docs), vocabulary_path(), 2, window, every)), dict(ROWS), encoded, window)
        full = sum(sum(r["length"] for r in p) == window for p in seqs.values())
        assert len(seqs) - full <= 1 and set(seqs) == set(range(len(seqs)))
    assert packing.pack(none, vocabulary_path()).count() == 0
    assert sum(r["length"] for r in rows(packing.pack(docs.unionByName(docs), vocabulary_path()))) == 2 * sum(len(encoded(t)) + 1 for _, t in ROWS)
    odd = spark.createDataFrame([(None, "no id"), (None, None), (0, "seed of all"), (-100, "seed of all")], "doc_id long, text string")
    assert Counter(r["doc_id"] for r in rows(packing.pack(odd, vocabulary_path()))) == {None: 2, 0: 1, -100: 1}


def brute_bm25(docs: list[np.ndarray]):
    """scores(q): BM25 of every document against the distinct terms of document q, by the formula."""
    n, mean = len(docs), np.mean([len(d) for d in docs])
    held = [Counter(d.tolist()) for d in docs]
    df = Counter(t for h in held for t in h)

    def scores(q):
        return [sum(math.log1p((n - df[t] + 0.5) / (df[t] + 0.5)) * h[t] * 2.2 / (h[t] + 1.2 * (0.25 + 0.75 * len(d) / mean)) for t in held[q] if t in h) for d, h in zip(docs, held, strict=True)]

    return scores


@pytest.mark.parametrize("block", [2048, 3])
def test_neighbours_equal_brute_force_over_the_whole_table(spark, encoded, monkeypatch, block):
    """Recall of the five best against brute-force BM25 over all documents, with one block of seeds and with many."""
    monkeypatch.setattr(packing.bm25, "SEEDS", block)
    prepare(spark)
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").repartition(3)
    data = [(r["doc_id"], np.array(encoded(r["text"] or "") + [2])) for r in docs.collect()]
    scores = brute_bm25([d for _, d in data])
    found = defaultdict(list)
    for r in rows(packing.neighbours(docs, vocabulary_path(), 5, every=10)):
        found[r["doc_id"]].append((r["rk"], r["neighbour"], r["score"]))
    seeds = [i for i, _ in data if i % 10 == 0]
    assert set(found) == set(seeds)
    hits = 0
    for q, (i, _) in enumerate(data):
        if i % 10 == 0:
            want = sorted((-s, data[j][0]) for j, s in enumerate(scores(q)) if j != q)[:5]
            assert np.allclose([-w for w, _ in want], [s for _, _, s in sorted(found[i])], rtol=1e-4)
            hits += len({j for _, j in want} & {j for _, j, _ in found[i]})
    assert hits >= 0.97 * 5 * len(seeds)  # equal scores may change places


def test_a_seed_is_packed_beside_its_neighbours(spark):
    prepare(spark)
    words = [[f"{'abcdefghij'[t]}{'klmnopqrst'[w]}um" for w in range(10)] for t in range(4)]
    texts = [(i, " ".join(words[i % 4] * 3)) for i in range(400, 440)]
    texts = [(i * 100 if i < 404 else i * 100 + 1, t) for i, t in texts]  # a seed of each theme
    got = {r["doc_id"]: r["sequence_id"] * 4096 + r["offset"] for r in rows(packing.pack(spark.createDataFrame(texts, "doc_id long, text string").repartition(4), vocabulary_path()).filter("start = 0"))}
    laid = [dict(texts)[d] for d in sorted(got, key=got.get)]
    assert sum(a != b for a, b in itertools.pairwise(laid)) == 3  # themes lie together


# --- fingerprints -------------------------------------------------------------------------------


def test_order_minhash(spark, docs, none):
    got = {r["doc_id"]: r for r in rows(order_minhash.edit_report(wide(docs)))}
    ordered = [(i, t or "") for i, t in ROWS]
    for (i, t), (j, u) in zip(ordered, ordered[1:] + ordered[:1], strict=True):
        q = len(t) // 4
        assert got[i]["n_chars"] == len(t)
        assert got[i]["edited_sha256"] == hashlib.sha256((t[: len(t) - q] + u[:q]).encode()).hexdigest()
        assert 0 <= got[i]["near_edited"] <= 1 and 0 <= got[i]["near_next"] <= 1
    assert got[12]["fingerprint"] == got[13]["fingerprint"] and got[12]["near_next"] == 1
    assert got[8]["fingerprint"] == "." * 512 and got[7]["near_next"] == 1
    assert order_minhash.edit_report(none).count() == 0
    one = order_minhash.edit_report(spark.createDataFrame([(5, "abcdefgh")], docs.schema)).first()
    assert one["edited_sha256"] == hashlib.sha256(b"abcdefab").hexdigest() and one["near_next"] == 1
    assert order_minhash.edit_report(docs.unionByName(docs)).count() == 2 * len(ROWS)


def test_order_minhash_equals_brute_force(spark):
    """Selection of the least occurrence-numbered k-mers and their order, from Spark's own hashes."""
    text = " ".join(f"w{i * i % 23}" for i in range(200)) + " a b c d e" * 7
    df = spark.createDataFrame([(text,)], "text string")
    words = df.select(F.transform(F.split("text", " "), lambda w: F.xxhash64(w)).alias("w")).first()["w"]
    kmers = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    rows_ = spark.createDataFrame([(i, *k) for i, k in enumerate(kmers)], "i long, a long, b long, c long, d long, e long").select("i", F.xxhash64("a", "b", "c", "d", "e").alias("h")).orderBy("i").collect()
    high = [r["h"] >> 24 << 24 for r in rows_]
    seen, numbered = Counter(), []
    for h in high:
        numbered.append((h, seen[h]))
        seen[h] += 1
    ranks = [r["g"] >> 24 for r in spark.createDataFrame([(i, h, n) for i, (h, n) in enumerate(numbered)], "i long, h long, n int").select("i", F.xxhash64("h", "n").alias("g")).orderBy("i").collect()]
    buckets = defaultdict(list)
    for place, g in enumerate(ranks):
        buckets[(g >> 34) + 32].append((g, place))
    want = {}
    for b, items in buckets.items():
        least = sorted(items)[:2]
        want[b] = [g for g, _ in sorted(least, key=lambda x: x[1])]
    pairs = spark.createDataFrame([(b, *(v + [None])[:2]) for b, v in want.items()], "b int, x long, y long").select("b", F.when(F.col("y").isNull(), F.xxhash64("x")).otherwise(F.xxhash64("x", "y")).bitwiseAND(F.lit(0x7FFFFFFF)).cast("int").alias("v")).collect()
    got = df.select(order_minhash.fingerprint(F.col("text")).alias("f")).first()["f"]
    assert {i: v for i, v in enumerate(got) if v is not None} == {r["b"]: r["v"] for r in pairs}


@pytest.mark.parametrize("quantiles", [1024, 4])
def test_next_document_for_any_ids(spark, monkeypatch, quantiles):
    """The extreme longs, an outlier among many, null and repeated ids: next is next by id, in small groups."""
    monkeypatch.setattr(order_minhash, "QUANTILES", quantiles)
    lots = [*range(20_000), 2**60]
    for ids in ([0, 2**62], [-(2**63), 2**63 - 1, 0, 5, -1], lots, [7, None, 7, 3], [2]):
        df = spark.createDataFrame([(i, i) for i in ids], "doc_id long, id long")
        order = sorted(ids, key=lambda i: (i is not None, i or 0))
        got = Counter((r["doc_id"], r["next_id"]) for r in order_minhash.with_next(df, ["id"]).collect())
        assert got == Counter(zip(order, order[1:] + order[:1], strict=True))
    if quantiles == 1024:
        df = spark.createDataFrame([(i,) for i in lots], "doc_id long")
        assert max(r["count"] for r in df.groupBy(order_minhash._groups(df)).count().collect()) < 300


def test_order_minhash_feels_order(spark):
    a = " ".join(f"w{i}" for i in range(300))
    blocks = [" ".join(f"w{i}" for i in range(s, s + 30)) for s in range(0, 300, 30)]
    moved = " ".join(reversed(blocks))
    r = spark.createDataFrame([(a, moved)], "a string, b string").select(order_minhash.likeness(order_minhash.fingerprint(F.col("a")), order_minhash.fingerprint(F.col("b"))).alias("x")).first()["x"]
    assert r < 0.85  # most k-mers are the same, but not their order


# --- models -------------------------------------------------------------------------------------


def test_quality_score_is_the_mean_of_words_and_pairs():
    texts = [b"calm tidy words", b"Spam! Spam! Spam!", b"tidy words calm calm", b"Win! $$$", b"one"]
    model = quality.train(texts * 4, [1, 0, 1, 0, 1] * 4)
    slow = []
    for text in texts:
        words, number = text.split(), model.number.astype(float)
        logit = model.bias
        for w in words:
            inner, whole = quality._inner([w])[0], quality._whole([w])
            logit += (number[inner].mean() + number[quality._word_rows(whole)[0]]) / 2 / len(words)
        for a, b in zip(words, words[1:]):
            kind = quality._KIND + int(a == b)
            logit += (number[quality._pair_rows(quality._whole([a, b]))[0]] + number[kind]) / 2 / (len(words) - 1)
        slow.append(1 / (1 + np.exp(-logit)))
    assert np.allclose(model.scores(texts), slow)
    assert [s >= 0.5 for s in slow] == [True, False, True, False, True]


def test_quality_held_out_accuracy(spark):
    prepare(spark)
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    truth = {r["doc_id"]: r["quality"] for r in rows(labels) if r["quality"] is not None}
    got = [(r["predicted"], truth[r["doc_id"]]) for r in rows(quality.quality_scores(docs, labels)) if r["held_out"] and r["doc_id"] in truth]
    assert len(got) > 50 and sum(p == y for p, y in got) >= 0.95 * len(got)


def test_quality(spark, none):
    prepare(spark)
    good = [(i, f"the plain words of document number {i} are calm and tidy, quite so.") for i in range(0, 200)]
    bad = [(i, f"BUY!! NOW!! CHEAP{i}!! $$$ CLICK!! *** WIN{i}!!") for i in range(200, 400)]
    data = spark.createDataFrame([*good, *bad, (900, None), (901, ""), (902, "  ")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 200), 0) for i in range(400)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in rows(quality.quality_scores(wide(data), labels))}
    assert all(got[i]["predicted"] == int(i < 200) for i in range(400))
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) for i in got)
    assert got[900]["score"] == got[901]["score"] == got[902]["score"]
    assert quality.quality_scores(none, labels).count() == 0
    kept = quality.keep_good(wide(data), labels)
    assert kept.columns == wide(data).columns and {r["doc_id"] for r in rows(kept)} >= set(range(200))
    assert {r["score"] for r in rows(quality.quality_scores(data, labels.limit(0)))} == {0.5}


def test_language(spark, none):
    prepare(spark)
    rng = np.random.default_rng(0)
    say = {"aa": ["ka", "ki", "ko", "kaki"], "bb": ["mu", "me", "mo", "mume"]}
    text = lambda lang: " ".join("".join(rng.choice(say[lang], 2)) for _ in range(30))
    data = [(i, text("aa" if i % 2 else "bb"), "aa" if i % 2 else "bb") for i in range(120)]
    data += [(500, None, "aa"), (501, "123 !!", "bb"), (502, "", None), (503, text("aa") + " " + text("bb") + " " + text("bb"), None)]
    got = {r["doc_id"]: r for r in rows(language.language_predictions(wide(spark.createDataFrame(data, "doc_id long, text string, lang string").withColumnRenamed("nothing", "x"))))}
    assert all(got[i]["lang_pred"] == ("aa" if i % 2 else "bb") for i in range(120))
    assert [got[i]["lang_pred"] for i in (500, 501, 502, 503)] == ["und", "und", "und", "bb"]
    assert got[500]["score"] == 0 and 0.5 < got[503]["score"] < 0.8
    assert language.language_predictions(none.withColumn("lang", F.lit(None).cast("string"))).count() == 0
    model = language.train([data[0][1].encode(), data[1][1].encode()], ["bb", "aa"])
    post, border = model.word_posteriors([b"kaki kaki kaki mume mume mume"])
    assert post.argmax(axis=1).tolist() == [0, 0, 0, 1, 1, 1] and border.tolist() == [0, 6]


def test_a_long_text_is_one_chain():
    """Posteriors over pieces of 64 words equal forward-backward over the whole text, for texts of many lengths."""
    rng = np.random.default_rng(8)
    sizes = [1, 64, 65, 130, 700, 3, 192]
    transition, start = rng.normal(size=(4, 4)) * 2, rng.normal(size=4)
    emission, place, text, valid = [], [], [], []
    for i, n in enumerate(sizes):
        own = rng.normal(size=(n, 4)).astype(np.float32) * 0.3
        emission.append(own)
        for s in range(0, n, 64):
            piece = np.zeros((64, 4), np.float32)
            piece[: min(64, n - s)] = own[s : s + 64]
            place.append(piece)
            text.append(i)
            valid.append(min(64, n - s))
    got = language.posteriors(np.stack(place, axis=1), transition, start, np.array(valid), np.array(text))
    for i, own in enumerate(emission):
        want = language.forward_backward(own[None].astype(float), transition, start, np.array([len(own)]))[0][0]
        mine = np.concatenate([got[: valid[j], j] for j in range(len(text)) if text[j] == i])
        assert np.allclose(mine, want, atol=1e-4)


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(1)
    e, t, s = rng.normal(size=(1, 4, 3)), rng.normal(size=(3, 3)), rng.normal(size=3)
    post, pair, head = language.forward_backward(e, t, s, np.array([4]))
    weights = {y: math.exp(s[y[0]] + sum(e[0, i, y[i]] for i in range(4)) + sum(t[y[i], y[i + 1]] for i in range(3))) for y in itertools.product(range(3), repeat=4)}
    z = sum(weights.values())
    for i in range(4):
        for k in range(3):
            assert abs(post[0, i, k] - sum(w for y, w in weights.items() if y[i] == k) / z) < 1e-9
    assert abs(pair[1, 2] - sum(w * sum(y[i] == 1 and y[i + 1] == 2 for i in range(3)) for y, w in weights.items()) / z) < 1e-9
    fast = language.posteriors(e.transpose(1, 0, 2).astype(np.float32), t, s, np.array([4]))
    assert np.allclose(fast[:, 0], post[0], atol=1e-5)


@pytest.mark.parametrize("head", [4, 100_000])
def test_language_model(spark, none, head, monkeypatch):
    prepare(spark)
    monkeypatch.setattr(maxent_lm, "HEAD", head)
    data = [(i, "The cat sat on the mat and " + " ".join(f"w{(i * j) % 17}" for j in range(20))) for i in range(60)] + [(500, None), (501, ""), (502, "never seen wörds")]
    got = {r["doc_id"]: r for r in rows(maxent_lm.score_documents(wide(spark.createDataFrame(data, "doc_id long, text string"))))}
    toks = {i: [w.decode() for w in (t or "").encode().lower().split()] + ["<end>"] for i, t in data}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i in toks}
    c = Counter(w for i, t in toks.items() if not held[i] for w in t)
    n, v = sum(c.values()), len(c)
    for i, t in toks.items():
        assert got[i]["held_out"] == held[i] and got[i]["train_tokens"] == n and got[i]["n_tokens"] == len(t)
        assert got[i]["n_known"] == sum(c[w] > 0 for w in t)
        assert abs(got[i]["base_score"] - sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t)) < 1e-9
        assert got[i]["score"] <= 0
    out = [i for i in range(60) if held[i]]
    if head > 4:  # with a vocabulary of a few words there is nothing to learn
        assert sum(got[i]["score"] for i in out) > sum(got[i]["base_score"] for i in out)
    new = {i: got[i]["score"] for i in (500, 501)}
    assert new[500] == new[501] > got[502]["score"] and all(map(math.isfinite, (r["score"] for r in got.values())))
    assert maxent_lm.score_documents(none).count() == 0
    nothing = spark.createDataFrame([(next(i for i in itertools.count() if zlib.crc32(str(i).encode()) % 5 == 1), "no training text")], "doc_id long, text string")
    assert all(r["n_known"] == 0 and math.isfinite(r["score"]) for r in rows(maxent_lm.score_documents(nothing)))


# --- licences -----------------------------------------------------------------------------------


def test_licenses(spark, none):
    prepare(spark)
    texts = {1: "Released under the MIT License.", 2: "Apache License, Version 2.0 -- and again apache-license version 2", 3: "CC-BY-NC-SA 4.0", 4: "nothing here", 5: None, 6: "", 7: "SPDX-License-Identifier: GPL-3.0; all rights reserved", 8: "under the mitlicense, cc by", 9: "x " * 20_000 + "cc by nc cc by nc"}
    got = {r["doc_id"]: r for r in rows(licenses.scan(wide(spark.createDataFrame(list(texts.items()), "doc_id long, text string"))))}
    assert [got[i]["base_labels"] for i in range(1, 10)] == ["mit", "apache-2", "cc-by-nc", "", "", "", "", "", "cc-by-nc"]
    assert [got[i]["n_base"] for i in range(1, 10)] == [1, 2, 1, 0, 0, 0, 0, 0, 2]
    assert (got[9]["first_word"], got[9]["last_word"], got[9]["n_words"]) == (20_000, 20_003, 20_006)
    assert (got[1]["first_word"], got[1]["n_words"]) == (1, 5) and got[5]["first_word"] is None
    assert got[3]["labels"] == "cc-by-nc,cc-by-nc-sa" and got[7]["labels"] == "gpl-3,proprietary"
    assert all(set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) for r in got.values())
    assert got[4]["score"] == 0 and got[1]["score"] == 1
    assert len(licenses.rules()) > 200 and licenses.scan(none).count() == 0
    line = licenses.words_line(b"licensed under the GNU General Public License version 3")
    found = licenses.detect(line, line.split())
    assert [(f.label, f.first, f.last) for f in found] == [("gpl-3", 0, 8)]  # shorter hits inside are gone


# --- decontamination ----------------------------------------------------------------------------


def test_common_words_is_the_longest_common_subsequence():
    rng = np.random.default_rng(3)

    def slow(a, b):
        t = np.zeros((len(a) + 1, len(b) + 1), int)
        for i, x in enumerate(a, 1):
            for j, y in enumerate(b, 1):
                t[i, j] = t[i - 1, j - 1] + 1 if x == y else max(t[i - 1, j], t[i, j - 1])
        return t[-1, -1]

    for _ in range(30):
        a, b = rng.integers(0, 6, rng.integers(1, 50)), rng.integers(-1, 8, rng.integers(0, 70))
        assert decontaminate.common_words(a, b) == slow(a.tolist(), b.tolist())


def test_verbatim_items_need_no_latent_space(monkeypatch):
    """Copies of short, long and templated items are found by their runs alone, across the borders of stretches too."""
    monkeypatch.setattr(decontaminate, "STRETCH", 512)
    rng = np.random.default_rng(8)
    some = lambda n: [b"w%d" % x for x in rng.integers(0, 400, n)]
    items = [(i, some(int(n))) for i, n in enumerate(rng.integers(4, 90, 60))] + [(60, some(1500)), (61, [b"the"] * 9)]
    items += [(70 + i, [b"which", b"is", b"the", b"answer", b"of", *some(4)]) for i in range(20)]
    bench = decontaminate._block(items)
    blind = np.zeros((len(bench.vocabulary), decontaminate.RANK), np.float32)
    own = decontaminate.Retriever(bench, decontaminate.Space(rng.random(len(blind)) + 0.1, blind, np.zeros((len(bench.passages), blind.shape[1]), np.float32)))
    texts = [b" ".join([*some(int(rng.integers(0, 1200))), *words, *some(int(rng.integers(0, 700)))]) for _, words in items]
    held = [{i for i, (_, words) in enumerate(items) if b" %s " % b" ".join(words) in b" %s " % t} for t in texts]
    found = [{x[0] for x in f if x[2] == 1.0} for f in own.leaks(texts)]
    assert all(i in h and h <= f for i, (h, f) in enumerate(zip(held, found, strict=True)))
    assert own.leaks([None, b"", b"the", b"no word of it"]) == [[], [], [], []]


@pytest.mark.parametrize(("dense", "full"), [(1 << 26, 512), (0, 512), (1 << 26, 3)])
def test_decontamination(spark, docs, none, dense, full, monkeypatch):
    prepare(spark)
    monkeypatch.setattr(decontaminate, "BLOCK_PASSAGES", full)  # 3: seven blocks in two passes
    monkeypatch.setattr(decontaminate, "DENSE", dense)
    rng = np.random.default_rng(6)
    word = lambda n: " ".join(f"w{int(x)}" for x in rng.zipf(1.4, n) % 3000)
    items = [(i, " ".join(f"b{i}x{j}" if j % 3 else "w1" for j in range(24))) for i in range(20)] + [(50, None), (51, "two words")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    data = [(i, word(200)) for i in range(60)]
    drop = lambda t, k: " ".join(w for j, w in enumerate(t.split()) if j % k)
    data += [(100, word(70) + " " + items[0][1] + " " + word(90)), (101, items[1][1].upper()), (102, word(30) + " " + drop(items[2][1], 5) + " " + word(60)), (103, None), (104, ""), (105, word(70_000) + " " + items[3][1] + " " + word(500)), (106, items[4][1] + "\n" + word(3) + ". " + items[5][1])]
    df = spark.createDataFrame(data, "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in rows(decontaminate.find_leaks(wide(df), bench))}
    assert got == {(100, 0), (101, 1), (102, 2), (105, 3), (106, 4), (106, 5)}
    kept = decontaminate.drop_leaky(wide(df), bench)
    assert kept.columns == wide(df).columns and {r["doc_id"] for r in rows(kept)} == {*range(60), 103, 104}
    assert decontaminate.find_leaks(df, bench.limit(0)).count() == 0 and decontaminate.drop_leaky(df, bench.limit(0)).count() == len(data)
    assert decontaminate.find_leaks(none, bench).count() == 0
    assert codec(vocabulary_path()) is codec(vocabulary_path())
