"""The pipeline's stages, each against the plain statement of what it decides, on the small table."""

import hashlib

import corpus_pipeline
from pushwave.llm import simhash
from pushwave.llm.common import prepare
from pushwave.llm.decontaminate import words_of
from pushwave.plans.durable import cut
from tests.llm.test_operators import brute_lines

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    prepare(spark)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    assert len(corpus_pipeline.STAGES) == 5
    last = len(corpus_pipeline.STAGES) - 1
    seen = [{r["doc_id"] for r in docs.select("doc_id").collect()}]
    items = [words_of(r["text"].encode()) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        before, docs = docs, cut(stage(spark, docs, SF))
        if i == 1:  # every text is what is left of it by brute force
            want = brute_lines([(r["doc_id"], r["text"]) for r in before.collect()])
            assert all(hashlib.sha256((r["text"] or "").encode()).hexdigest() == want[r["doc_id"]][2] and r["n_chars"] == len(r["text"]) for r in docs.collect())
        if i == 3:  # documents that hold an item word by word go, those far from all items stay
            kept = {r["doc_id"] for r in docs.collect()}
            for r in before.collect():
                line = b" %s " % b" ".join(words_of(r["text"].encode()))
                if any(b" %s " % b" ".join(item) in line for item in items):
                    assert r["doc_id"] not in kept
                elif all(len(set(item) & set(line.split())) < 0.4 * len(set(item)) for item in items):
                    assert r["doc_id"] in kept
        seen.append({r["doc_id"] for r in docs.select("doc_id").collect()})
        assert seen[-1] <= seen[-2]
        if i < last:
            assert docs.columns == columns
        if i == 2:
            left = simhash.near_duplicate_classes(docs.select("doc_id", "text"))
            assert left.filter("doc_id <> component_id").count() == 0
    assert seen[-1] == seen[-2]  # packing loses no document
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    assert sum(labels.get(i) == 0 for i in seen[1]) <= 0.5 * sum(q == 0 for q in labels.values())
    assert sum(labels.get(i) == 1 for i in seen[1]) >= 0.98 * sum(q == 1 for q in labels.values())
    assert sum(r["length"] for r in docs.collect()) > 0
