from __future__ import annotations

import collections

import corpus_pipeline
from regpath.llm import decontaminate, mixing
from tests.llm.test_operators import ITEM, docs_of, near, odd, words


def test_stages_and_run_agree(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        out = str(tmp_path / name)
        stage(spark, docs, sf).write.parquet(out)
        before, docs = docs, spark.read.parquet(out)
        kept[name] = docs
        if name != "shard":
            assert docs.columns == before.columns
    rows = {r["doc_id"]: r["text"] for r in kept["language_id"].collect()}
    ids = sorted(rows)
    _, component = near([rows[i] for i in ids], k=5)
    assert {r["doc_id"] for r in kept["near_dedup"].collect()} == {ids[i] for i in range(len(ids)) if component[i] == i}
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    hit = {r["doc_id"] for r in decontaminate.overlaps(kept["near_dedup"], bench).collect()}
    assert hit and {r["doc_id"] for r in kept["decontaminate"].collect()} == {r["doc_id"] for r in kept["near_dedup"].collect()} - hit
    copies = collections.Counter(r["doc_id"] for r in kept["mix_sources"].collect())
    assert copies == collections.Counter(r["doc_id"] for r in mixing.mix(kept["decontaminate"]).collect())
    assert kept["shard"].count() == sum(copies.values())
    run = corpus_pipeline.run(spark, sf)
    assert collections.Counter(map(tuple, run.collect())) == collections.Counter(map(tuple, kept["shard"].collect()))


def test_stages_stand_odd_rows(spark, sf):
    import random

    rng = random.Random(1)
    texts = [" ".join(words(rng, 40)) for _ in range(6)]
    empty = docs_of(spark, texts).where("false")
    for docs in (odd(spark), empty):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, docs, sf)
            out.collect()
            if name != "shard":
                assert out.columns == docs.columns


def test_planted_passages_go_and_clean_ones_stay(spark, sf):
    bench = spark.createDataFrame([(1, ITEM)], "item_id long, text string")
    docs = docs_of(spark, ["a clean text of some words", f"so {ITEM} it is", "another clean one"])
    assert {r["doc_id"] for r in decontaminate.clean(docs, bench).collect()} == {0, 2}
