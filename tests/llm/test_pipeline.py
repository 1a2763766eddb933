"""The pipeline on the smallest tables, stage by stage."""

import corpus_pipeline
from sketchselect.llm import decontaminate, shingles

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_take_effect(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    seen = [docs]
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.written(stage(spark, docs, small), name)
        seen.append(docs)
    assert [d.columns for d in seen[:-1]] == [COLUMNS] * 5
    assert set(seen[-1].columns) == {*COLUMNS, "shard", "slot"}
    counts = [d.count() for d in seen]
    assert counts[0] >= counts[1] >= counts[2] >= counts[3] > 0 and counts[4] == counts[5]
    index = decontaminate.Index(items, 5, 0.8, 16)
    assert not any(index.search(r["text"]) for r in seen[3].collect())
    kept = [set(shingles.hashes(shingles.words(r["text"]), 5).tolist()) for r in seen[2].collect()]
    assert not any(len(a & b) >= 0.8 * len(a | b) for i, a in enumerate(kept) for b in kept[:i] if a or b)


def test_run_gives_the_last_stage(spark, small):
    assert corpus_pipeline.run(spark, small).count() > 0
