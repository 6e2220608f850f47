"""The pipeline's stages against brute force."""

from collections import Counter

import corpus_pipeline
from test_ops import brute_components, brute_leaks

SF = "/root/testdata/sf0.001"


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    at, rows = {}, {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        at[name] = docs.columns
        docs = spark.read.parquet(str(tmp_path / name))
        rows[name] = [(r["doc_id"], r["text"]) for r in docs.collect()]
        if name != "sharding":
            assert docs.columns == at["language_id"]
    before = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    lettered = {d for d, t in before if any(c.isalpha() for c in t or "")}
    assert {d for d, _ in rows["language_id"]} == lettered
    groups = brute_components(rows["language_id"], 5, 80)
    assert Counter(d for d, _ in rows["near_dup"]) == Counter({c for _, c in groups.values()})
    bad = {d for d, _ in brute_leaks(rows["near_dup"], items)}
    assert {d for d, _ in rows["decontamination"]} == {d for d, _ in rows["near_dup"]} - bad
    assert max(Counter(d for d, _ in rows["mixing"]).values()) <= 3
    assert Counter(rows["sharding"]) == Counter(rows["mixing"])


def test_run_is_the_stages(spark):
    got = corpus_pipeline.run(spark, SF)
    assert {"doc_id", "text", "shard", "slot"} <= set(got.columns) and got.count() > 0
