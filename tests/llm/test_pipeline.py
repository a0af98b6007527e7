"""The pipeline's stages on small tables."""

import re

import corpus_pipeline as P
from tests.llm.test_pairs import shingles


def test_stages_in_order_and_effective(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    for i, (name, stage) in enumerate(P.STAGES):
        before = docs.count()
        docs = stage(spark, docs, small).persist()
        n = docs.count()
        if i < 3:
            assert docs.columns == columns and 0 < n <= before
        if name == "near_dedup":
            sets = [shingles(r.text) for r in docs.collect()]
            for a in range(len(sets)):
                for b in range(a):
                    u = len(sets[a] | sets[b])
                    assert not u or len(sets[a] & sets[b]) / u < 0.8
        if name == "decontamination":
            items = [shingles(r.text) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
            for r in docs.collect():
                s = shingles(r.text)
                assert all(len(q & s) < 0.8 * len(q) for q in items)
    assert {"doc_id", "shard", "slot"} <= set(docs.columns)


def test_run_returns_the_last_stage(spark, small):
    out = P.run(spark, small)
    assert out.count() > 0 and re.match("doc_id", out.columns[0])
