"""The corpus pipeline against plain Python, stage by stage."""

import collections
import re

import corpus_pipeline
from framepatterns.llm import registry

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def test_pipeline_stage_by_stage(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "mixing", "sharding"]
    at = docs
    for name, stage in corpus_pipeline.STAGES:
        before = at.collect()
        out = stage(spark, at, sf)
        rows = out.collect()
        had = {r.doc_id for r in before}
        assert {r.doc_id for r in rows} <= had
        if name == "near_duplicates":
            from test_contracts import brute_components

            want = brute_components([(r.doc_id, r.text, r.lang, r.source) for r in before], 5, 80)
            assert {r.doc_id for r in rows} == {d for d, (_, c) in want.items() if c == d}
        if name == "decontamination":
            items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            assert not any(x in r.text for r in rows for x in items)
            assert len(had) - len(rows) <= sum(any(x in r.text for x in items) for r in before) + 1
        if name == "mixing":
            taken, have = collections.Counter(), collections.Counter()
            for r in rows:
                taken[r.source] += len(WORDS.findall(r.text))
            for r in before:
                have[r.source] += len(WORDS.findall(r.text))
            assert abs(sum(taken.values()) - 1.5 * sum(have.values())) < 0.1 * sum(have.values())
            assert max(collections.Counter(r.doc_id for r in rows).values()) <= 2
        if name == "sharding":
            counts = collections.Counter(r.shard for r in rows)
            assert len(rows) == len(before) and max(counts.values()) - min(counts.values()) <= 1
            break
        assert out.columns == list(corpus_pipeline.COLUMNS)
        at = spark.createDataFrame(rows, out.schema)


def test_run_equals_its_stages(spark, sf):
    a = registry.pipeline(spark, sf).select("doc_id", "shard", "slot").collect()
    b = corpus_pipeline.run(spark, sf).select("doc_id", "shard", "slot").collect()
    assert sorted(a) == sorted(b) and len(a) > 0
