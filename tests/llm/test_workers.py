"""What Python workers hold during and after the tasks of the pipeline."""

import re
import sys
import tracemalloc
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest

import corpus_pipeline
from framepatterns.llm import scratch, toxicity


def test_stages_give_memory_back_and_use_one_pool(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kind, ran = type(docs), []
    plain = kind.mapInArrow
    monkeypatch.setattr(kind, "mapInArrow", lambda self, run, *a, **b: (ran.append(run.__qualname__), plain(self, run, *a, **b))[1])

    def second_pool(*_, **__):
        raise AssertionError("rows of a Python list go through workers of their own")

    monkeypatch.setattr(type(spark), "_create_dataframe", second_pool)
    for stage in (corpus_pipeline.drop_toxic, corpus_pipeline.drop_near_duplicates):
        assert stage(spark, docs, sf).count() > 0
    assert len(ran) >= 8 and all(x.startswith("map_batches") for x in ran)


def test_packing_holds_few_copies_of_its_pairs():
    words = np.random.default_rng(1).integers(0, 36**4, 1_400_000)
    rows = [" ".join(np.base_repr(x, 36) for x in part) for part in np.array_split(words, 1400)]
    batches = [pa.RecordBatch.from_arrays([pa.array(rows[a : a + 100])], names=["text"]) for a in range(0, 1400, 100)]
    hot = np.sort(toxicity.pair_key(np.arange(1000, dtype=np.uint64), np.uint64(1)))
    tracemalloc.start()
    try:
        sent = sum(sum(map(len, b.column("contexts").to_pylist())) for b in toxicity._contexts(iter(batches), 12, hot))
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert sent >= 5 * 1_390_000
    assert peak < 12 * 8 * toxicity.HELD_PAIRS


@pytest.mark.skipif(not sys.platform.startswith("linux"), reason="reads /proc")
def test_a_task_that_ended_holds_nothing():
    held = lambda: int(re.search(r"RssAnon:\s+(\d+)", Path("/proc/self/status").read_text())[1]) >> 10
    pinned = []

    def run(batches):
        blocks = []
        for batch in batches:
            for _ in range(4000):
                blocks.append(b"x" * (50 << 10))
            pinned.append(b"y" * 1000)
            yield batch

    class Rows:
        def mapInArrow(self, run, schema):
            return run

    before = held()
    assert list(scratch.map_batches(Rows(), run, "x long")(iter([1]))) == [1]
    assert held() - before < 60


def test_words_are_found_in_sorted_few():
    few, values = np.array([2, 5, 9], np.uint64), np.array([0, 2, 3, 9, 10, 5], np.uint64)
    assert toxicity._among(values, few).tolist() == [False, True, False, True, False, True]
    assert not toxicity._among(values, few[:0]).any()
