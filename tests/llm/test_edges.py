"""Nulls, empty and very long texts, ties, repeated rows, empty tables and clashing column names, for every operator and stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from framepatterns.llm import curve_shards, decontamination, licenses, near_duplicates, repeated_passages, secrets, source_mixing, toxicity, transcripts, vector_graph

LONG = " ".join(f"word{i % 977}x{i % 31}" for i in range(150_000))
ONE_WORD = "y" * 700_000
COPY = " ".join(f"c{i}" for i in range(40))
EXTRA = ("key", "n", "regs", "shard", "slot", "curve", "size", "copies", "target", "toxicity", "_key", "_d0", "a", "h", "doc", "pos", "spans", "license", "id", "u", "v")


def frame(spark, rows):
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumns({c: F.lit(7) for c in EXTRA})


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(1, None, "en", "a", None), (2, "", "en", "a", 0), (3, " \t\n ", None, None, 3), (None, COPY, "en", "b", 5), (5, COPY, "en", "b", 5), (6, COPY, "de", "b", 5), (6, COPY, "de", "b", 5), (7, "two words", "en", "c", 2), (8, "two words", "en", "c", 2), (9, LONG, "en", "a", 9), (10, ONE_WORD, "en", "a", 9), (11, "Ü\u0001\u0002 ok", "fr", None, 1)]
    return frame(spark, rows)


@pytest.fixture(scope="module")
def none(spark):
    return frame(spark, [])


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, COPY), (2, None), (3, ""), (4, "single"), (None, "x y z"), (1, COPY)], "item_id long, text string")


@pytest.fixture(scope="module")
def marks(spark):
    return spark.createDataFrame([(5, 1), (6, None), (None, 1), (7, 0), (7, 0), (99, 1)], "doc_id long, toxic int")


def test_shards(odd, none):
    rows = curve_shards.document_shards(odd, 3).collect()
    assert len(rows) == 12 and sorted(r.slot for r in rows) == sorted([*range(4)] * 3)
    assert next(r for r in rows if r.doc_id == 1).size == 8 and next(r for r in rows if r.doc_id == 1).text_crc32 == 0
    assert curve_shards.curve_shards(odd, 24).count() == 12
    assert curve_shards.document_shards(none).count() == 0


def test_near_duplicates(odd, none):
    got = {(r.doc_id, r.n_shingles, r.component_id, r.kept) for r in near_duplicates.near_duplicates(odd).collect()}
    assert {(1, 0, 1, True), (2, 0, 2, True), (3, 0, 3, True), (5, 37, 5, True), (6, 37, 5, False), (7, 1, 7, True), (8, 1, 7, False), (10, 1, 10, True)} <= got
    assert near_duplicates.near_duplicates(odd).count() == 12
    assert near_duplicates.near_duplicates(none).count() == 0


def test_toxicity(spark, odd, none, marks):
    rows = toxicity.toxicity(odd, marks).collect()
    assert len(rows) == 12 and all(0 <= r.score <= 1 for r in rows)
    assert len({r.score for r in rows if r.doc_id in (1, 2, 3)}) == 1
    assert toxicity.toxicity(none, marks).count() == 0
    assert toxicity.toxicity(odd, marks.limit(0)).count() == 12


def test_repeats(odd, none):
    got = [(r.doc_id, r.n_words, r.n_removed) for r in repeated_passages.remove_repeats(odd).collect()]
    assert {(1, 0, 0), (2, 0, 0), (3, 0, 0), (5, 40, 0), (7, 2, 0), (10, 1, 0), (None, 40, 0)} <= set(got)
    assert got.count((6, 40, 40)) == 2 and len(got) == 12
    assert repeated_passages.remove_repeats(none).count() == 0
    assert repeated_passages.doubled_repeats(none).count() == 0


def test_transcripts(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", None), (1, 1, "assistant", None), (None, 0, "user", "lost"), (2, None, None, "x"), (3, 0, "tool", ""), (4, 0, "user", "z\n" * 5000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumns({c: F.lit(1) for c in ("line", "pos", "k")})
    out = transcripts.format_conversations(df).collect()
    assert {r.conv_id for r in out} >= {1, None, 2, 4} and all(r.rendered.startswith("<|") for r in out)
    assert transcripts.format_conversations(df.limit(0)).count() == 0


def test_contamination(odd, none, items):
    got = {(r.doc_id, r.item_id) for r in decontamination.contaminated(odd, items).collect()}
    assert got == {(None, 1), (5, 1), (6, 1)}
    assert decontamination.contaminated(none, items).count() == 0
    assert decontamination.contaminated(odd, items.limit(0)).count() == 0
    assert decontamination.decontaminate(odd, items).count() == 8


def test_licenses(spark, odd, none):
    out = licenses.license_scan(licenses.document_paths(odd)).collect()
    assert len(out) == 12 and all(r.license is None for r in out)
    assert licenses.license_scan(licenses.document_paths(none)).count() == 0
    null_path = spark.createDataFrame([(1, None, "Released under the MIT License."), (1, None, None)], "doc_id long, path string, text string")
    assert [r.license for r in licenses.license_scan(null_path).collect()] == ["MIT", "MIT"]


def test_secrets(odd, none):
    assert secrets.secret_digest(odd).count() == 12
    assert secrets.secret_digest(none).count() == 0


def test_mixing(odd, none):
    out = source_mixing.mix_sources(odd).collect()
    assert len(out) == 12 and all(r.copies * r["size"] <= 2 * r["size"] for r in out)
    assert {r.copies for r in out if r.doc_id == 6} in ({0}, {1}, {2})
    assert source_mixing.mix_sources(none).count() == 0 and source_mixing.mix_plan(none).count() == 0


def test_vectors(spark):
    v = [1.0, 0.0, 0.5]
    rows = [(1, 1, v), (2, 1, v), (3, None, v), (4, 2, v), (5, 1, None), (6, 1, [0.0, 0.0, 0.0]), (7, 1, [float("nan"), 1.0, 1.0]), (8, 1, [float("inf"), 1.0, 1.0]), (9, 1, [None, 1.0, 1.0]), (10, 1, [1.0, 0.0]), (2, 1, v), (11, 1, []), (None, 1, v)]
    df = spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").withColumns({c: F.lit(1) for c in ("shard", "dim", "asks", "id")})
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vector_graph.near_vectors(df).collect()}
    assert got[1] == (1, 1, True) and got[2] == (1, 1, False)
    assert all(got[i] == (0, i, True) for i in (3, 4, 5, 6, 7, 8, 9, 10, 11)) and got[None][0] == 0
    assert vector_graph.near_vectors(df.limit(0)).count() == 0


def test_stages_on_odd_rows(spark, odd, none, items, marks, tmp_path):
    d = str(tmp_path)
    items.write.parquet(f"{d}/benchmark.parquet")
    marks.write.parquet(f"{d}/labels.parquet")
    for name, stage in corpus_pipeline.STAGES:
        for df in (odd, none):
            out = stage(spark, df, d)
            if name != corpus_pipeline.STAGES[-1][0]:
                assert out.columns == list(corpus_pipeline.COLUMNS)
            out.collect()
