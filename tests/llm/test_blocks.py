"""Building blocks: word hashing, sliding minima, bit sets, components, native plans."""

import re

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from framepatterns.llm import registry
from framepatterns.llm.components import connected_components
from framepatterns.llm.scratch import Scratch, bitmap, test_bits
from framepatterns.llm.words import grams, hashed_rows, shingle_set, sliding_min

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text("abAB é \t\n\x0b|", max_size=60)), max_size=8), st.integers(1, 40))
def test_words_are_the_patterns(texts, block):
    """The same words get the same hashes, wherever they stand and however rows are cut into blocks."""
    seen: dict[str, int] = {}
    rows = 0
    for row, end, h, w in hashed_rows(pa.array(texts, pa.string()), block=block):
        for i in range(end - row):
            words = WORDS.findall(texts[row + i] or "")
            mine = h[w[i] : w[i + 1]]
            assert len(words) == mine.size
            for x, v in zip(words, mine, strict=True):
                assert seen.setdefault(x, int(v)) == int(v)
        rows += end - row
    assert rows == len(texts) and len(set(seen.values())) == len(seen)


def test_sliced_and_wide_columns():
    texts = pa.array(["a b", "c", None, "d e f"] * 3)
    want = [h.tolist() for _, _, h, _ in hashed_rows(texts.slice(4, 4))]
    assert want == [h.tolist() for _, _, h, _ in hashed_rows(texts.slice(4, 4).cast(pa.large_string()))]
    assert sum(map(len, want)) == 6


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 1000), min_size=1, max_size=40), st.integers(1, 12))
def test_sliding_min(x, w):
    if len(x) >= w:
        assert sliding_min(np.array(x), w).tolist() == [min(x[i : i + w]) for i in range(len(x) - w + 1)]


def test_shingles():
    h = next(iter(hashed_rows(pa.array(["a b c d a b c d e"]))))[2]
    assert shingle_set(h, 4).size == 5 and shingle_set(h[:3], 4).size == 1 and shingle_set(h[:0], 4).size == 0
    assert grams(h, 4)[0] == grams(h, 4)[4] and grams(np.tile(h, 20), 100).size == 81


def test_bit_sets_have_no_false_negatives(spark):
    keys = [(int(x),) for x in np.random.default_rng(1).integers(-(1 << 62), 1 << 62, 500)]
    bits = bitmap(spark.createDataFrame(keys, "k long"), "k", 12)
    assert test_bits(bits, np.array([k for k, in keys], np.int64).view(np.uint64)).all()
    assert not bitmap(spark.createDataFrame([], "k long"), "k", 12).any()


test_bits.__test__ = False


@pytest.mark.parametrize("few", [1 << 22, 0])
@pytest.mark.parametrize("shape", ["path", "star", "random", "loops", "empty"])
def test_components(spark, shape, few, monkeypatch):
    from framepatterns.llm import components

    monkeypatch.setattr(components, "FEW_EDGES", few)
    rng = np.random.default_rng(4)
    edges = {
        "path": [(i, i + 1) for i in range(150)],
        "star": [(500, i) for i in range(400)],
        "random": [tuple(map(int, rng.integers(0, 300, 2))) for _ in range(220)],
        "loops": [(1, 1), (2, 3), (3, 2), (2, 3), (None, 4)],
        "empty": [],
    }[shape]
    up: dict = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        if a is not None and b is not None and a != b:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    got = {r.id: r.component for r in connected_components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark, "t")).collect()}
    assert got == {x: root(x) for x in up}


def test_native_operators_run_no_python(spark, sf):
    from framepatterns.plans.explain import python_nodes

    for name in ("op1_hilbert_shards", "op7_license_scan", "op8_secret_scan"):
        assert python_nodes(registry.queries()[name](spark, sf)) == []
