"""Operators with several patterns give one answer; edge frames; semantics flags; measures and choices."""

import pytest
from pyspark.sql import functions as F

from framepatterns.baselines import broadcast_only, brute
from framepatterns.measure import coverage
from framepatterns.measure.shuffle_volume import shuffle_volume
from framepatterns.measure.timing import Run, efficiency, speed_up, strong_scaling, timed
from framepatterns.operators import columnagg, grouping, joining, ordering, reshape, windows
from framepatterns.operators.aggregates import classify
from framepatterns.plans import cardinality, choose, cost
from framepatterns.sources import readers, sidecar, writers
from framepatterns.workloads.frames import bench_a, table


def bag(df):
    return sorted(repr(tuple(r)) for r in df.collect())


EDGES = {"empty": [], "one": [(1, 2.0)], "same key": [(7, float(i)) for i in range(30)], "distinct": [(i, 1.0) for i in range(30)], "nulls": [(None, 1.0), (1, None), (None, None), (1, 3.0)], "negative": [(-i, float("nan") if i % 5 == 0 else 1.0) for i in range(20)]}


@pytest.mark.parametrize("name", EDGES)
def test_group_patterns_agree(spark, name):
    df = spark.createDataFrame(EDGES[name], "k long, v double")
    aggs = {"n": ("v", "count"), "s": ("v", "sum"), "m": ("v", "median")}
    want = bag(grouping.groupby(df, ["k"], aggs, "combine").df)
    assert bag(grouping.groupby(df, ["k"], aggs, "shuffle", partitions=7).df) == want
    assert bag(grouping.groupby(df, ["k"], aggs, "auto").df) == want
    few = {"n": ("v", "count"), "hi": ("v", "max")}
    assert bag(grouping.groupby(df, ["k"], few, "combine", salt=3).df) == bag(grouping.groupby(df, ["k"], few, "combine").df)


@pytest.mark.parametrize("how", ["inner", "left", "left_semi", "left_anti"])
def test_join_forms_agree(spark, how):
    l = spark.createDataFrame([(i % 5 if i % 7 else None, i) for i in range(60)], "k long, a long")
    r = spark.createDataFrame([(i, i * 10) for i in range(3)] + [(None, 5)], "k long, b long")
    want = bag(l.join(r, "k", how))
    assert bag(joining.join(l, r, ["k"], how, algorithm="sort").df) == want
    assert bag(joining.join(l, r, ["k"], how, algorithm="hash").df) == want
    assert bag(joining.join(l, r, ["k"], how, partitions=5).df) == want
    assert bag(joining.broadcast_join(l, r, ["k"], how).df) == want
    assert bag(joining.join_auto(l, r, ["k"], how).df) == want
    assert bag(joining.salted_join(l, r, ["k"], how, salts=3, share=0.05)) == want


def test_broadcast_refuses_to_keep_the_replicated_side(spark):
    df = spark.range(3).withColumnRenamed("id", "k")
    for how in ("right", "outer", "full_outer"):
        with pytest.raises(ValueError):
            joining.broadcast_join(df, df, ["k"], how)
    with pytest.raises(broadcast_only.MemoryGuard):
        broadcast_only.join(df, df, ["k"], limit=1)


def test_null_keys_can_match(spark):
    df = spark.createDataFrame([(None, 1), (2, 2)], "k long, v long")
    assert joining.join(df, df, ["k"], null_keys="match").df.count() == 2
    assert joining.join(df, df, ["k"]).df.count() == 1


def test_outer_join_with_other_names(spark):
    a, b = spark.createDataFrame([(1, "a")], "x long, s string"), spark.createDataFrame([(2, "b")], "y long, t string")
    assert bag(joining.join(a, b, [("x", "y")], "outer").df) == ["(1, 'a', None)", "(2, None, 'b')"]


@pytest.mark.parametrize("keep", ["first", "last", "none", "any"])
def test_unique(spark, keep):
    df = spark.createDataFrame([(1, 1), (1, 2), (2, 3), (None, 4), (None, 5)], "k long, at long")
    out = grouping.unique(df, ["k"], keep, "at").df
    if keep == "any":
        assert out.count() == 3 and grouping.unique(df, ["k"], pattern="shuffle").df.count() == 3
    else:
        want = {"first": [(1, 1), (2, 3), (None, 4)], "last": [(1, 2), (2, 3), (None, 5)], "none": [(2, 3)]}[keep]
        assert bag(out) == sorted(map(repr, want))


@pytest.mark.parametrize("n,k,block", [(0, 3, 16), (1, 3, 16), (100, 1, 10), (100, 7, 10), (100, 90, 8), (50, 60, 8)])
def test_rolling_equals_brute_force(spark, n, k, block):
    df = spark.range(0, n, 1, 3).select("id", (F.col("id") * 37 % 11).alias("v"))
    got = {r["id"]: r["s"] for r in windows.rolling(df, ["id"], k, {"s": lambda: F.sum("v")}, block=block).collect()}
    want = brute.rolling([i * 37 % 11 for i in range(n)], k, sum)
    assert [got[i] for i in range(n)] == want


def test_expanding_and_shift_over_many_blocks(spark):
    df = spark.range(0, 200, 1, 3).select("id", F.when(F.col("id") % 4 != 0, F.col("id") * 13 % 29).alias("v"))
    got = {r["id"]: (r["s"], r["m"]) for r in windows.expanding(df, ["id"], {"s": ("v", "sum"), "m": ("v", "mean")}, block=16).collect()}
    run, cnt = 0, 0
    for i in range(200):
        if i % 4:
            run, cnt = run + i * 13 % 29, cnt + 1
        assert got[i] == ((run, run / cnt) if cnt else (None, None))
    s = {r["id"]: r["x"] for r in windows.shift(df, ["id"], "id", -3, "x", block=16).collect()}
    assert s[0] == 3 and s[196] == 199 and s[197] is None


def test_rank_methods(spark):
    values = [5, 3, 3, 9, 5, 5, 1]
    df = spark.createDataFrame(list(enumerate(values)), "i long, v long")
    dense = {r["i"]: r["rank"] for r in ordering.rank(df, ["v"], "dense", partitions=3).collect()}
    assert [dense[i] for i in range(7)] == brute.rank_dense(values)
    low = {r["i"]: r["rank"] for r in ordering.rank(df, ["v"], "min", partitions=3).collect()}
    assert [low[i] for i in range(7)] == [1 + sum(x < v for x in values) for v in values]


def test_transpose_forms(spark):
    df = spark.createDataFrame([(i, i * 2, i * 3) for i in range(10)], "r long, a long, b long")
    cells = {(r[0], r[1]): r[2] for r in reshape.transpose(df, "r").collect()}
    wide = {r["column"]: r.asDict() for r in reshape.transpose(df, "r", "wide").collect()}
    blocks = {(r[0], r[1]): r[2] for r in reshape.transpose(df, "r", "blocks", block=4).collect()}
    assert all(wide[c][str(i)] == v for (c, i), v in cells.items())
    assert blocks["b", 1] == [12, 15, 18, 21]
    with pytest.raises(ValueError):
        reshape.transpose(df, "r", "wide", max_columns=5)


def test_equality_sees_counts_and_values(spark):
    a = spark.createDataFrame([(1, "x"), (1, "x"), (2, None)], "k long, s string")
    assert columnagg.frames_equal(a, a.repartition(3))
    assert not columnagg.frames_equal(a, a.distinct())
    assert not columnagg.frames_equal(a, a.where("k = 1"))
    assert columnagg.frames_equal_ordered(a.select("k"), a.select("k"), ["k"])


def test_combine_writes_less_where_keys_are_few(spark, sf):
    for c, better in ((0.9, "shuffle"), (1e-5, "combine")):
        f = bench_a(spark, sf, c).repartition(4).cache()
        n = f.count()
        aggs = {"s": ("v", "sum")}
        hashed = shuffle_volume(grouping.groupby(f, ["k"], aggs, "shuffle").df)
        combined = shuffle_volume(grouping.groupby(f, ["k"], aggs, "combine").df)
        assert hashed.rows == n and combined.rows <= n
        assert choose.choose_group_pattern(f, ["k"]).pattern == better
        if better == "combine":
            assert combined.rows < n / 100
        f.unpersist()


def test_estimates(spark, sf):
    li = table(spark, sf, "lineitem")
    exact, sketch = cardinality.cardinality(li, ["l_orderkey"], "exact"), cardinality.cardinality(li, ["l_orderkey"])
    assert abs(exact - sketch) < 0.03 * exact
    assert abs(cardinality.modelled_ratio(600_000, 20_000, 4) - 0.133) < 0.01
    s = grouping.groupby(li, ["l_returnflag"], {"n": ("l_partkey", "nunique_approx")}, "combine").df
    want = dict(li.groupBy("l_returnflag").agg(F.count_distinct("l_partkey")).collect())
    assert all(abs(n - want[k]) < 0.15 * want[k] for k, n in s.collect())


def test_choices(spark):
    assert classify(["sum", "median"]) == "holistic" and classify(["sum", "mean"]) == "algebraic"
    assert choose.choose_group_pattern(None, [], "holistic").pattern == "shuffle"
    assert choose.choose_sort(["a"], {"a": "bigint"}).pattern == "range"
    assert choose.choose_sort(["a"], {"a": "string"}).pattern == "sample"
    assert cost.cheaper_group_pattern(10**9, 256, 0.999) == "shuffle" and cost.cheaper_group_pattern(10**9, 256, 1e-5) == "combine"
    assert coverage.coverage_share() > 0.6


def test_timing_records_failure(spark):
    assert timed(lambda: spark.range(10), 1).completed
    bad = timed(lambda: spark.range(3).select(F.raise_error(F.lit("no"))), 1)
    assert not bad.completed and bad.failure
    assert speed_up(Run(4.0), Run(2.0)) == 2.0 and efficiency(Run(4.0), Run(2.0), 4) == 0.5
    assert set(strong_scaling(lambda p: spark.range(0, 100, 1, p), [1, 2], 1)) == {1, 2}


def test_layout_travels_with_files(spark, tmp_path):
    from framepatterns.model import Hashed, Ordered

    for layout in (Hashed(("a", "b"), 8), Ordered(("k",), (1, 5), 3)):
        sidecar.save_layout(spark, str(tmp_path / "t"), layout)
        assert sidecar.load_layout(spark, str(tmp_path / "t")) == layout


def test_io_guards(spark, tmp_path, sf):
    with pytest.raises(ValueError):
        readers.read_partitioned(spark, str(tmp_path), "csv")
    with pytest.raises(MemoryError):
        writers.write_single(spark.range(100), str(tmp_path / "x"), limit=10)
    assert readers.assign_evenly(list("abcde"), 2) == {0: ["a", "b", "c"], 1: ["d", "e"]}
    assert readers.read_local(spark, f"{sf}/region.parquet", 2).count() == 5
    writers.write_partitioned(spark.range(0, 10, 1, 3), str(tmp_path / "p"))
    assert len(list((tmp_path / "p").glob("*.parquet"))) == 3


def test_stream_late_rows_and_batches(spark, tmp_path):
    from framepatterns.streaming import streams

    rows = [("2024-01-01 00:00:00", 1), ("2024-01-01 05:00:00", 1)]
    src = tmp_path / "in"
    for i, r in enumerate([rows, [("2024-01-01 00:10:00", 1)], [("2024-01-01 09:00:00", 1)]]):
        spark.createDataFrame(r, "t string, v int").select(F.to_timestamp("t").alias("ts"), "v").coalesce(1).write.mode("append").parquet(str(src))
        del i
    s = streams.file_stream(spark, str(src), "ts timestamp, v int", files_per_batch=1)
    agg = streams.tumbling(s, "ts", "1 hour", [], [F.count("*").alias("n")])
    out = streams.run_to_end(agg, "append")
    assert out.agg(F.sum("n")).first()[0] <= 4
    seen = []
    streams.to_batches(s, lambda df, i: seen.append(df.count()))
    assert sum(seen) == 4
    with pytest.raises(NotImplementedError):
        ordering.sort(s, ["v"], algorithm="range")


@pytest.mark.parametrize("closed", ["right", "left", "both", "neither"])
@pytest.mark.parametrize("keys", [None, ["g"]])
def test_time_windows_by_their_ends(spark, closed, keys):
    at = [0, 1, 1, 4, 10, 11, 25, 40, 41]
    df = spark.createDataFrame([(i, t, 0) for i, t in enumerate(at)], "i long, t long, g long").withColumn("ts", F.timestamp_micros("t"))
    got = {r["i"]: r["n"] for r in windows.rolling_time(df, "ts", 10, {"n": lambda: F.count("*")}, keys=keys, closed=closed, bucket_micros=7).collect()}
    test = {"right": lambda x, t: t - 10 < x <= t, "left": lambda x, t: t - 10 <= x < t, "both": lambda x, t: t - 10 <= x <= t, "neither": lambda x, t: t - 10 < x < t}[closed]
    assert got == {i: sum(test(x, t) for x in at) for i, t in enumerate(at)}


def test_explain_tells_pattern_and_layout(spark):
    df = spark.range(100).select((F.col("id") % 3).alias("k"), "id")
    text = grouping.groupby(df, ["k"], {"n": ("id", "count")}).explain()
    assert "combine-shuffle-reduce" in text and "choice: combine" in text and "exchange: Exchange hashpartitioning" in text


def test_rolling_state_crosses_batches(spark, tmp_path):
    from framepatterns.streaming import streams

    for i in range(3):
        spark.createDataFrame([(1, 2 * i, 10), (1, 2 * i + 1, 10), (2, i, 1)], "k long, at long, v long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    s = streams.file_stream(spark, str(tmp_path / "in"), "k long, at long, v long", files_per_batch=1)
    out = streams.run_to_end(streams.rolling_by_key(s, "k", "at", "v", 4), "append")
    got = {(r.k, r.at): r.rolled for r in out.collect()}
    assert len(got) == 9 and sorted(v for (k, _), v in got.items() if k == 1) == [10, 20, 30, 40, 40, 40]


def test_coverage_names_have_functions():
    found = coverage.served()
    assert all(callable(f) or isinstance(f, property) for f in found.values()) and len(found) == sum(n for _, n in coverage.coverage())


def test_assigned_files_by_full_name(spark, tmp_path, monkeypatch):
    """Equal base names, blanks and signs in paths; with a plan node a worker and by file names."""
    import pyarrow as pa
    import pyarrow.parquet as pq

    from framepatterns.sources import readers

    files = {}
    for w, folder in enumerate(("a", "b c", "d+e%20f", None, "a/deep")):
        if folder:
            (tmp_path / folder).mkdir(parents=True, exist_ok=True)
            pq.write_table(pa.table({"x": list(range(10 * w, 10 * w + 3))}), tmp_path / folder / "part-0")
            files[w] = [str(tmp_path / folder / "part-0")]
    want = sorted((x, w) for w in files for x in range(10 * w, 10 * w + 3))
    for many in (64, 0):
        monkeypatch.setattr(readers, "MANY_WORKERS", many)
        out = readers.read_assigned(spark, files).withColumn("p", F.spark_partition_id())
        rows = out.collect()
        assert sorted((r.x, r.worker) for r in rows) == want and all(r.p == r.worker for r in rows)
    with pytest.raises(ValueError):
        readers.read_assigned(spark, {0: files[0], 1: files[0]})


def test_left_side_is_replicated(spark):
    from framepatterns.plans.explain import exchanges

    small, big = spark.range(10).select("id", F.lit("s").alias("s")), spark.range(100_000).select((F.col("id") % 20).alias("id"), F.lit("b").alias("b"))
    for how, rows in (("inner", 50_000), ("right", 100_000)):
        assert choose.choose_join_pattern(small, big, how, 4).side == "left"
        out = joining.join_auto(small, big, ["id"], how)
        assert not [e for e in exchanges(out.df) if e.startswith("Exchange")] and out.df.count() == rows
    assert choose.choose_join_pattern(small, big, "left", 4).pattern == "shuffle"
    assert choose.choose_join_pattern(small, big, "outer", 4).pattern == "shuffle"


def test_asof_of_hot_groups(spark):
    """Slices of time carry the last right row on; nulls in the key are a group."""
    import random

    rng = random.Random(3)
    right = [(rng.choice([1, 1, 1, 2, None]), rng.randrange(500), i) for i in range(300)]
    left = [(rng.choice([1, 1, 1, 2, 3, None]), rng.randrange(500), i) for i in range(300)]
    l, r = spark.createDataFrame(left, "g long, t long, i long"), spark.createDataFrame(right, "g long, t long, v long")
    want = []
    for g, t, i in left:
        near = [(b, v) for a, b, v in right if a == g and b <= t]
        want.append((i, max(near)[1] if near else None))
    for slices in (0, 1, 7, 40):
        got = joining.asof_join(l, r, ["g"], "t", ["v"], tie="v", slices=slices)
        assert sorted((x.i, x.asof_v) for x in got.collect()) == sorted(want), slices


def test_ratio_reads_few_partitions(spark, tmp_path):
    """Only the chosen partitions' tasks run."""
    spark.range(0, 4000, 1, 40).select((F.col("id") % 7).alias("k")).write.parquet(f"{tmp_path}/t")
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        seen.add(1)
        yield from batches

    df = spark.range(0, 4000, 1, 40).select((F.col("id") % 7).alias("k")).mapInArrow(count, "k long")
    assert abs(cardinality.combine_ratio(df, ["k"], splits=4) - 0.07) < 1e-9 and seen.value == 4
    assert cardinality.combine_ratio(df, ["k"], splits=4) == cardinality.combine_ratio(df, ["k"], splits=4) and seen.value == 4


def test_quantile_sketch_is_close(spark):
    from framepatterns.operators import columnagg

    df = spark.range(20_000).select((F.col("id") * 7919 % 20_011).alias("x"))
    assert abs(columnagg.column_agg(df, {"m": ("x", "quantile_approx")}).first().m - 10_005) < 100


def test_streams_refuse_what_needs_all_rows(spark, sf):
    from framepatterns.operators import reshape
    from framepatterns.streaming import streams

    s = streams.table_stream(spark, sf, "events").select("event_id", "value")
    for fn in (lambda: windows.rolling(s, ["event_id"], 3, {"n": lambda: F.count("*")}), lambda: ordering.sort(s, ["event_id"], algorithm="range"), lambda: ordering.sort(s, ["event_id"], algorithm="sample"), lambda: reshape.transpose(s, "event_id", "blocks")):
        with pytest.raises(NotImplementedError):
            fn()


def test_transpose_pattern_applies_the_operator(spark):
    from framepatterns.patterns import transpose_compute

    df = spark.range(25).select("id", (F.col("id") * 2).alias("a"), (F.col("id") * 3).alias("b"))
    out = transpose_compute(df, "id", lambda v: F.transform(v, lambda x: x + 1), block=10).df
    got = {(r.column, r.block): r["values"] for r in out.collect()}
    assert got["a", 2] == [2 * i + 1 for i in range(20, 25)] and got["b", 0] == [3 * i + 1 for i in range(10)] and len(got) == 6
