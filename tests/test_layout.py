"""Where rows lie: co-location, order, lengths, balance; the same answers for every partition count."""

import pytest
from pyspark.sql import functions as F

from framepatterns import collectives
from framepatterns.layout import hashing, ranges, rebalance, sampling
from framepatterns.measure.balance import balance
from framepatterns.model import Frame, Hashed, Ordered
from framepatterns.operators import ordering
from framepatterns.patterns import order_by_range, order_by_sample, shuffle_compute
from framepatterns.plans.explain import exchanges, single_partition


def numbers(spark, n, parts=5):
    return spark.range(0, n, 1, parts).select(F.col("id"), (F.col("id") * 7919 % 1013).alias("k"), (F.col("id") % 3).alias("g"))


def test_hash_pid_is_sparks_own(spark):
    df = numbers(spark, 500)
    dealt = df.withColumn("want", hashing.hash_pid(["k"], 7)).repartition(7, "k").withColumn("is", F.spark_partition_id())
    assert dealt.where("want <> is").count() == 0


def test_equal_rows_meet(spark):
    df = numbers(spark, 300)
    pid = hashing.hash_pid("*", 6, df)
    both = df.union(df).withColumn("p", pid)
    assert both.groupBy("id").agg(F.count_distinct("p").alias("n")).where("n > 1").isEmpty()


def test_split_counts_add_up(spark):
    df = numbers(spark, 400)
    assert hashing.split_counts(df, hashing.hash_pid(["k"], 4)).agg(F.sum("rows")).first()[0] == 400


@pytest.mark.parametrize("n,parts", [(0, 3), (1, 3), (1000, 1), (1000, 2), (1000, 7), (5, 16)])
def test_positions(spark, n, parts):
    df = numbers(spark, n)
    got = sorted((r["k"], r["id"], r["position"]) for r in rebalance.with_position(df, ["k", "id"], partitions=parts).collect())
    assert [p for _, _, p in got] == list(range(n))


def test_many_pivots_search(spark):
    df = numbers(spark, 2000)
    few = df.select(ranges.range_pid(F.col("k"), [10, 500], F.lit).alias("p")).groupBy("p").count().collect()
    assert {r[0] for r in few} == {0, 1, 2}
    pivots = list(range(0, 1000, 10))
    bad = df.withColumn("p", ranges.range_pid(F.col("k"), pivots, F.lit)).where(F.col("p") != F.least(F.floor(F.col("k") / 10) + 1, F.lit(100)))
    assert bad.isEmpty()


@pytest.mark.parametrize("parts", [1, 2, 7, 16])
def test_rebalance_equal_and_given(spark, parts):
    df = numbers(spark, 500)
    out = rebalance.rebalance(df, ["k", "id"], parts)
    lengths = rebalance.partition_lengths(out)
    assert sum(lengths) == 500 and max(lengths) - min(lengths) <= 1
    given = [100, 0, 250, 150]
    assert rebalance.partition_lengths(rebalance.rebalance(df, ["k", "id"], lengths=given)) == given
    with pytest.raises(ValueError):
        rebalance.rebalance(df, ["k", "id"], lengths=[1, 2])


@pytest.mark.parametrize("algorithm", ["range", "sample"])
def test_order_along_partitions(spark, algorithm):
    df = numbers(spark, 3000).where("k >= 0")
    f = order_by_range(df, "k", 6) if algorithm == "range" else order_by_sample(df, ["k", "id"], 6)
    assert isinstance(f.layout, Ordered)
    rows = [(r["p"], r["k"]) for r in f.df.withColumn("p", F.spark_partition_id()).collect()]
    assert [k for _, k in rows] == sorted(k for _, k in rows)
    assert balance(f.df).max_over_mean <= 2.0


def test_sketch_pivots_balance_skew(spark):
    df = spark.range(0, 4000).select((F.pow(F.col("id") / 4000, F.lit(8.0)) * 1e6).alias("k"))
    bins, sketch = balance(order_by_range(df, "k", 8, bins=16, sketch=False).df), balance(order_by_range(df, "k", 8).df)
    assert bins.max_over_mean < 1.3 and sketch.max_over_mean < 1.3


def test_strict_regular_sample(spark):
    s = sampling.regular_sample(numbers(spark, 5000, 4), [F.col("k")], 16, 4)
    assert abs(s.count() - 4 * 16) <= 5
    many = sampling.regular_sample(numbers(spark, 5000, 500), [F.col("id")], 16, 4).select("key.k0").toPandas().k0
    assert abs(many.count() - 64) <= 20 and abs(many.mean() - 2500) < 500  # short partitions are sampled evenly


SKEWED = {
    "three keys": lambda i: i % 3,
    "one key": lambda i: F.lit(7).cast("long"),
    "half hot": lambda i: F.when(i % 2 == 0, 500).otherwise(i),
    "outlier": lambda i: F.when(i == 77, 10**15).otherwise(i),
    "two outliers, hot": lambda i: F.when(i == 77, 10**15).when(i == 78, -(10**12)).when(i % 3 == 0, 4).otherwise(i),
}


@pytest.mark.parametrize("shape", sorted(SKEWED))
@pytest.mark.parametrize("how", ["sketch", "histogram", "sample"])
@pytest.mark.parametrize("label", [True, False])
def test_sort_of_few_hot_and_outlying_keys(spark, shape, how, label):
    df = spark.range(0, 40_000, 1, 5).select(SKEWED[shape](F.col("id")).cast("long").alias("k"), *(["id"] if label else []))
    f = order_by_sample(df, ["k"], 8) if how == "sample" else order_by_range(df, "k", 8, sketch=how == "sketch")
    rows = [(r["p"], r["k"]) for r in f.df.withColumn("p", F.spark_partition_id()).select("p", "k").collect()]
    assert [k for _, k in rows] == sorted(k for _, k in rows) and len(rows) == 40_000
    b = balance(f.df)
    assert len(b.lengths) == 8 and b.max_over_mean <= 2.0
    assert sorted(r[0] for r in df.select("k").collect()) == [k for _, k in rows]


def test_positions_of_hot_keys(spark):
    df = spark.range(0, 20_000, 1, 4).select((F.col("id") % 3).alias("k"), "id")
    out = rebalance.with_position(df, ["k"], partitions=8)
    assert balance(out).max_over_mean <= 2.0
    assert sorted(r[0] for r in out.select("position").collect()) == list(range(20_000))
    assert out.where(F.col("k") != F.least(F.floor(F.col("position") / 6667), F.lit(2))).count() < 3


def test_pivots_are_kept_and_used_again(spark, tmp_path):
    from framepatterns.patterns import deal_by_pivots
    from framepatterns.sources.sidecar import load_layout, save_layout

    f = order_by_sample(numbers(spark, 3000), ["k", "id"], 6)
    save_layout(spark, f"{tmp_path}/t", f.layout)
    layout = load_layout(spark, f"{tmp_path}/t")
    assert layout == f.layout and len(layout.pivots) == 5
    again = deal_by_pivots(numbers(spark, 1000).withColumn("x", F.lit(1)), layout).df
    ends = lambda d: {r.p: r for r in d.groupBy(F.spark_partition_id().alias("p")).agg(F.min("k").alias("lo"), F.max("k").alias("hi")).collect()}
    a, b = ends(f.df), ends(again)
    assert all(a[p].lo <= b[q].hi for q in b for p in a if p <= q) and len(b) == 6


def test_histogram_pivots_with_odd_numbers(spark):
    values = [float("nan"), float("inf"), float("-inf"), None, 1.7e308, -1.7e308, *map(float, range(200))]
    df = spark.createDataFrame([(v,) for v in values], "k double")
    for sketch in (True, False):
        got = [r[0] for r in order_by_range(df, "k", 4, sketch=sketch).df.collect()]
        assert got[:2] == [float("-inf"), -1.7e308] and got[-1] is None and got[-2] != got[-2] and len(got) == len(values)
    many = order_by_range(numbers(spark, 3000).withColumn("k", F.when(F.col("k") > 5, F.col("k"))), "k", 24).df
    assert [r.k for r in many.collect()][-1] is None


def test_halo_pattern(spark):
    from framepatterns.patterns import halo

    df = numbers(spark, 500)
    from pyspark.sql import window as W

    w = W.Window.partitionBy("_block").orderBy("_at").rowsBetween(-40, 25)
    got = halo(df, ["id"], 40, 25, lambda near: near.withColumn("s", F.sum("k").over(w)), block=1).df
    k = [i * 7919 % 1013 for i in range(500)]
    assert sorted((r.id, r.s) for r in got.collect()) == [(i, sum(k[max(i - 40, 0) : i + 26])) for i in range(500)]


def test_dealt_input_is_not_moved_again(spark):
    f = shuffle_compute([numbers(spark, 100)], ["k"], lambda d: d, 6)
    assert f.layout == Hashed(("k",), 6) and f.co_located(("k", "g"))
    again = shuffle_compute([f], ["k"], lambda d: d.groupBy("k").count(), 6)
    assert "not moved" in again.why[0]
    assert len([e for e in exchanges(again.df) if e.startswith("Exchange")]) == 1


def test_sort_edges(spark):
    for values in ([], [3], [1] * 50, [None, 2, None, 1]):
        df = spark.createDataFrame([(v,) for v in values], "k long")
        got = [r[0] for r in ordering.sort(df, ["k"], algorithm="range", partitions=4).df.collect()]
        assert got == sorted([v for v in values if v is not None]) + [None] * values.count(None)
    down = ordering.sort(numbers(spark, 100), ["id"], False, algorithm="range", partitions=4).df
    assert [r["id"] for r in down.collect()] == list(range(99, -1, -1))


def test_collectives(spark):
    df = collectives.scatter(spark, [(i,) for i in range(10)], "v long", 3)
    assert sorted(rebalance.partition_lengths(df)) == [3, 3, 4]
    assert collectives.gather(df).num_rows == 10
    with pytest.raises(MemoryError):
        collectives.gather(df, 5)
    with pytest.raises(MemoryError):
        collectives.all_gather(df, 5)
    assert collectives.all_reduce(df, F.sum("v").alias("s")).where("s <> 45").isEmpty()
    assert len(collectives.barrier_map(df.repartition(2), lambda it: it, "v long").collect()) == 10


def test_labels(spark):
    f = Frame(numbers(spark, 20)).to_labels("id", check=True)
    assert f.labels == ("id",) and f.rename({"id": "x"}).labels == ("x",)
    with pytest.raises(ValueError):
        Frame(numbers(spark, 20)).to_labels("g", check=True)
    assert f.from_labels(["id"]).labels == ("label",)


def test_no_single_partition_in_global_windows(spark):
    from framepatterns.operators import windows

    df = numbers(spark, 200)
    out = windows.rolling(df, ["id"], 5, {"s": lambda: F.sum("k")}, block=64)
    assert not single_partition(out)
