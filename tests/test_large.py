"""Queries on tables larger than the smallest ones, where sampling, pieces and memory begin to matter."""

import pytest
from pyspark.sql import functions as F

from framepatterns import catalog
from framepatterns.baselines import broadcast_only, serial
from framepatterns.plans import cardinality


@pytest.fixture
def uncoalesced(spark):
    """Every shuffle partition stays by itself, as in large tables."""
    key = "spark.sql.adaptive.coalescePartitions.enabled"
    before = spark.conf.get(key)
    spark.conf.set(key, "false")
    yield
    spark.conf.set(key, before)


def orders(spark, folder, n=30_000):
    """More rows than the engine's sort draws for its pivots, so that it draws others each time."""
    o = spark.range(n).select((F.col("id") * 7919 % n).alias("o_orderkey"), F.concat(F.lit("p"), F.col("id") % 5).alias("o_orderpriority"))
    o.coalesce(1).write.parquet(f"{folder}/orders.parquet")
    return [(r.o_orderpriority, r.o_orderkey) for r in o.collect()]


def positions(df):
    return [r.o_orderkey for r in sorted(df.collect(), key=lambda r: r["at"])], sorted(r["at"] for r in df.collect())


def test_native_sort_is_numbered_in_one_order(spark, tmp_path, uncoalesced):
    want = sorted(k for _, k in orders(spark, tmp_path))
    keys, at = positions(catalog.queries()["sort_native"](spark, str(tmp_path)))
    assert at == list(range(len(want))) and keys == want


def test_native_sort_of_several_keys_is_numbered_in_one_order(spark, tmp_path, uncoalesced):
    rows = sorted(orders(spark, tmp_path), key=lambda r: r[1])
    want = [k for _, k in sorted(rows, key=lambda r: r[0], reverse=True)]
    keys, at = positions(catalog.queries()["sort_multikey"](spark, str(tmp_path)))
    assert at == list(range(len(want))) and keys == want


def lineitem(spark, folder, sf, n=20_000):
    """Some lines repeated, with nulls in the columns that keys and values are made of."""
    li = spark.read.parquet(f"{sf}/lineitem.parquet").limit(2_000).crossJoin(spark.range(n // 2_000))
    null = lambda c, every: F.when(F.col("l_suppkey") % every == 0, None).otherwise(F.col(c)).alias(c)
    changed = {c: null(c, m) for c, m in (("l_orderkey", 5), ("l_linenumber", 3), ("l_partkey", 4))}
    li.select(*[changed.get(c, F.col(c)) for c in li.columns if c != "id"]).coalesce(1).write.parquet(f"{folder}/lineitem.parquet")


def by_sql(folder, name):
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{folder}/lineitem.parquet/*.parquet')")
    return con.execute(catalog.oracles()[name]).fetchall()


def test_serial_group_brings_no_rows_to_the_driver(spark, sf, tmp_path, monkeypatch):
    lineitem(spark, tmp_path, sf)
    cls = type(spark.range(1))
    with monkeypatch.context() as m:
        for way in ("toPandas", "toArrow", "collect", "toLocalIterator"):
            m.setattr(cls, way, lambda *a, **k: pytest.fail("rows at the driver"))
        df = catalog.queries()["b1_serial_groupby"](spark, str(tmp_path))
    assert sorted(map(repr, map(tuple, df.collect()))) == sorted(map(repr, by_sql(tmp_path, "b1_serial_groupby")))


def test_serial_sums_of_pieces_add_up():
    import pyarrow as pa

    keys = [None if i % 11 == 0 else 7 if i % 2 else i % 13 for i in range(5_000)]
    values = [None if k == 4 or i % 3 == 0 else (1 << 60) + i if i < 3 else i for i, k in enumerate(keys)]
    batches = pa.table({"k": pa.array(keys, pa.int64()), "v": pa.array(values, pa.int64())}).to_batches(max_chunksize=100)
    want = {k: None if all(v is None for v in vs) else sum(v for v in vs if v is not None) for k in set(keys) for vs in [[v for x, v in zip(keys, values) if x == k]]}
    parts = [t for t in serial.sums_of_pieces(iter(batches), 700)]
    assert len(parts) == 8
    got = pa.Table.from_batches(serial.total_sums(b for t in parts for b in t.to_batches())).to_pylist()
    assert {r["k"]: r["v"] for r in got} == want and len(got) == len(want)


@pytest.fixture
def replicated(monkeypatch):
    """At most 500 rows of two numbers at once; the rows of each frame that is replicated."""
    monkeypatch.setattr(broadcast_only, "AT_ONCE", 32 * 500, raising=False)
    sizes, real = [], F.broadcast

    def seen(df):
        sizes.append(df.count())
        return real(df)

    monkeypatch.setattr(broadcast_only.F, "broadcast", seen)
    return sizes


def test_broadcast_only_join_replicates_pieces(spark, sf, same_as_sql, replicated):
    same_as_sql(catalog.queries()["w5_join_broadcast_only"], catalog.oracles()["w5_join_broadcast_only"])
    assert len(replicated) > 5 and max(replicated) <= 1_000
    assert sum(replicated) == spark.read.parquet(f"{sf}/lineitem.parquet").count()


def test_broadcast_only_sizes_replicate_pieces(spark, sf, same_as_sql, replicated):
    same_as_sql(catalog.queries()["w5_join_sizes"], catalog.oracles()["w5_join_sizes"])
    assert len(replicated) > 5 and max(replicated) <= 1_000
    assert sum(replicated) == spark.read.parquet(f"{sf}/lineitem.parquet").count()


@pytest.mark.parametrize("keys", ["even", "hot", "null", "nan", "none on the left"])
def test_pieces_are_the_whole_join(spark, replicated, keys):
    key = {"even": F.col("id") % 900, "hot": F.when(F.col("id") % 10 > 0, 7).otherwise(F.col("id")), "null": F.lit(None), "nan": F.when(F.col("id") % 5 == 0, float("nan")).otherwise(F.col("id")), "none on the left": F.col("id")}[keys]
    right = spark.range(0, 3_000, 1, 3).select(key.cast("double").alias("k"), F.col("id").alias("b"))
    left = spark.range(0, 0 if keys == "none on the left" else 40, 1, 2).select(key.cast("double").alias("k"), F.col("id").alias("a"))
    want = sorted(map(repr, map(tuple, left.join(right, ["k"]).collect())))
    got = broadcast_only.join_by_pieces(left, right, ["k"])
    assert got.columns == ["k", "a", "b"] and sorted(map(repr, map(tuple, got.collect()))) == want
    assert max(replicated) <= 1_000 and bool(want) == (keys in ("even", "hot", "nan"))


def test_pieces_need_keys_of_one_type(spark):
    a, b = spark.range(3), spark.range(3).select(F.col("id").cast("int"))
    with pytest.raises(ValueError):
        next(broadcast_only.pieces(a, b, ["id"]))


def test_combine_ratio_of_everything_needs_no_single_task(spark, tmp_path, sf, monkeypatch):
    lineitem(spark, tmp_path, sf)
    cls = type(spark.range(1))
    with monkeypatch.context() as m:
        for way in ("coalesce", "mapInArrow"):
            m.setattr(cls, way, lambda *a, **k: pytest.fail("all rows in one task"))
        got = catalog.queries()["s0b_combine_ratio"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(by_sql(tmp_path, "s0b_combine_ratio"))


def test_keys_seen_are_merged_a_few_times_only(monkeypatch):
    """Merging sorts all keys so far, so its work must not grow with the number of batches."""
    import numpy as np
    import pyarrow as pa

    n, size = 400_000, 1_000
    values = np.arange(n, dtype=np.int64) * 7919 % 250_007
    sorted_rows, real = [], np.unique
    monkeypatch.setattr(np, "unique", lambda a, *r, **k: (sorted_rows.append(len(a)), real(a, *r, **k))[1])
    batches = (pa.RecordBatch.from_arrays([pa.array(values[i : i + size])], names=["h"]) for i in range(0, n, size))
    (found,) = cardinality._distinct(batches)
    assert found.to_pylist() == [{"n": n, "d": 250_007}]
    calls = list(sorted_rows)
    assert calls and len(calls) <= 4 and sum(calls) <= 4 * n


def test_whole_ratio_of_nulls_and_nothing(spark):
    import math

    df = spark.createDataFrame([(1, "a"), (1, None), (None, "a"), (2, "b"), (2, "b")], "k int, s string")
    assert cardinality.whole_ratio(df, ["k"]) == 2 / 5 and cardinality.whole_ratio(df, ["k", "s"]) == 2 / 5
    assert math.isnan(cardinality.whole_ratio(df.limit(0), ["k"]))
