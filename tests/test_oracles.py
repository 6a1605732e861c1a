"""Every query against its DuckDB twin on the smallest tables."""

import pytest

from framepatterns import catalog

ORACLES = catalog.oracles()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(name, same_as_sql):
    same_as_sql(catalog.queries()[name], ORACLES[name])


def test_all_but_sketches_have_a_twin():
    assert set(catalog.queries()) - set(ORACLES) == {"agg_sketches"}


def test_entry_runs(spark):
    import __spark_entry__ as e

    df = e.entry(spark)
    assert df.columns == ["n_name", "year", "revenue", "lines"] and df.count() > 0


def test_whole_table_queries_use_every_row(spark, sf):
    q = catalog.queries()
    read = lambda t: spark.read.parquet(f"{sf}/{t}.parquet")
    assert q["join_range"](spark, sf).select("span_id").distinct().count() == read("events").count()
    assert set(q["transpose_wide"](spark, sf).columns) == {"column", *(str(r[0]) for r in read("nation").select("n_nationkey").collect())}
    lines, parts = ([None if k == 7 else k for (k,) in read(t).select(c).collect()] for t, c in (("lineitem", "l_partkey"), ("part", "p_partkey")))
    got = q["join_null_keys"](spark, sf).first()
    assert tuple(got) == (sum(parts.count(k) for k in lines), lines.count(None) * parts.count(None))
