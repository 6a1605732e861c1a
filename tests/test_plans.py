"""Plans that scale: pushdown, pruning, exchanges, no Python where SQL suffices; and the survey's golden values."""

from pyspark.sql import functions as F

from framepatterns import catalog
from framepatterns.operators import columnagg, grouping, joining, setops
from framepatterns.plans.explain import exchanges, physical_plan, python_nodes, single_partition
from framepatterns.workloads.frames import bench_a, bench_b, table

Q = catalog.queries()


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = physical_plan(Q["select_rows"](spark, sf))
    assert "PushedFilters: [Or(EqualTo(l_returnflag,R)" in plan or "GreaterThan(l_quantity,25.0)" in plan
    assert "l_comment" not in plan and "l_tax" not in plan.split("ReadSchema")[1]


def test_row_local_operators_move_nothing(spark, sf):
    for name in ("select_rows", "project_cols", "map_scalar_add", "map_columns", "row_agg", "rename_cols", "case_when", "fn_math", "w1_scalar"):
        assert exchanges(Q[name](spark, sf)) == [], name


def test_group_forms_have_one_exchange(spark, sf):
    li = table(spark, sf, "lineitem")
    for pattern in ("combine", "shuffle"):
        out = grouping.groupby(li, ["l_partkey"], {"n": ("l_quantity", "count")}, pattern)
        assert len(exchanges(out.df)) == 1
    assert len(exchanges(grouping.unique(li.select("l_partkey"), pattern="shuffle").df)) == 1


def test_join_forms(spark, sf):
    o, n = table(spark, sf, "customer"), table(spark, sf, "nation")
    b = physical_plan(joining.broadcast_join(o, n, o["c_nationkey"] == n["n_nationkey"]).df)
    assert "BroadcastHashJoin" in b
    s = physical_plan(joining.join(o, n, [("c_nationkey", "n_nationkey")], algorithm="sort").df)
    assert "SortMergeJoin" in s
    h = physical_plan(joining.join(o, n, [("c_nationkey", "n_nationkey")], algorithm="hash").df)
    assert "ShuffledHashJoin" in h


def test_no_python_in_sql_operators(spark, sf):
    allowed = {"group_apply", "local_kernel", "udf_scalar", "udtf_tokens", "sort_sample", "a7_regular_sample"}
    for name in ("rolling_count_global", "expanding_global", "sort_range", "transpose_cells", "join_asof", "join_range", "join_skew_salted", "w10_pipeline", "unique_first", "global_position"):
        assert name not in allowed and python_nodes(Q[name](spark, sf)) == [], name


def test_no_single_partition_over_all_rows(spark, sf):
    for name in ("rolling_count_global", "shift_diff", "global_row_number", "global_position", "sort_sample", "rolling_time"):
        assert not single_partition(Q[name](spark, sf)), name


def test_golden_values(spark, sf):
    a, b = bench_a(spark, sf, 0.9), bench_b(spark, sf, 0.9)
    assert a.select("k").distinct().count() == 5365 and b.select("k").distinct().count() == 5413
    j = joining.join(a, b, ["k"]).df.agg(F.count("*"), F.sum(F.col("v_x") * F.col("v_y"))).first()
    assert tuple(j) == (1278, 20717)
    li, o, d = (table(spark, sf, t) for t in ("lineitem", "orders", "documents"))
    assert li.select("l_returnflag", "l_linestatus").distinct().count() == 6
    assert li.select("l_partkey", "l_suppkey").distinct().count() == 1905
    assert joining.join(o, li, [("o_orderkey", "l_orderkey")]).df.count() == 6000
    assert joining.join(o, li, [("o_orderkey", "l_orderkey")], "left").df.count() == 6027
    assert setops.difference(o.select("o_orderkey"), li.select("l_orderkey")).count() == 27
    assert setops.union_rows(o.select("o_custkey"), li.select("l_partkey"), by="position").count() == 200
    assert grouping.unique(d.select("text")).df.count() == 189 and d.count() == 200
    total = columnagg.column_agg(li, {"p": (F.col("l_extendedprice").cast("decimal(18,2)"), "sum"), "q": (F.col("l_quantity").cast("decimal(18,2)"), "sum")}).first()
    assert (str(total.p), int(total.q)) == ("317364757.31", 152257)


def test_bucketed_tables_keep_their_layout(spark, sf, tmp_path):
    from framepatterns.sources import writers

    spark.sql(f"CREATE DATABASE IF NOT EXISTS fp LOCATION '{tmp_path}'")
    li, o = table(spark, sf, "lineitem"), table(spark, sf, "orders")
    writers.write_bucketed(li.select("l_orderkey", "l_quantity"), "fp.li", ["l_orderkey"], 4)
    writers.write_bucketed(o.select("o_orderkey", "o_custkey"), "fp.o", ["o_orderkey"], 4)
    j = spark.table("fp.li").hint("merge").join(spark.table("fp.o"), F.col("l_orderkey") == F.col("o_orderkey"))
    assert not [e for e in exchanges(j) if e.startswith("Exchange")] and j.count() == 6000
    spark.sql("DROP DATABASE fp CASCADE")
