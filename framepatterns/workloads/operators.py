"""One query for each operator and variant, with its SQL twin."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import functions as F

from framepatterns.catalog import query
from framepatterns.layout.rebalance import weighted_pid, with_position
from framepatterns.layout.sampling import row_index
from framepatterns.operators import columnagg, grouping, joining, ordering, reshape, rows, setops, windows
from framepatterns.operators.aggregates import GEOMETRIC_MEAN, STD_MOMENTS
from framepatterns.patterns import Frame, all_reduce, local_kernel
from framepatterns.sources import writers
from framepatterns.workloads.frames import money, table

M = "CAST({} AS DECIMAL(18,2))"


@query("select_rows", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > 25 AND (l_returnflag = 'R' OR l_shipdate >= TIMESTAMP '1997-01-01') AND l_partkey IS NOT NULL")
def select_rows(spark, d):
    keep = (F.col("l_quantity") > 25) & ((F.col("l_returnflag") == "R") | (F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz"))) & F.col("l_partkey").isNotNull()
    return rows.project(rows.select_rows(table(spark, d, "lineitem"), keep), ["l_orderkey", "l_linenumber", "l_quantity"])


@query("project_cols", "SELECT l_shipdate, l_orderkey, l_extendedprice FROM lineitem")
def project_cols(spark, d):
    return rows.project(table(spark, d, "lineitem"), ["l_shipdate", "l_orderkey", "l_extendedprice"])


@query("map_scalar_add", "SELECT l_orderkey + 7 AS l_orderkey, l_linenumber + 7 AS l_linenumber FROM lineitem")
def map_scalar_add(spark, d):
    return rows.map_scalar(table(spark, d, "lineitem").select("l_orderkey", "l_linenumber"), ["l_orderkey", "l_linenumber"], "add", 7)


@query("map_scalar_mul", "SELECT l_orderkey, l_quantity * 2 AS l_quantity FROM lineitem")
def map_scalar_mul(spark, d):
    return rows.map_scalar(table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), ["l_quantity"], "mul", 2)


@query("map_columns", "SELECT l_orderkey, l_linenumber, CAST(round(l_extendedprice * 100) AS BIGINT) AS cents, least(greatest(l_quantity, 10), 40) AS clipped, CASE WHEN l_returnflag = 'N' THEN NULL ELSE l_returnflag END AS flag, CASE l_linestatus WHEN 'O' THEN 'open' ELSE 'final' END AS status FROM lineitem")
def map_columns(spark, d):
    li = table(spark, d, "lineitem")
    out = rows.map_columns(li, {"cents": F.round(F.col("l_extendedprice") * 100).cast("long"), "clipped": rows.clip(F.col("l_quantity"), 10.0, 40.0), "flag": rows.mask(F.col("l_returnflag"), F.col("l_returnflag") == "N"), "status": F.when(F.col("l_linestatus") == "O", "open").otherwise("final")})
    return out.select("l_orderkey", "l_linenumber", "cents", "clipped", "flag", "status")


@query("row_agg", "SELECT l_orderkey, l_linenumber, l_quantity + l_extendedprice AS s, least(l_quantity, l_extendedprice, l_discount) AS lo, greatest(l_quantity, l_extendedprice, l_discount) AS hi, 3 AS n, round((l_quantity + l_extendedprice) / 2, 6) AS m FROM lineitem")
def row_agg(spark, d):
    three = ["l_quantity", "l_extendedprice", "l_discount"]
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", rows.row_agg(three[:2], "sum").alias("s"), rows.row_agg(three, "min").alias("lo"), rows.row_agg(three, "max").alias("hi"), rows.row_agg(three, "count").alias("n"), F.round(rows.row_agg(three[:2], "mean"), 6).alias("m"))


@query("rename_cols", "SELECT l_orderkey AS order_id, l_linenumber AS line FROM lineitem")
def rename_cols(spark, d):
    return rows.rename(table(spark, d, "lineitem").select("l_orderkey", "l_linenumber"), {"l_orderkey": "order_id", "l_linenumber": "line"})


@query("to_labels", "SELECT o_orderkey, o_custkey, o_totalprice FROM orders")
def to_labels(spark, d):
    return Frame(table(spark, d, "orders")).to_labels("o_orderkey", check=True).df.select("o_orderkey", "o_custkey", "o_totalprice")


@query("from_labels", "SELECT row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS label, o_orderkey FROM orders")
def from_labels(spark, d):
    f = Frame(table(spark, d, "orders").select("o_orderkey", "o_totalprice")).to_labels("o_orderkey")
    return f.from_labels(order=["o_totalprice", "o_orderkey"]).df.select("label", "o_orderkey")


_O, _L = "(SELECT o_custkey AS k FROM orders)", "(SELECT l_partkey AS k FROM lineitem)"


def _keys(spark, d):
    return table(spark, d, "orders").select(F.col("o_custkey").alias("k")), table(spark, d, "lineitem").select(F.col("l_partkey").alias("k"))


@query("union_distinct", f"SELECT k FROM {_O} UNION SELECT k FROM {_L}")
def union_distinct(spark, d):
    return setops.union_rows(*_keys(spark, d))


@query("union_all", f"SELECT k FROM {_O} UNION ALL SELECT k FROM {_L}")
def union_all(spark, d):
    return setops.union_rows(*_keys(spark, d), distinct=False)


@query("difference_set", "SELECT o_orderkey AS k FROM orders EXCEPT SELECT l_orderkey FROM lineitem")
def difference_set(spark, d):
    return setops.difference(table(spark, d, "orders").select(F.col("o_orderkey").alias("k")), table(spark, d, "lineitem").select("l_orderkey"))


@query("difference_bag", f"SELECT k FROM {_O} EXCEPT ALL SELECT k FROM {_L}")
def difference_bag(spark, d):
    return setops.difference(*_keys(spark, d), multiset=True)


@query("intersect_set", f"SELECT k FROM {_O} INTERSECT SELECT k FROM {_L}")
def intersect_set(spark, d):
    return setops.intersection(*_keys(spark, d))


@query("intersect_bag", f"SELECT k FROM {_O} INTERSECT ALL SELECT k FROM {_L}")
def intersect_bag(spark, d):
    return setops.intersection(*_keys(spark, d), multiset=True)


@query("difference_symmetric", f"(SELECT k FROM {_O} EXCEPT SELECT k FROM {_L}) UNION ALL (SELECT k FROM {_L} EXCEPT SELECT k FROM {_O})")
def difference_symmetric(spark, d):
    return setops.symmetric_difference(*_keys(spark, d))


def _ol(spark, d):
    return table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey"), table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", "l_partkey")


def _join_sql(how: str) -> str:
    return f"SELECT {'coalesce(o_orderkey, l_orderkey)' if how != 'LEFT' else 'o_orderkey'} AS k, o_custkey, l_linenumber, l_partkey FROM orders {how} JOIN lineitem ON o_orderkey = l_orderkey"


@query("join_inner", _join_sql("INNER"))
def join_inner(spark, d):
    return joining.join(*_ol(spark, d), ["k"], "inner").df


@query("join_left", _join_sql("LEFT"))
def join_left(spark, d):
    return joining.join(*_ol(spark, d), ["k"], "left", algorithm="hash").df


@query("join_right", "SELECT o_orderkey AS k, o_custkey, l_linenumber, l_partkey FROM lineitem RIGHT JOIN orders ON o_orderkey = l_orderkey")
def join_right(spark, d):
    o, l = _ol(spark, d)
    return joining.join(l, o, ["k"], "right").df.select("k", "o_custkey", "l_linenumber", "l_partkey")


@query("join_outer", "SELECT coalesce(s.k, p.k) AS k, s_name, p_name FROM (SELECT s_suppkey AS k, s_name FROM supplier) s FULL JOIN (SELECT p_partkey + 50 AS k, p_name FROM part) p ON s.k = p.k")
def join_outer(spark, d):
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("k"), "s_name")
    p = table(spark, d, "part").select((F.col("p_partkey") + 50).alias("k"), "p_name")
    return joining.join(s, p, ["k"], "outer").df


@query("join_semi", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(spark, d):
    big = table(spark, d, "lineitem").where("l_quantity > 45")
    return joining.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), big, [("o_orderkey", "l_orderkey")], "left_semi").df


@query("join_anti", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def join_anti(spark, d):
    return joining.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), table(spark, d, "lineitem"), [("o_orderkey", "l_orderkey")], "left_anti").df


@query("join_multikey", "SELECT a.l_partkey, a.l_suppkey, a.l_orderkey AS l_orderkey_x, b.l_orderkey AS l_orderkey_y FROM lineitem a JOIN lineitem b USING (l_partkey, l_suppkey) WHERE a.l_orderkey < b.l_orderkey")
def join_multikey(spark, d):
    a = table(spark, d, "lineitem").select("l_partkey", "l_suppkey", "l_orderkey")
    return joining.join(a, a, ["l_partkey", "l_suppkey"], "inner", algorithm="sort").df.where("l_orderkey_x < l_orderkey_y")


@query("join_null_keys", "SELECT count(*) AS n, count(*) FILTER (a.k IS NULL) AS n_null FROM (SELECT nullif(l_partkey, 7) AS k FROM lineitem) a JOIN (SELECT nullif(p_partkey, 7) AS k FROM part) b ON a.k IS NOT DISTINCT FROM b.k")
def join_null_keys(spark, d):
    a = table(spark, d, "lineitem").select(F.nullif("l_partkey", F.lit(7)).alias("k"))
    b = table(spark, d, "part").select(F.nullif("p_partkey", F.lit(7)).alias("k"))
    return joining.join(a, b, ["k"], null_keys="match").df.agg(F.count("*").alias("n"), F.count_if(F.col("k").isNull()).alias("n_null"))


@query("join_local_buckets", _join_sql("INNER"))
def join_local_buckets(spark, d):
    from framepatterns.patterns import shuffle_compute

    o, l = _ol(spark, d)
    return shuffle_compute([o, l], ["k"], lambda a, b: a.join(b, ["k", "_bucket"]).drop("_bucket"), 8, local_buckets=16).df


@query("join_oversplit", _join_sql("INNER"))
def join_oversplit(spark, d):
    from framepatterns.patterns import shuffle_compute

    return shuffle_compute(list(_ol(spark, d)), ["k"], lambda a, b: a.join(b, "k"), 8, oversplit=4).df


@query("join_skew_salted", "SELECT s.k, l_orderkey, p_name FROM (SELECT CASE WHEN l_linenumber <= 5 THEN 0 ELSE l_partkey END AS k, l_orderkey FROM lineitem) s JOIN (SELECT p_partkey AS k, p_name FROM part) p ON s.k = p.k")
def join_skew_salted(spark, d):
    s = table(spark, d, "lineitem").select(F.when(F.col("l_linenumber") <= 5, 0).otherwise(F.col("l_partkey")).cast("long").alias("k"), "l_orderkey")
    p = table(spark, d, "part").select(F.col("p_partkey").alias("k"), "p_name")
    return joining.join(s, p, ["k"], skew="salt").df


_GEO = "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query("join_broadcast", _GEO)
def join_broadcast(spark, d):
    c, n, r = (table(spark, d, t) for t in ("customer", "nation", "region"))
    cn = joining.broadcast_join(c, n, c["c_nationkey"] == n["n_nationkey"])
    return joining.broadcast_join(cn, r, cn.df["n_regionkey"] == r["r_regionkey"]).df.select("c_custkey", "n_name", "r_name")


@query("join_auto", "SELECT l_orderkey, l_linenumber, s_name FROM lineitem JOIN supplier ON l_suppkey = s_suppkey")
def join_auto(spark, d):
    l = table(spark, d, "lineitem").select(F.col("l_suppkey").alias("k"), "l_orderkey", "l_linenumber")
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("k"), "s_name")
    return joining.join_auto(l, s, ["k"]).df.select("l_orderkey", "l_linenumber", "s_name")


@query("join_auto_left", "SELECT s_name, l_orderkey, l_linenumber FROM supplier RIGHT JOIN lineitem ON s_suppkey = l_suppkey")
def join_auto_left(spark, d):
    """The small side is the left one, and all rows of the right side are kept."""
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("k"), "s_name")
    l = table(spark, d, "lineitem").select(F.col("l_suppkey").alias("k"), "l_orderkey", "l_linenumber")
    return joining.join_auto(s, l, ["k"], "right").df.select("s_name", "l_orderkey", "l_linenumber")


@query("join_theta", "SELECT s_suppkey, n_nationkey FROM supplier JOIN nation ON s_nationkey < n_nationkey AND s_acctbal > 0")
def join_theta(spark, d):
    s, n = table(spark, d, "supplier"), table(spark, d, "nation")
    return joining.theta_join(s, n, (s["s_nationkey"] < n["n_nationkey"]) & (s["s_acctbal"] > 0)).select("s_suppkey", "n_nationkey")


@query("join_range", "SELECT e.event_id, w.event_id AS span_id FROM events e JOIN events w ON epoch_us(e.ts) >= epoch_us(w.ts) AND epoch_us(e.ts) < epoch_us(w.ts) + 60000000")
def join_range(spark, d):
    at = table(spark, d, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    spans = at.select(F.col("event_id").alias("span_id"), F.col("us").alias("lo"), (F.col("us") + 60000000).alias("hi"))
    return joining.range_join(at, "us", spans, "lo", "hi", 60000000).select("event_id", "span_id")


_ASOF = """SELECT l.event_id, l.user_id, r.event_id AS asof_event_id FROM (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)) l
ASOF LEFT JOIN (SELECT * FROM events WHERE event_type <> (SELECT min(event_type) FROM events)) r ON l.user_id = r.user_id AND l.ts >= r.ts"""


@query("join_asof", _ASOF)
def join_asof(spark, d):
    e = table(spark, d, "events")
    first = e.agg(F.min("event_type")).first()[0]
    out = joining.asof_join(e.where(F.col("event_type") == first).select("user_id", "ts", "event_id"), e.where(F.col("event_type") != first), ["user_id"], "ts", ["event_id"], tie="event_id")
    return out.select("event_id", "user_id", "asof_event_id")


@query("unique_rows", "SELECT DISTINCT text FROM documents")
def unique_rows(spark, d):
    return grouping.unique(table(spark, d, "documents").select("text")).df


@query("unique_first", "SELECT o_custkey, min(o_orderkey) AS o_orderkey FROM orders GROUP BY o_custkey")
def unique_first(spark, d):
    return grouping.unique(table(spark, d, "orders").select("o_custkey", "o_orderkey"), ["o_custkey"], "first", "o_orderkey").df


@query("unique_last", "SELECT o_custkey, max(o_orderkey) AS o_orderkey FROM orders GROUP BY o_custkey")
def unique_last(spark, d):
    return grouping.unique(table(spark, d, "orders").select("o_custkey", "o_orderkey"), ["o_custkey"], "last", "o_orderkey").df


@query("unique_none", "SELECT l_partkey, l_suppkey FROM lineitem GROUP BY ALL HAVING count(*) = 1")
def unique_none(spark, d):
    return grouping.unique(table(spark, d, "lineitem").select("l_partkey", "l_suppkey"), keep="none").df


@query("unique_shuffle", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def unique_shuffle(spark, d):
    return grouping.unique(table(spark, d, "lineitem").select("l_partkey", "l_suppkey"), pattern="shuffle").df


@query("duplicated_flag", "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) > 1 AS duplicated FROM orders")
def duplicated_flag(spark, d):
    return grouping.duplicated(table(spark, d, "orders").select("o_orderkey", "o_custkey"), ["o_custkey"], "o_orderkey").select("o_orderkey", "duplicated")


LOW, HIGH = ["l_returnflag", "l_linestatus"], ["l_partkey", "l_suppkey"]


def _group_sql(keys: list[str]) -> str:
    k = ", ".join(keys)
    return f"SELECT {k}, CAST(sum({M.format('l_quantity')}) AS DOUBLE) AS qty, count(l_quantity) AS n, max(l_extendedprice) AS hi FROM lineitem GROUP BY {k}"


def _group(spark, d, keys, pattern, **more):
    aggs = {"qty": (money("l_quantity"), "sum"), "n": ("l_quantity", "count"), "hi": ("l_extendedprice", "max")}
    out = grouping.groupby(table(spark, d, "lineitem"), keys, aggs, pattern, **more).df
    return out.withColumn("qty", F.col("qty").cast("double"))


@query("groupby_combine_lowC", _group_sql(LOW))
def groupby_combine_low(spark, d):
    return _group(spark, d, LOW, "combine")


@query("groupby_combine_highC", _group_sql(HIGH))
def groupby_combine_high(spark, d):
    return _group(spark, d, HIGH, "combine")


@query("groupby_shuffle_lowC", _group_sql(LOW))
def groupby_shuffle_low(spark, d):
    return _group(spark, d, LOW, "shuffle")


@query("groupby_shuffle_highC", _group_sql(HIGH))
def groupby_shuffle_high(spark, d):
    return _group(spark, d, HIGH, "shuffle")


@query("groupby_auto", _group_sql(HIGH))
def groupby_auto(spark, d):
    return _group(spark, d, HIGH, "auto")


@query("groupby_salted", _group_sql(LOW))
def groupby_salted(spark, d):
    return _group(spark, d, LOW, "combine", salt=8)


@query("groupby_drop_null_keys", "SELECT k, count(*) AS n FROM (SELECT nullif(l_partkey % 7, 0) AS k FROM lineitem) WHERE k IS NOT NULL GROUP BY k")
def groupby_drop_null_keys(spark, d):
    li = table(spark, d, "lineitem").select(F.nullif(F.col("l_partkey") % 7, F.lit(0)).alias("k"))
    return grouping.groupby(li, ["k"], {"n": ("k", "size")}, "combine", null_keys="drop").df


@query("group_transform", f"SELECT l_orderkey, l_linenumber, CAST(sum({M.format('l_quantity')}) OVER (PARTITION BY l_suppkey) AS DOUBLE) AS supplier_qty FROM lineitem")
def group_transform(spark, d):
    out = grouping.group_transform(table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", "l_quantity"), ["l_suppkey"], {"supplier_qty": F.sum(money("l_quantity")).cast("double")})
    return out.select("l_orderkey", "l_linenumber", "supplier_qty")


@query("group_filter", "SELECT o_orderkey, o_custkey FROM orders WHERE o_custkey IN (SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(*) > 12)")
def group_filter(spark, d):
    return grouping.group_filter(table(spark, d, "orders").select("o_orderkey", "o_custkey"), ["o_custkey"], F.count("*") > 12)


@query("group_apply", "SELECT c_nationkey, max(c_acctbal) - min(c_acctbal) AS spread FROM customer GROUP BY c_nationkey")
def group_apply(spark, d):
    import pyarrow as pa
    import pyarrow.compute as pc

    def spread(t: pa.Table) -> pa.Table:
        r = pc.min_max(t["c_acctbal"]).as_py()
        return pa.table({"c_nationkey": t["c_nationkey"][:1], "spread": pa.array([r["max"] - r["min"]])})

    return grouping.group_apply(table(spark, d, "customer").select("c_nationkey", "c_acctbal"), ["c_nationkey"], spread, "c_nationkey int, spread double")


@query("agg_std_moments", "SELECT l_suppkey, round(stddev_samp(l_linenumber), 6) AS std FROM lineitem GROUP BY l_suppkey")
def agg_std_moments(spark, d):
    out = grouping.groupby(table(spark, d, "lineitem"), ["l_suppkey"], {"std": (F.col("l_linenumber").cast("double"), STD_MOMENTS)}, "combine").df
    return out.withColumn("std", F.round("std", 6))


@query("agg_std_builtin", "SELECT l_suppkey, round(stddev_samp(l_linenumber), 6) AS std, round(var_pop(l_linenumber), 6) AS var0 FROM lineitem GROUP BY l_suppkey")
def agg_std_builtin(spark, d):
    li = table(spark, d, "lineitem")
    return li.groupBy("l_suppkey").agg(F.round(F.stddev_samp("l_linenumber"), 6).alias("std"), F.round(F.var_pop("l_linenumber"), 6).alias("var0"))


@query("agg_mean", "SELECT l_returnflag, round(CAST(sum(l_linenumber) AS DOUBLE) / count(*), 9) AS mean FROM lineitem GROUP BY l_returnflag")
def agg_mean(spark, d):
    return grouping.groupby(table(spark, d, "lineitem"), ["l_returnflag"], {"mean": ("l_linenumber", "mean")}, "combine").df.withColumn("mean", F.round("mean", 9))


@query("agg_nunique", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
def agg_nunique(spark, d):
    return grouping.groupby(table(spark, d, "lineitem"), ["l_returnflag"], {"parts": ("l_partkey", "nunique")}, "combine").df


@query("agg_median", "SELECT l_suppkey, median(l_quantity) AS med, quantile_cont(l_quantity, 0.5) AS q, mode_q FROM lineitem JOIN (SELECT l_suppkey, l_quantity AS mode_q, row_number() OVER (PARTITION BY l_suppkey ORDER BY count(*) DESC, l_quantity) AS r FROM lineitem GROUP BY l_suppkey, l_quantity) m USING (l_suppkey) WHERE r = 1 GROUP BY l_suppkey, mode_q")
def agg_median(spark, d):
    return grouping.groupby(table(spark, d, "lineitem"), ["l_suppkey"], {"med": ("l_quantity", "median"), "q": ("l_quantity", "quantile"), "mode_q": ("l_quantity", "mode")}, "auto").df


@query("agg_minmax", "SELECT l_suppkey, min(l_shipdate) AS lo, max(l_shipdate) AS hi, bool_or(l_quantity > 49) AS any_big, bool_and(l_quantity > 1) AS all_big FROM lineitem GROUP BY l_suppkey")
def agg_minmax(spark, d):
    aggs = {"lo": ("l_shipdate", "min"), "hi": ("l_shipdate", "max"), "any_big": (F.col("l_quantity") > 49, "any"), "all_big": (F.col("l_quantity") > 1, "all")}
    return grouping.groupby(table(spark, d, "lineitem"), ["l_suppkey"], aggs, "combine").df


@query("agg_first_last", "SELECT o_custkey, arg_min(o_totalprice, o_orderkey) AS first_price, arg_max(o_totalprice, o_orderkey) AS last_price FROM orders GROUP BY o_custkey")
def agg_first_last(spark, d):
    return grouping.groupby(table(spark, d, "orders"), ["o_custkey"], {"first_price": ("o_totalprice", "first"), "last_price": ("o_totalprice", "last")}, "combine", label=F.col("o_orderkey")).df


@query("agg_moments", "SELECT round(covar_samp(l_linenumber, l_partkey), 4) AS cov, round(corr(l_linenumber, l_partkey), 9) AS corr FROM lineitem")
def agg_moments(spark, d):
    return columnagg.pair_agg(table(spark, d, "lineitem"), "l_linenumber", "l_partkey").select(F.round("cov", 4).alias("cov"), F.round("corr", 9).alias("corr"))


@query("agg_sketches")
def agg_sketches(spark, d):
    """Approximate distinct count and quantile by mergeable sketches (estimates; tests bound their error)."""
    return columnagg.column_agg(table(spark, d, "lineitem"), {"parts": ("l_partkey", "nunique_approx"), "median": ("l_quantity", "quantile_approx")})


@query("agg_collect", "SELECT o_custkey, list_sort(list(DISTINCT o_orderstatus)) AS states FROM orders GROUP BY o_custkey")
def agg_collect(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_set("o_orderstatus")).alias("states"))


@query("udaf_declared", "SELECT l_suppkey, round(exp(sum(ln(l_quantity)) / count(*)), 6) AS gmean FROM lineitem GROUP BY l_suppkey")
def udaf_declared(spark, d):
    return grouping.groupby(table(spark, d, "lineitem"), ["l_suppkey"], {"gmean": ("l_quantity", GEOMETRIC_MEAN)}, "combine").df.withColumn("gmean", F.round("gmean", 6))


@query("column_agg", f"SELECT count(*) AS n, CAST(sum({M.format('l_extendedprice')}) AS DOUBLE) AS total, min(l_shipdate) AS first_day, max(l_quantity) AS most, count(DISTINCT l_suppkey) AS suppliers, round(stddev_samp(l_linenumber), 6) AS std, median(l_quantity) AS med, round(skewness(l_linenumber), 3) AS skew FROM lineitem")
def column_agg(spark, d):
    out = columnagg.column_agg(table(spark, d, "lineitem"), {"n": ("l_orderkey", "size"), "total": (money("l_extendedprice"), "sum"), "first_day": ("l_shipdate", "min"), "most": ("l_quantity", "max"), "suppliers": ("l_suppkey", "nunique"), "std": ("l_linenumber", "std"), "med": ("l_quantity", "median"), "skew": ("l_linenumber", "skew")})
    return out.withColumns({"total": F.col("total").cast("double"), "std": F.round("std", 6), "skew": F.round("skew", 3)})


@query("all_reduce", "SELECT l_orderkey, l_linenumber, (SELECT max(l_quantity) FROM lineitem) AS most FROM lineitem")
def all_reduce_query(spark, d):
    return all_reduce(table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity"), F.max("l_quantity").alias("most")).select("l_orderkey", "l_linenumber", "most")


@query("array_reduce", "SELECT CAST(i - 1 AS INTEGER) AS position, round(sum(CAST(embedding[i] AS DOUBLE)), 3) AS value FROM embeddings, range(1, 65) r(i) GROUP BY i")
def array_reduce(spark, d):
    from framepatterns.collectives import reduce_array

    e = table(spark, d, "embeddings").select(F.col("embedding").cast("array<double>").alias("e"))
    return reduce_array(e, "e").select("position", F.round("value", 3).alias("value"))


@query("dist_length", "SELECT count(*) AS length FROM lineitem")
def dist_length(spark, d):
    return table(spark, d, "lineitem").agg(F.count("*").alias("length"))


@query("frames_equal", "SELECT true AS same, false AS other")
def frames_equal(spark, d):
    o = table(spark, d, "orders")
    same = columnagg.frames_equal(o, o.repartition(7))
    other = columnagg.frames_equal(o, o.where("o_orderkey > 0"))
    return spark.createDataFrame([(same, other)], "same boolean, other boolean")


def _wide_sql(column):
    return f"SELECT '{column}' AS \"column\", " + ", ".join(f'max(CAST({column} AS VARCHAR)) FILTER (n_nationkey = {k}) AS "{k}"' for k in range(25)) + " FROM nation"


@query("transpose_wide", f"{_wide_sql('n_name')} UNION ALL {_wide_sql('n_regionkey')}")
def transpose_wide(spark, d):
    return reshape.transpose(table(spark, d, "nation"), "n_nationkey", "wide")


@query("transpose_cells", "UNPIVOT (SELECT o_orderkey AS label, o_totalprice, CAST(o_custkey AS DOUBLE) AS o_custkey FROM orders) ON o_totalprice, o_custkey INTO NAME \"column\" VALUE value")
def transpose_cells(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice", F.col("o_custkey").cast("double").alias("o_custkey"))
    return reshape.transpose(o, "o_orderkey", "cells")


@query("transpose_blocks", "SELECT c AS \"column\", b AS block, list(v ORDER BY o_orderkey) AS \"values\" FROM (SELECT 'o_totalprice' AS c, o_orderkey, o_totalprice AS v, (row_number() OVER (ORDER BY o_orderkey) - 1) // 1000 AS b FROM orders) GROUP BY c, b")
def transpose_blocks(spark, d):
    return reshape.transpose(table(spark, d, "orders").select("o_orderkey", "o_totalprice"), "o_orderkey", "blocks", block=1000)


@query("pivot_flags", f"SELECT l_returnflag, CAST(sum({M.format('l_quantity')}) FILTER (l_linestatus = 'F') AS DOUBLE) AS F, CAST(sum({M.format('l_quantity')}) FILTER (l_linestatus = 'O') AS DOUBLE) AS O FROM lineitem GROUP BY l_returnflag")
def pivot_flags(spark, d):
    return reshape.pivot(table(spark, d, "lineitem"), ["l_returnflag"], "l_linestatus", ["F", "O"], F.sum(money("l_quantity")).cast("double"))


@query("melt_money", "UNPIVOT (SELECT l_orderkey, l_linenumber, l_extendedprice, l_discount, l_tax FROM lineitem) ON l_extendedprice, l_discount, l_tax INTO NAME \"column\" VALUE value")
def melt_money(spark, d):
    return reshape.melt(table(spark, d, "lineitem"), ["l_orderkey", "l_linenumber"], ["l_extendedprice", "l_discount", "l_tax"])


def _numbered(frame, name="at"):
    """Global positions read off a sorted frame's partitions: shows the order that the sort made.

    The engine's own sort draws its pivots anew in each run, so a row's partition and place in it are written once,
    and lengths and positions are both taken from what was written.
    """
    placed = writers.written_once(frame.df.withColumns({"_p": F.spark_partition_id(), "_i": row_index()}), "sorted")
    lengths = dict(placed.groupBy("_p").count().collect())
    offsets = list(accumulate((lengths.get(i, 0) for i in range(max(lengths, default=0))), initial=0))
    shift = F.element_at(F.array(*[F.lit(o).cast("long") for o in offsets]), F.col("_p") + 1)
    return placed.withColumn(name, shift + F.col("_i")).drop("_p", "_i")


@query("sort_range", "SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS at, o_orderkey FROM orders")
def sort_range(spark, d):
    mixed = table(spark, d, "orders").select("o_orderkey").repartition(7, "o_orderkey")
    return _numbered(ordering.sort(mixed, ["o_orderkey"], algorithm="range", partitions=8))


@query("sort_sample", "SELECT row_number() OVER (ORDER BY o_orderpriority, o_totalprice, o_orderkey) - 1 AS at, o_orderkey FROM orders")
def sort_sample(spark, d):
    o = table(spark, d, "orders").select("o_orderpriority", "o_totalprice", "o_orderkey")
    return _numbered(ordering.sort(o, ["o_orderpriority", "o_totalprice", "o_orderkey"], algorithm="sample", partitions=8)).select("at", "o_orderkey")


@query("sort_native", "SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS at, o_orderkey FROM orders")
def sort_native(spark, d):
    """The engine's own range sort, to compare the two above with."""
    mixed = table(spark, d, "orders").select("o_orderkey").orderBy((F.col("o_orderkey") * 7919) % 15013)
    return _numbered(ordering.sort(mixed, ["o_orderkey"], algorithm="native"))


@query("sort_multikey", "SELECT row_number() OVER (ORDER BY o_orderpriority DESC, o_orderkey) - 1 AS at, o_orderkey FROM orders")
def sort_multikey(spark, d):
    o = table(spark, d, "orders").select("o_orderpriority", "o_orderkey")
    return _numbered(ordering.sort(o, ["o_orderpriority", "o_orderkey"], [False, True], algorithm="native")).select("at", "o_orderkey")


@query("global_row_number", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rn, rank() OVER (ORDER BY o_orderpriority) AS rk, dense_rank() OVER (ORDER BY o_orderpriority) AS dr FROM orders")
def global_row_number(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice", "o_orderpriority")
    r = ordering.rank(o, ["o_totalprice"], "first", ["o_orderkey"], "rn")
    r = ordering.rank(r, ["o_orderpriority"], "min", name="rk")
    return ordering.rank(r, ["o_orderpriority"], "dense", name="dr").select("o_orderkey", "rn", "rk", "dr")


_MEAN_RANK = "(2 * rank() OVER (ORDER BY o_orderpriority) + count(*) OVER (PARTITION BY o_orderpriority) - 1) / 2"


@query("rank_ties", f"SELECT o_orderkey, CAST(rank() OVER (ORDER BY o_orderpriority) + count(*) OVER (PARTITION BY o_orderpriority) - 1 AS BIGINT) AS hi, {_MEAN_RANK} AS mean, round({_MEAN_RANK} / count(*) OVER (), 12) AS pct FROM orders")
def rank_ties(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_orderpriority")
    for method, name in (("max", "hi"), ("average", "mean"), ("pct", "pct")):
        o = ordering.rank(o, ["o_orderpriority"], method, name=name)
    return o.select("o_orderkey", "hi", "mean", F.round("pct", 12).alias("pct"))


@query("global_position", "SELECT doc_id, row_number() OVER (ORDER BY n_chars, doc_id) - 1 AS position FROM documents")
def global_position(spark, d):
    return with_position(table(spark, d, "documents").select("doc_id", "n_chars"), ["n_chars", "doc_id"]).select("doc_id", "position")


@query("weighted_partition", "SELECT doc_id, CAST(least(floor(b * 8 / t), 7) AS INTEGER) AS pid FROM (SELECT doc_id, coalesce(sum(n_chars) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b, sum(n_chars) OVER () AS t FROM documents)")
def weighted_partition(spark, d):
    return weighted_pid(table(spark, d, "documents").select("doc_id", "n_chars"), "n_chars", ["doc_id"], 8).select("doc_id", "pid")


_E = "ORDER BY ts, event_id"


@query("rolling_count_global", f"SELECT event_id, CASE WHEN c = 7 THEN s END AS s, CASE WHEN c = 7 THEN hi END AS hi FROM (SELECT event_id, count(*) OVER w AS c, CAST(sum({M.format('value')}) OVER w AS DOUBLE) AS s, max(value) OVER w AS hi FROM events WINDOW w AS ({_E} ROWS BETWEEN 6 PRECEDING AND CURRENT ROW))")
def rolling_count_global(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "value")
    out = windows.rolling(e, ["ts", "event_id"], 7, {"s": lambda: F.sum(money("value")), "hi": lambda: F.max("value")}, block=512)
    return out.select("event_id", F.col("s").cast("double").alias("s"), "hi")


@query("rolling_centered", f"SELECT event_id, min(value) OVER ({_E} ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS lo FROM events")
def rolling_centered(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "value")
    return windows.rolling(e, ["ts", "event_id"], 5, {"lo": lambda: F.min("value")}, center=True, min_periods=1, block=512).select("event_id", "lo")


@query("rolling_count_keyed", f"SELECT event_id, CASE WHEN count(*) OVER w = 3 THEN CAST(sum({M.format('value')}) OVER w AS DOUBLE) END AS s FROM events WINDOW w AS (PARTITION BY user_id {_E} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)")
def rolling_count_keyed(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "value", "user_id")
    out = windows.rolling(e, ["ts", "event_id"], 3, {"s": lambda: F.sum(money("value"))}, keys=["user_id"])
    return out.select("event_id", F.col("s").cast("double").alias("s"))


@query("rolling_time", "SELECT event_id, count(*) OVER (ORDER BY ts RANGE BETWEEN INTERVAL 3599999999 MICROSECONDS PRECEDING AND CURRENT ROW) AS n FROM events")
def rolling_time(spark, d):
    return windows.rolling_time(table(spark, d, "events").select("event_id", "ts"), "ts", 3_600_000_000, {"n": lambda: F.count("*")}).select("event_id", "n")


@query("rolling_time_keyed", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def rolling_time_keyed(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "user_id")
    return windows.rolling_time(e, "ts", 86_400_000_000, {"n": lambda: F.count("*")}, keys=["user_id"], closed="both").select("event_id", "n")


@query("expanding_global", f"SELECT event_id, CAST(sum({M.format('value')}) OVER w AS DOUBLE) AS s, max(value) OVER w AS hi, count(value) OVER w AS n FROM events WINDOW w AS ({_E} ROWS UNBOUNDED PRECEDING)")
def expanding_global(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "value", money("value").alias("m"))
    out = windows.expanding(e, ["ts", "event_id"], {"s": ("m", "sum"), "hi": ("value", "max"), "n": ("value", "count")}, block=512)
    return out.select("event_id", F.col("s").cast("double").alias("s"), "hi", "n")


@query("shift_diff", f"SELECT event_id, lag(value, 2) OVER w AS before, event_id - lag(event_id, 1) OVER w AS step FROM events WINDOW w AS ({_E})")
def shift_diff(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "value")
    out = windows.diff(windows.shift(e, ["ts", "event_id"], "value", 2, "before", block=512), ["ts", "event_id"], "event_id", 1, "step", block=512)
    return out.select("event_id", "before", "step")


@query("cumsum_global", f"SELECT event_id, CAST(sum({M.format('value')}) OVER ({_E} ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS s FROM events")
def cumsum_global(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", money("value").alias("m"))
    return windows.cumulate(e, ["ts", "event_id"], "m", "sum", "s").select("event_id", F.col("s").cast("double").alias("s"))


@query("local_kernel", "SELECT l_orderkey, l_quantity * 3 AS tripled FROM lineitem")
def local_kernel_query(spark, d):
    import pyarrow.compute as pc

    def triple(t):
        return t.drop_columns(["l_quantity"]).append_column("tripled", pc.multiply(t["l_quantity"], 3.0))

    return local_kernel(table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), triple, "l_orderkey long, tripled double").df
