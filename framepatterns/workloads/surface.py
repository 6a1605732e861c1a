"""Queries around the operators: aggregation sets, windows, functions, I/O, streams, SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.catalog import query
from framepatterns.functions import kernel, udf
from framepatterns.operators import ordering, rows, windows
from framepatterns.session import shared_root
from framepatterns.sources import readers, writers
from framepatterns.streaming import streams
from framepatterns.workloads.frames import money, table

Q = "CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty"


@query("case_when", "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'medium' ELSE 'large' END AS size FROM lineitem")
def case_when(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.when(F.col("l_quantity") < 10, "small").when(F.col("l_quantity") < 30, "medium").otherwise("large").alias("size"))


@query("filter_in", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 200000")
def filter_in(spark, d):
    return table(spark, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 200000)).select("o_orderkey", "o_orderpriority")


@query("filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-M]')")
def filter_like(spark, d):
    return table(spark, d, "part").where(F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-M]")).select("p_partkey", "p_name")


@query("agg_distinct", "SELECT count(DISTINCT l_suppkey) AS s, count(DISTINCT l_partkey) AS p, count(*) FILTER (l_returnflag = 'R') AS r FROM lineitem")
def agg_distinct(spark, d):
    return table(spark, d, "lineitem").agg(F.count_distinct("l_suppkey").alias("s"), F.count_distinct("l_partkey").alias("p"), F.count(F.when(F.col("l_returnflag") == "R", 1)).alias("r"))


@query("agg_rollup", f"SELECT l_returnflag, l_linestatus, {Q} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark, d):
    return table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.sum(money("l_quantity")).cast("double").alias("qty"))


@query("agg_cube", f"SELECT l_returnflag, l_linestatus, {Q} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, d):
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.sum(money("l_quantity")).cast("double").alias("qty"))


@query("agg_grouping_sets", f"SELECT l_returnflag, l_linestatus, {Q} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, d):
    li = table(spark, d, "lineitem")
    return li.groupingSets([[li["l_returnflag"]], [li["l_linestatus"]], []], li["l_returnflag"], li["l_linestatus"]).agg(F.sum(money("l_quantity")).cast("double").alias("qty"))


@query("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) >= 15")
def agg_having(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n >= 15")


@query("win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, CAST(rank() OVER w AS BIGINT) AS rk FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_rank(spark, d):
    w = W.Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"))


@query("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS next, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_lead(spark, d):
    w = W.Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.first("event_id").over(w).alias("f"))


@query("win_frames", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS hi, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM events")
def win_frames(spark, d):
    by = W.Window.partitionBy("user_id")
    return table(spark, d, "events").select("event_id", F.max("value").over(by.orderBy("ts", "event_id").rowsBetween(-2, 1)).alias("hi"), F.count("*").over(by.orderBy("event_id").rangeBetween(-100, 0)).alias("near"))


@query("win_ntile", "SELECT o_orderkey, CAST(ntile(4) OVER w AS INTEGER) AS q, round(percent_rank() OVER w, 9) AS pr FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)")
def win_ntile(spark, d):
    w = W.Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.ntile(4).over(w).alias("q"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk(spark, d):
    return ordering.top_k(table(spark, d, "orders").select("o_orderkey", "o_totalprice"), 25, [F.desc("o_totalprice"), "o_orderkey"])


@query("topk_per_key", "SELECT o_custkey, o_orderkey, rn FROM (SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS INTEGER) AS rn FROM orders) WHERE rn <= 3")
def topk_per_key(spark, d):
    return ordering.top_k_per_key(table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice"), 3, ["o_custkey"], [F.desc("o_totalprice"), "o_orderkey"]).select("o_custkey", "o_orderkey", "rn")


@query("fn_string", "SELECT p_partkey, upper(p_name) AS up, length(p_name) AS n, substr(p_name, 1, 5) AS head, replace(p_name, 'a', '@') AS rep, trim('  ' || p_brand || ' ') AS t, contains(p_name, 'e') AS has, string_split(p_name, ' ')[1] AS first_word, CAST(levenshtein(p_brand, 'Brand#11') AS INTEGER) AS lev FROM part")
def fn_string(spark, d):
    return table(spark, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").cast("long").alias("n"), F.substring("p_name", 1, 5).alias("head"), F.replace("p_name", F.lit("a"), F.lit("@")).alias("rep"), F.trim(F.concat(F.lit("  "), "p_brand", F.lit(" "))).alias("t"), F.contains("p_name", F.lit("e")).alias("has"), F.split("p_name", " ")[0].alias("first_word"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("lev"))


@query("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS mon, CAST(o_orderdate AS DATE) + 30 AS due, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS age, strftime(o_orderdate, '%Y-%m-%d') AS iso FROM orders")
def fn_date(spark, d):
    c = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.year(c).alias("y"), F.month(c).alias("m"), F.date_trunc("month", c).cast("timestamp_ntz").alias("mon"), F.date_add(c.cast("date"), 30).alias("due"), F.datediff(c.cast("date"), F.lit("1992-01-01").cast("date")).alias("age"), F.date_format(c, "yyyy-MM-dd").alias("iso"))


@query("fn_math", "SELECT l_orderkey, l_linenumber, round(l_extendedprice, 1) AS r, floor(l_quantity / 3) AS f, ceil(l_quantity / 3) AS c, abs(l_quantity - 25) AS a, round(ln(l_quantity), 6) AS lg, round(sqrt(l_quantity), 6) AS sq, l_partkey % 7 AS md, greatest(l_quantity, 20) AS g FROM lineitem")
def fn_math(spark, d):
    q = F.col("l_quantity")
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round("l_extendedprice", 1).alias("r"), F.floor(q / 3).cast("double").alias("f"), F.ceil(q / 3).cast("double").alias("c"), F.abs(q - 25).alias("a"), F.round(F.ln(q), 6).alias("lg"), F.round(F.sqrt(q), 6).alias("sq"), (F.col("l_partkey") % 7).alias("md"), F.greatest(q, F.lit(20.0)).alias("g"))


@query("fn_array", "SELECT vec_id, len(embedding) AS n, embedding[1] AS head, list_max(embedding) AS hi, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2 FROM embeddings")
def fn_array(spark, d):
    e = F.col("embedding")
    norm = F.aggregate(e, F.lit(0.0), lambda acc, x: acc + x.cast("double") * x)
    return table(spark, d, "embeddings").select("vec_id", F.size(e).cast("long").alias("n"), F.element_at(e, 1).alias("head"), F.array_max(e).alias("hi"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("pos"), F.round(norm, 4).alias("norm2"))


@query("fn_map", "SELECT o_orderkey, o_orderstatus AS status, 2 AS n FROM orders")
def fn_map(spark, d):
    m = F.create_map(F.lit("status"), F.col("o_orderstatus"), F.lit("priority"), F.col("o_orderpriority"))
    return table(spark, d, "orders").select("o_orderkey", m["status"].alias("status"), F.size(F.map_keys(m)).alias("n"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, json_extract_string(props, '$.k') AS s FROM events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").alias("s"))


@query("fn_missing", "SELECT l_orderkey, l_linenumber, coalesce(k, -1) AS filled, k IS NULL AS missing FROM (SELECT l_orderkey, l_linenumber, nullif(l_partkey % 7, 0) AS k FROM lineitem)")
def fn_missing(spark, d):
    k = F.nullif(F.col("l_partkey") % 7, F.lit(0))
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.coalesce(k, F.lit(-1)).alias("filled"), k.isNull().alias("missing"))


@query("fill_forward", "SELECT event_id, last_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS filled FROM (SELECT *, CASE WHEN event_id % 3 = 0 THEN NULL ELSE value END AS v FROM events)")
def fill_forward(spark, d):
    e = table(spark, d, "events").withColumn("v", F.when(F.col("event_id") % 3 != 0, F.col("value")))
    return windows.fill_forward(e, ["user_id"], ["ts", "event_id"], "v", "filled").select("event_id", "filled")


@query("sample_mod", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_orderkey * 31 + l_linenumber) % 10 = 3")
def sample_mod(spark, d):
    """Sampling operator: a repeatable tenth of the rows."""
    return table(spark, d, "lineitem").where((F.col("l_orderkey") * 31 + F.col("l_linenumber")) % 10 == 3).select("l_orderkey", "l_linenumber")


_HASH = "substr(md5(concat_ws('|', CAST(l_orderkey AS VARCHAR), CAST(l_linenumber AS VARCHAR))), 1, 8)"


@query("sample_rows", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE {_HASH} < '40000000'")
def sample_rows(spark, d):
    """Sampling operator: a repeatable quarter."""
    return rows.sample_rows(table(spark, d, "lineitem"), 0.25, ["l_orderkey", "l_linenumber"]).select("l_orderkey", "l_linenumber")


@query("sample_strata", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE {_HASH} < CASE l_returnflag WHEN 'R' THEN '80000000' WHEN 'A' THEN 'g' ELSE '20000000' END")
def sample_strata(spark, d):
    """Sampling operator: a share for each stratum."""
    return rows.sample_rows(table(spark, d, "lineitem"), 0.125, ["l_orderkey", "l_linenumber"], "l_returnflag", {"R": 0.5, "A": 1.0}).select("l_orderkey", "l_linenumber")


_GAPS = "(SELECT *, CASE WHEN event_id % 3 = 0 THEN NULL ELSE value END AS v FROM events)"


@query("fill_backward", f"SELECT event_id, first_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS filled FROM {_GAPS}")
def fill_backward(spark, d):
    e = table(spark, d, "events").withColumn("v", F.when(F.col("event_id") % 3 != 0, F.col("value")))
    return windows.fill_backward(e, ["user_id"], ["ts", "event_id"], "v", "filled").select("event_id", "filled")


@query("interpolate", f"""SELECT event_id, round(coalesce(v, py + (qy - py) * (event_id - px) / nullif(qx - px, 0), py), 6) AS filled FROM (SELECT event_id, v, last_value(v IGNORE NULLS) OVER b AS py, last_value(x IGNORE NULLS) OVER b AS px,
first_value(v IGNORE NULLS) OVER a AS qy, first_value(x IGNORE NULLS) OVER a AS qx FROM (SELECT *, CASE WHEN v IS NOT NULL THEN CAST(event_id AS DOUBLE) END AS x FROM {_GAPS})
WINDOW b AS (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING), a AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))""")
def interpolate(spark, d):
    e = table(spark, d, "events").withColumn("v", F.when(F.col("event_id") % 3 != 0, F.col("value")))
    return windows.interpolate(e, ["user_id"], "event_id", "v", "filled").select("event_id", F.round("filled", 6).alias("filled"))


def _arrow_double(t):
    import pyarrow as pa
    import pyarrow.compute as pc

    return pa.table({"p_partkey": t["p_partkey"], "y": pc.multiply(t["p_retailprice"], 2.0)})


def _pandas_double(t):
    return t.assign(y=t["p_retailprice"] * 2.0)[["p_partkey", "y"]]


@query("local_kernels", "SELECT kind, p_partkey, p_retailprice * 2.0 AS y FROM part, (VALUES ('sql'), ('arrow'), ('pandas')) k(kind)")
def local_kernels(spark, d):
    """The same local operator in three languages behind one interface."""
    part = table(spark, d, "part").select("p_partkey", "p_retailprice")
    kinds = {"sql": kernel.SqlKernel({"y": F.col("p_retailprice") * 2.0}), "arrow": kernel.ArrowKernel(_arrow_double, "p_partkey long, y double"), "pandas": kernel.PandasKernel(_pandas_double, "p_partkey long, y double")}
    parts = [kernel.local(part, k).df.select(F.lit(name).alias("kind"), "p_partkey", "y") for name, k in kinds.items()]
    return parts[0].union(parts[1]).union(parts[2])


@query("udf_scalar", "SELECT p_partkey, p_retailprice * 2 + 1 AS y FROM part")
def udf_scalar(spark, d):
    twice = udf.scalar(lambda s: s * 2 + 1, "double")
    return table(spark, d, "part").select("p_partkey", twice("p_retailprice").alias("y"))


@query("udtf_tokens", "SELECT p_partkey, w AS word, CAST(length(w) AS INTEGER) AS length FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w FROM part) WHERE w <> ''")
def udtf_tokens(spark, d):
    p = table(spark, d, "part").select("p_partkey", "p_name")
    return p.lateralJoin(udf.Tokens(F.col("p_name").outer())).select("p_partkey", "word", "length")


@query("sql_surface", f"SELECT n_name, {Q} FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def sql_surface(spark, d):
    names = {t: table(spark, d, t) for t in ("lineitem", "supplier", "nation")}
    return spark.sql("SELECT n_name, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty FROM {lineitem} JOIN {supplier} ON l_suppkey = s_suppkey JOIN {nation} ON s_nationkey = n_nationkey GROUP BY n_name", **names)


def _folder(spark) -> str:
    return f"{shared_root(spark)}/io_{uuid.uuid4().hex}"


_LI = "SELECT l_orderkey, l_linenumber, l_quantity, l_returnflag FROM lineitem"


def _roundtrip(spark, d, fmt, **options):
    src = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity", "l_returnflag")
    path = _folder(spark)
    writers.write_partitioned(src.repartition(4), path, fmt, **options)
    return readers.read_partitioned(spark, path, fmt, src.schema, **options)


@query("io_roundtrip_csv", _LI)
def io_roundtrip_csv(spark, d):
    return _roundtrip(spark, d, "csv", header="true")


@query("io_roundtrip_json", _LI)
def io_roundtrip_json(spark, d):
    return _roundtrip(spark, d, "json")


@query("io_roundtrip_parquet", _LI)
def io_roundtrip_parquet(spark, d):
    return _roundtrip(spark, d, "parquet")


@query("io_roundtrip_orc", _LI)
def io_roundtrip_orc(spark, d):
    return _roundtrip(spark, d, "orc")


@query("io_text", "SELECT r_name AS value FROM region")
def io_text(spark, d):
    path = _folder(spark)
    writers.write_partitioned(table(spark, d, "region").select("r_name"), path, "text")
    return readers.read_partitioned(spark, path, "text")


@query("io_binary", "SELECT CAST(sum(strlen(r_name) + 1) AS BIGINT) AS bytes FROM region")
def io_binary(spark, d):
    path = _folder(spark)
    writers.write_partitioned(table(spark, d, "region").select("r_name"), path, "text")
    return readers.read_partitioned(spark, path, "binaryFile").agg(F.sum(F.octet_length("content").cast("long")).alias("bytes"))


@query("io_read_with", "SELECT n_nationkey, n_name FROM nation")
def io_read_with(spark, d):
    """A reader of one's own: a function from a path to rows, one task a group of paths."""
    path = _folder(spark)
    nation = table(spark, d, "nation").select("n_nationkey", "n_name")
    writers.write_partitioned(nation.repartition(3), path)
    files = [(f,) for f in spark.read.parquet(path).inputFiles()]
    return readers.read_with(spark.createDataFrame(files, "path string"), _parquet_table, nation.schema)


def _parquet_table(path: str):
    import pyarrow.parquet as pq
    from pyarrow import fs

    where, name = fs.FileSystem.from_uri(path)
    return pq.read_table(name, filesystem=where)


@query("io_assigned_files", "SELECT r_regionkey AS k, r_name AS name, 0 AS worker FROM region UNION ALL SELECT n_nationkey, n_name, 1 FROM nation")
def io_assigned_files(spark, d):
    base = _folder(spark)
    r = table(spark, d, "region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("name"))
    n = table(spark, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name"))
    writers.write_single(r, f"{base}/r")
    writers.write_single(n, f"{base}/n")
    files = {i: spark.read.parquet(f"{base}/{x}").inputFiles() for i, x in enumerate("rn")}
    return readers.read_assigned(spark, files, "parquet")


@query("stream_rowlocal", "SELECT event_id, value * 2 AS v FROM events WHERE event_type <> ''")
def stream_rowlocal(spark, d):
    s = streams.table_stream(spark, d, "events").where("event_type <> ''").select("event_id", (F.col("value") * 2).alias("v"))
    return streams.run_to_end(s, "append")


_T = "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"


@query("stream_tumbling", _T)
def stream_tumbling(spark, d):
    s = streams.tumbling(streams.table_stream(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_type"), "ts", "1 hour", ["event_type"], [F.count("*").alias("n")])
    return streams.run_to_end(s).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("batch_tumbling", _T)
def batch_tumbling(spark, d):
    e = table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_type")
    return e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("stream_sliding", "SELECT time_bucket(INTERVAL '30 minutes', ts) - INTERVAL 30 MINUTES * i AS start, count(*) AS n FROM events, range(2) r(i) GROUP BY 1")
def stream_sliding(spark, d):
    s = streams.sliding(streams.table_stream(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts")), "ts", "1 hour", "30 minutes", [], [F.count("*").alias("n")])
    return streams.run_to_end(s).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


_SESSION = """SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOURS AS stop, count(*) AS n FROM (
SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS > ts THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s"""


@query("stream_session", _SESSION)
def stream_session(spark, d):
    src = streams.table_stream(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    s = streams.session(src, "ts", "6 hours", ["user_id"], [F.count("*").alias("n")])
    return streams.run_to_end(s).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), F.col("session_window.end").cast("timestamp_ntz").alias("stop"), "n")


@query("stream_dedup", "SELECT DISTINCT user_id FROM events")
def stream_dedup(spark, d):
    s = streams.table_stream(spark, d, "events").select("user_id").dropDuplicates(["user_id"])
    return streams.run_to_end(s, "append")


@query("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    s = streams.table_stream(spark, d, "events").select("event_id", F.col("user_id").alias("c_custkey"))
    return streams.run_to_end(streams.with_static(s, table(spark, d, "customer").select("c_custkey", "c_mktsegment"), ["c_custkey"]).select("event_id", "c_mktsegment"), "append")


@query("stream_rolling", "SELECT user_id, epoch_us(ts) AS us, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS rolled FROM events")
def stream_rolling(spark, d):
    src = streams.table_stream(spark, d, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "event_id")
    return streams.run_to_end(streams.rolling_by_key(src, "user_id", "us", "event_id", 3), "append")
