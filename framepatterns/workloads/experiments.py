"""The paper's experiments on the given tables: scalar, scalar aggregation, group-by, join, cardinality, join swap, pipeline."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns import collectives
from framepatterns.baselines import broadcast_only, stock
from framepatterns.catalog import query
from framepatterns.layout.rebalance import weighted_pid
from framepatterns.operators import grouping, joining, ordering, rows
from framepatterns.operators.aggregates import STD_MOMENTS
from framepatterns.session import shared_root
from framepatterns.sources import readers, writers
from framepatterns.workloads.frames import bench_a, bench_b, money, sql_a, sql_b, table

A, B = sql_a(0.9), sql_b(0.9)


@query("w0_frame", f"SELECT k, v FROM {A}")
def w0_frame(spark, d):
    return bench_a(spark, d, 0.9)


@query("w1_scalar", f"SELECT k + 42 AS k, v + 42 AS v FROM {A}")
def w1_scalar(spark, d):
    return rows.map_scalar(bench_a(spark, d, 0.9), ["k", "v"], "add", 42)


def _plus_42(batches):
    import pyarrow as pa
    import pyarrow.compute as pc

    for b in batches:
        yield pa.RecordBatch.from_arrays([pc.add(c, 42) for c in b.columns], names=b.schema.names)


@query("w1_scalar_barrier", f"SELECT k + 42 AS k, v + 42 AS v FROM {A}")
def w1_scalar_barrier(spark, d):
    """The scalar test with a barrier before the local work: what waiting for all workers costs."""
    return collectives.barrier_map(bench_a(spark, d, 0.9).repartition(2), _plus_42, "k long, v long")


@query("w2_scalar_agg", f"SELECT CAST(sum(k) AS BIGINT) AS k, CAST(sum(v) AS BIGINT) AS v, round(CAST(sum(v) AS DOUBLE) / count(*), 9) AS mean FROM {A}")
def w2_scalar_agg(spark, d):
    return bench_a(spark, d, 0.9).agg(F.sum("k").alias("k"), F.sum("v").alias("v"), F.round(F.avg("v"), 9).alias("mean"))


def _group_sql(c: float) -> str:
    return f"SELECT k, CAST(sum(v) AS BIGINT) AS total, round(CAST(sum(v) AS DOUBLE) / count(*), 9) AS mean, round(stddev_samp(v), 6) AS std FROM {sql_a(c)} GROUP BY k"


def _group(spark, d, c, pattern):
    f = bench_a(spark, d, c)
    out = grouping.groupby(f, ["k"], {"total": ("v", "sum"), "mean": ("v", "mean"), "std": (F.col("v").cast("double"), STD_MOMENTS)}, pattern).df
    return out.select("k", "total", F.round("mean", 9).alias("mean"), F.round("std", 6).alias("std"))


@query("w3_groupby", _group_sql(0.9))
def w3_groupby(spark, d):
    return _group(spark, d, 0.9, "auto")


@query("w3_groupby_stock", _group_sql(0.9))
def w3_groupby_stock(spark, d):
    return stock.group(bench_a(spark, d, 0.9), ["k"], F.sum("v").alias("total"), F.round(F.avg("v"), 9).alias("mean"), F.round(F.stddev_samp("v"), 6).alias("std"))


_J = f"SELECT k, a.v AS v_x, b.v AS v_y FROM {A} a JOIN {B} b USING (k)"


@query("w4_join", _J)
def w4_join(spark, d):
    return joining.join(bench_a(spark, d, 0.9), bench_b(spark, d, 0.9), ["k"]).df


@query("w4_join_stock", _J)
def w4_join_stock(spark, d):
    return stock.join(bench_a(spark, d, 0.9).withColumnRenamed("v", "v_x"), bench_b(spark, d, 0.9).withColumnRenamed("v", "v_y"), ["k"])


@query("w4_join_fk", "SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def w4_join_fk(spark, d):
    l = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber")
    return joining.join(l, table(spark, d, "orders").select("o_orderkey", "o_custkey"), [("l_orderkey", "o_orderkey")]).df.select("l_orderkey", "l_linenumber", "o_custkey")


@query("w5_join_broadcast_only", _J)
def w5_join_broadcast_only(spark, d):
    return broadcast_only.join_by_pieces(bench_a(spark, d, 0.9).withColumnRenamed("v", "v_x"), bench_b(spark, d, 0.9).withColumnRenamed("v", "v_y"), ["k"])


@query("w5_join_sizes", f"SELECT 'table' AS size, true AS completed, (SELECT count(*) FROM ({_J})) AS rows UNION ALL SELECT 'tenfold', false, NULL")
def w5_join_sizes(spark, d):
    """Broadcast-only joins at two sizes a factor of ten apart, under a memory limit between them.

    The large join is refused, which is recorded; a tenth of it completes, piece by piece where it is more than may
    be replicated at once.  The tenfold side is ten tables.
    """
    a, b = (f(spark, d, 0.9).withColumnRenamed("v", v) for f, v in ((bench_a, "v_x"), (bench_b, "v_y")))
    limit = 3 * collectives.estimated_bytes(b)
    ten = reduce(DataFrame.unionAll, [b] * 10)
    found = []
    for size, side in (("table", b), ("tenfold", ten)):
        try:
            broadcast_only.guard(side, limit)
            found.append((size, True, sum(p.count() for p in broadcast_only.pieces(a, side, ["k"]))))
        except broadcast_only.MemoryGuard:
            found.append((size, False, None))
    return spark.createDataFrame(found, "size string, completed boolean, rows long")


@query("w6_hash_C09", _group_sql(0.9))
def w6_hash_high(spark, d):
    return _group(spark, d, 0.9, "shuffle")


@query("w6_mapred_C09", _group_sql(0.9))
def w6_mapred_high(spark, d):
    return _group(spark, d, 0.9, "combine")


@query("w6_hash_Clow", _group_sql(1e-5))
def w6_hash_low(spark, d):
    return _group(spark, d, 1e-5, "shuffle")


@query("w6_mapred_Clow", _group_sql(1e-5))
def w6_mapred_low(spark, d):
    return _group(spark, d, 1e-5, "combine")


@query("w6_cardinality", " UNION ALL ".join(f"SELECT CAST({c} AS DOUBLE) AS wanted, round(count(DISTINCT k) / count(*), 6) AS found FROM {sql_a(c)}" for c in (0.9, 0.5, 0.1)))
def w6_cardinality(spark, d):
    out = None
    for c in (0.9, 0.5, 0.1):
        one = bench_a(spark, d, c).agg(F.lit(c).alias("wanted"), F.round(F.count_distinct("k") / F.count("*"), 6).alias("found"))
        out = one if out is None else out.union(one)
    return out


_SWAP = "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey"


@query("w7_join_shuffle", _SWAP)
def w7_join_shuffle(spark, d):
    c, n = table(spark, d, "customer"), table(spark, d, "nation")
    return joining.join(c, n, [("c_nationkey", "n_nationkey")], algorithm="sort").df.select("c_custkey", "n_name")


@query("w7_join_swap", _SWAP)
def w7_join_swap(spark, d):
    c, n = table(spark, d, "customer"), table(spark, d, "nation")
    return joining.broadcast_join(c, n, c["c_nationkey"] == n["n_nationkey"]).df.select("c_custkey", "n_name")


_W10 = """SELECT n_name, CAST(year(o_orderdate) AS INTEGER) AS year,
CAST(sum(CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DECIMAL(18,4))) AS DOUBLE) AS revenue, count(*) AS lines
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
WHERE l_returnflag <> 'A' GROUP BY 1, 2"""


@query("w10_pipeline", _W10)
def w10_pipeline(spark, d):
    """Read, select, map, join (shuffle and broadcast), group, sort: revenue per nation and year."""
    li = rows.select_rows(table(spark, d, "lineitem"), F.col("l_returnflag") != "A").select("l_orderkey", (money("l_extendedprice") * (1 - F.col("l_discount").cast("decimal(4,2)"))).cast("decimal(18,4)").alias("revenue"))
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").alias("year"))
    c = joining.broadcast_join(table(spark, d, "customer").select("c_custkey", "c_nationkey"), table(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name"), ["c_nationkey"])
    lo = joining.join(li, o, [("l_orderkey", "o_orderkey")])
    all_ = joining.join(lo, c, [("o_custkey", "c_custkey")])
    out = grouping.groupby(all_, ["n_name", "year"], {"revenue": ("revenue", "sum"), "lines": ("revenue", "size")}, "combine")
    return ordering.sort(out.with_df(out.df.withColumn("revenue", F.col("revenue").cast("double"))), ["n_name", "year"], algorithm="native").df


@query("w10_pipeline_written", _W10)
def w10_pipeline_written(spark, d):
    """The pipeline with its last step: written by year and read again."""
    out, path = w10_pipeline(spark, d), f"{shared_root(spark)}/w10_{uuid.uuid4().hex}"
    writers.write_partitioned(out, path, by=["year"])
    return readers.read_partitioned(spark, path, schema=out.schema).select(*out.columns)


@query("w11_docs_unique", "SELECT lang, source, count(DISTINCT text) AS texts, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY lang, source")
def w11_docs_unique(spark, d):
    docs = table(spark, d, "documents")
    texts = grouping.unique(docs.select("lang", "source", "text")).df.groupBy("lang", "source").agg(F.count("*").alias("texts"))
    return texts.join(docs.groupBy("lang", "source").agg(F.sum("n_chars").alias("chars")), ["lang", "source"])


@query("w11_docs_labels", "SELECT lang, CAST(sum(quality) AS BIGINT) AS good, CAST(sum(toxic) AS BIGINT) AS toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def w11_docs_labels(spark, d):
    j = joining.join_auto(table(spark, d, "documents").select("doc_id", "lang"), table(spark, d, "labels"), ["doc_id"])
    return j.df.groupBy("lang").agg(F.sum("quality").alias("good"), F.sum("toxic").alias("toxic"), F.count("*").alias("n"))


@query("w11_docs_balance", "SELECT pid, count(*) AS docs, CAST(sum(n_chars) AS BIGINT) AS chars FROM (SELECT n_chars, CAST(least(floor(b * 4 / t), 3) AS INTEGER) AS pid FROM (SELECT n_chars, coalesce(sum(n_chars) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b, sum(n_chars) OVER () AS t FROM documents)) GROUP BY pid")
def w11_docs_balance(spark, d):
    return weighted_pid(table(spark, d, "documents").select("doc_id", "n_chars"), "n_chars", ["doc_id"], 4).groupBy("pid").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))
