"""Mixing sources to target weights by hash-threshold histograms.

A source's target is met by whole passes over it plus one partial pass.  The partial pass takes the documents
whose hash lies below a threshold.  The threshold is found without sorting: tokens are summed by source and
hash bucket, the bucket in which the running sum crosses the budget is the boundary bucket, and only its rows
are summed again by the next digits of the hash, until the boundary is a single hash value.  Thresholds are
nested: a larger budget keeps every document that a smaller one takes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.llm.scratch import Scratch

KEY_BITS, STEP_BITS = 60, 12


def word_count(text: Column) -> Column:
    """Number of runs of characters other than space and U+0009..U+000D; a null text has none."""
    marks = F.regexp_replace(text, r"[^\x20\x09-\x0D]+", "x")
    return F.coalesce(F.length(F.translate(marks, " \t\n\x0b\x0c\r", "")), F.lit(0)).cast("long")


def hash_key(doc_id: Column) -> Column:
    """The first 60 bits of the MD5 of the id's digits, the same in every SQL engine."""
    return F.coalesce(F.conv(F.substring(F.md5(doc_id.cast("string")), 1, KEY_BITS // 4), 16, 10).cast("long"), F.lit(0))


def source_targets(sizes: DataFrame, weights=(5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """Add weight and target to a table (source, source_size) of one row a source.

    Weights repeat over the sources in code-point order, null last.  All sources share ``share`` times the
    total; a target stops at ``cap`` times its source's size and the excess is shared again by weight until
    none is above, which is the level at which filling all sources in proportion to weight meets the budget.
    """
    order = W.Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    full = W.Window.orderBy(F.lit(1)).rowsBetween(W.Window.unboundedPreceding, W.Window.unboundedFollowing)
    by_need = W.Window.orderBy((F.col("most") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before, rest = by_need.rowsBetween(W.Window.unboundedPreceding, -1), by_need.rowsBetween(0, W.Window.unboundedFollowing)
    t = ranked.withColumn("most", F.lit(float(cap)) * F.col("source_size")).withColumn("budget", F.lit(float(share)) * F.sum("source_size").over(full))
    t = t.withColumn("met", F.coalesce(F.sum("most").over(before), F.lit(0.0)) + F.col("most") / F.col("weight") * F.sum("weight").over(rest) <= F.col("budget"))
    capped = F.coalesce(F.sum(F.when(F.col("met"), F.col("most"))).over(full), F.lit(0.0))
    free = F.sum(F.when(~F.col("met"), F.col("weight"))).over(full)
    t = t.withColumn("level", (F.col("budget") - capped) / free)
    return t.select("source", "source_size", "weight", F.when(F.col("met"), F.col("most")).otherwise(F.col("level") * F.col("weight")).alias("target"))


def mix_sources(docs: DataFrame, weights=(5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """``docs`` with size, source_size, target and copies (how often the mix takes the document: 0, 1, 2 ...).

    Sizes are words.  A document is taken floor(target / source_size) times, and once more where its hash is
    below its source's threshold; the document at the threshold is taken if that comes nearer to the target.
    Reruns agree, for the hash depends on doc_id alone; rows that repeat a doc_id are taken or left together.

    Null texts have size 0; a null source is a source of its own, last in order; a source without words has
    target 0.  An empty table gives an empty result.  Needs the columns doc_id, source and text; other columns
    pass through, and a column that has the name of one added here is replaced.
    """
    scratch = Scratch(docs.sparkSession, "mix")
    base = docs.drop("size", "source_size", "target", "copies")
    plan = thresholds(scratch.save(_narrow(base)), scratch, weights, share, cap)
    rows = base.select("source", word_count(F.col("text")).alias("size"), hash_key(F.col("doc_id")).alias("key"), F.struct(*base.columns).alias("row"))
    return _taken(rows, plan).select("row.*", "size", "source_size", "target", "copies")


def mix_plan(docs: DataFrame, weights=(5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """Like ``mix_sources``, but only doc_id, source and the added columns, from one pass over the texts."""
    scratch = Scratch(docs.sparkSession, "mix")
    narrow = scratch.save(_narrow(docs))
    plan = thresholds(narrow, scratch, weights, share, cap)
    return _taken(narrow, plan).select("doc_id", "source", "size", "source_size", "target", "copies")


def _narrow(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), hash_key(F.col("doc_id")).alias("key"))


def _taken(rows: DataFrame, plan: DataFrame) -> DataFrame:
    t = plan.withColumnRenamed("source", "_source")
    joined = rows.join(t, rows["source"].eqNullSafe(t["_source"]), "left")
    more = (F.col("key") < F.col("edge")) | ((F.col("key") == F.col("edge")) & F.col("edge_taken"))
    return joined.withColumn("copies", F.coalesce(F.col("passes") + F.when(more, 1).otherwise(0), F.lit(0)).cast("long"))


def thresholds(narrow: DataFrame, scratch: Scratch, weights=(5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """One row a source: source, source_size, target, passes, edge (hash at the threshold) and edge_taken."""
    sizes = narrow.groupBy("source").agg(F.sum("size").alias("source_size"))
    targets = source_targets(sizes, weights, share, cap).withColumn("passes", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0))
    targets = scratch.save(targets.withColumn("rest", F.col("target") - F.col("passes") * F.col("source_size")))
    state = targets.select("source", "rest", F.lit(0).cast("long").alias("below"), F.lit(0).cast("long").alias("prefix"))
    sources, shift = targets.count(), KEY_BITS
    while shift > 0:
        shift -= STEP_BITS
        s = state.withColumnRenamed("source", "_source")
        inside = narrow.join(s, narrow["source"].eqNullSafe(s["_source"]) & (F.shiftright("key", shift + STEP_BITS) == F.col("prefix")))
        buckets = inside.groupBy("source", F.shiftright("key", shift).alias("prefix")).agg(
            F.sum("size").alias("tokens"), F.first("rest").alias("rest"), F.first("below").alias("below"), F.min("key").alias("low"), F.max("key").alias("high")
        )
        upto = W.Window.partitionBy("source").orderBy("prefix")
        run = buckets.withColumn("upto", F.col("below") + F.sum("tokens").over(upto))
        crossing = run.where("upto > rest").groupBy("source").agg(F.min_by(F.struct("rest", (F.col("upto") - F.col("tokens")).alias("below"), "prefix", "tokens", "low", "high"), "prefix").alias("b"))
        state = scratch.save(crossing.select("source", "b.*"), rows=sources)
        if state.where("low < high").isEmpty():
            break
    edge = state.select(F.col("source").alias("_source"), F.col("low").alias("edge"), (2 * (F.col("rest") - F.col("below")) >= F.col("tokens")).alias("edge_taken"))
    return targets.join(edge, targets["source"].eqNullSafe(edge["_source"]), "left").select("source", "source_size", "target", "passes", F.coalesce("edge", F.lit(0)).alias("edge"), F.coalesce("edge_taken", F.lit(False)).alias("edge_taken"))


OP9_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 15) AS BIGINT) AS key
  FROM documents),
s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight
  FROM d GROUP BY source),
n AS (
  SELECT *, 2.0::DOUBLE * source_size AS most, 1.5::DOUBLE * CAST(sum(source_size) OVER () AS DOUBLE) AS budget FROM s),
m AS (
  SELECT *, coalesce(sum(most) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)
         + most / weight * CAST(sum(weight) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) <= budget AS met
  FROM n),
l AS (
  SELECT *, (budget - coalesce(sum(most) FILTER (met) OVER (), 0)) / CAST(sum(weight) FILTER (NOT met) OVER () AS DOUBLE) AS level FROM m),
t AS (
  SELECT source, source_size, CASE WHEN met THEN most ELSE level * weight END AS target FROM l),
p AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS passes FROM t),
k AS (
  SELECT source, key, CAST(sum(size) AS BIGINT) AS tokens FROM d GROUP BY source, key),
r AS (
  SELECT source, key, tokens, CAST(sum(tokens) OVER (PARTITION BY source ORDER BY key) AS BIGINT) AS upto FROM k),
e AS (
  SELECT r.source, min(struct_pack(key := r.key, tokens := r.tokens, rest := p.target - p.passes * p.source_size - (r.upto - r.tokens))) AS b
  FROM r JOIN p ON r.source IS NOT DISTINCT FROM p.source
  WHERE r.upto > p.target - p.passes * p.source_size GROUP BY r.source)
SELECT d.doc_id, d.size, p.source_size, p.target,
       CAST(d.size * (p.passes + CASE WHEN d.key < e.b.key OR (d.key = e.b.key AND 2 * e.b.rest >= e.b.tokens) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM d JOIN p ON d.source IS NOT DISTINCT FROM p.source LEFT JOIN e ON d.source IS NOT DISTINCT FROM e.source
"""
