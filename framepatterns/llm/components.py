"""Connected components of a distributed edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.llm.scratch import Scratch


#: A node with more than this share of all edge ends is a hub; there are fewer than 1 / HUB of them.
HUB = 1e-3
#: Edges up to which one task may hold a hub's: they are 16 bytes each.
FEW_EDGES = 1 << 22


def _with_low(edges: DataFrame, low: DataFrame, rows: int) -> DataFrame:
    """Edges with their u's m.  In large tables hubs are replicated, their number is bounded, so their edges stay where they are."""
    if rows <= FEW_EDGES:
        return edges.join(low.select("u", "m"), "u")
    hubs = low.where(F.col("c") > HUB * rows).select("u", F.col("m").alias("h"))
    seen = edges.join(F.broadcast(hubs), "u", "left")
    rest = seen.where("h is null").select("u", "v").join(low.select("u", "m"), "u")
    return seen.where("h is not null").select("u", "v", F.col("h").alias("m")).union(rest)


def _large_star(edges: DataFrame, rows: int) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("c")).select("u", F.least("u", "m").alias("m"), "c")
    return _with_low(both, low, 2 * rows).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame, rows: int) -> DataFrame:
    low = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("c"))
    moved = _with_low(edges, low, rows).where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(low.select("u", F.col("m").alias("v")))


def connected_components(edges: DataFrame, scratch: Scratch, max_rounds: int = 64, rows: int | None = None) -> DataFrame:
    """(id, component) for every id that has a link to another id; component is the smallest reachable id.

    ``edges`` has long columns u and v; direction, repeats, self-links and nulls don't matter.  Smallest neighbours
    come from aggregations with map-side combine, and of more than FEW_EDGES links those of hubs are not brought
    together; each round is written to the shared folder.  ``rows`` is about the number of edges, where it is known,
    and only sets how many files they go to.  ``edges`` is computed once.  An empty edge table gives an empty result.
    """
    e = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e, seen = scratch.save(e, rows=rows), None
    for _ in range(max_rounds):
        state = e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.pmod(F.xxhash64("v", "u"), F.lit(1 << 30)))).first()
        if tuple(state) == seen or state[0] == 0:
            break
        seen = tuple(state)
        after = scratch.save(_small_star(_large_star(e, state[0]), state[0]).where("u <> v").distinct(), rows=2 * state[0])
        scratch.drop(e)
        e = after
    else:
        raise RuntimeError("components did not settle")
    out = e.groupBy(F.col("u").alias("id")).agg(F.min("v").alias("component")).union(e.select("v", "v").distinct())
    return scratch.save(out, rows=2 * state[0])
