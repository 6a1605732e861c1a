"""Near-duplicate vectors by navigable small-world graphs, one for each shard.

Vectors of one label and dimension are dealt into shards of about SHARD_ROWS rows.  A shard's graph has layers
of geometrically fewer nodes.  It is built by insertion: a batch of new nodes searches the graph that is there,
each takes diverse near neighbours among what it found and among its batch, and gets links back; one more link
chains it behind the nearest node that was there before, so every node can be reached however crowded it is.
Every vector queries every shard of its label: a search descends through the layers and ends with a beam on
the lowest.  A beam that is full of matches is widened and searched again, and so is a whole batch as long as
an audit against brute force on part of the batch finds too few of all matches, or too few of a query's own on
average.  Matches are verified in double precision.

Queries of a batch advance together, so each step is a few numpy calls for hundreds of queries.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.llm.components import connected_components
from framepatterns.llm.scratch import Scratch

SHARD_ROWS, DEGREE, BATCH, BEAM, AUDIT_EVERY = 8192, 16, 256, 48, 16
#: Beam of an insertion, and recall that an audit asks for.
INSERT_BEAM, RECALL = 48, 0.995


class Graph:
    """Layers of neighbour lists over unit vectors; -1 pads a list.

    A list holds the neighbours that a node chose, links back from nodes that chose it, and the next node of its
    chain.
    """

    def __init__(self, unit: np.ndarray, ids: np.ndarray):
        self.x = unit.astype(np.float32)
        n = len(unit)
        rng = np.random.default_rng(n)
        level = np.minimum((-np.log(np.maximum(rng.random(n), 1e-12)) / np.log(DEGREE)).astype(int), 8)
        order = rng.permutation(n)
        self.layers: list[tuple[np.ndarray, np.ndarray]] = [None] * (int(level.max()) + 1 if n else 0)
        for at in range(len(self.layers) - 1, -1, -1):  # nodes of higher layers come first, a search starts from them
            nodes = order[level[order] >= at]
            nodes = nodes[np.argsort(-np.minimum(level[nodes], at + 1), kind="stable")]
            degree = DEGREE * (2 if at == 0 else 1)
            self.layers[at] = (nodes, np.full((n, 2 * degree + 1), -1, np.int32))
            self._insert(nodes, at, degree)

    def _insert(self, nodes: np.ndarray, at: int, degree: int) -> None:
        table = self.layers[at][1]
        filled = np.zeros(len(self.x), int)  # links back
        done = 0
        while done < len(nodes):
            batch = nodes[done : done + min(BATCH, max(done, 64))]
            q = self.x[batch]
            old = np.zeros((len(batch), 0), np.int64)
            if done:
                old, sims = self._beam(q, at, self._starts(q, at, nodes[: min(done, 4 * DEGREE)]), min(INSERT_BEAM, done))
                old = np.take_along_axis(old, np.argsort(-sims, axis=1), 1)
                old[np.isin(old, batch)] = -1
            width = min(degree, len(batch) - 1)
            s = q @ q.T
            np.fill_diagonal(s, -2)
            new = batch[np.argpartition(-s, width - 1, axis=1)[:, :width]] if width > 0 else np.zeros((len(batch), 0), np.int64)
            near = self._diverse(q, np.concatenate([old, new], axis=1), degree)
            table[batch, : near.shape[1]] = near
            self._link_back(table, filled, batch, near, degree)
            if done:
                for node, before in zip(batch, old.tolist(), strict=True):
                    spot = next((x for x in before if x >= 0), nodes[0])
                    table[node, -1], table[spot, -1] = table[spot, -1], node
            else:
                table[batch[:-1], -1] = batch[1:]
            done += len(batch)

    def _diverse(self, q: np.ndarray, cand: np.ndarray, degree: int) -> np.ndarray:
        """Of each row's candidates those that are nearer to the node than to any chosen one, then the nearest."""
        sim = np.where(cand >= 0, np.einsum("qwd,qd->qw", self.x[np.maximum(cand, 0)], q), -3.0)
        order = np.argsort(-sim, axis=1, kind="stable")
        cand, sim = np.take_along_axis(cand, order, 1), np.take_along_axis(sim, order, 1)
        among = np.einsum("qad,qbd->qab", self.x[np.maximum(cand, 0)], self.x[np.maximum(cand, 0)])
        crowd, chosen = np.full_like(sim, -2), np.zeros(sim.shape, bool)
        for c in range(cand.shape[1]):
            take = (sim[:, c] > crowd[:, c]) & (sim[:, c] > -2) & (chosen.sum(1) < degree)
            chosen[:, c] = take
            crowd[take] = np.maximum(crowd[take], among[take, c])
        rank = np.argsort(np.where(chosen, 0, 1) * 10.0 - sim, axis=1, kind="stable")[:, :degree]
        return np.take_along_axis(cand, rank, 1)

    @staticmethod
    def _link_back(table: np.ndarray, filled: np.ndarray, batch: np.ndarray, near: np.ndarray, degree: int) -> None:
        src, dst = np.repeat(batch, near.shape[1]), near.ravel()
        src, dst = src[dst >= 0], dst[dst >= 0]
        order = np.argsort(dst, kind="stable")
        src, dst = src[order], dst[order]
        start = np.flatnonzero(np.concatenate(([True], dst[1:] != dst[:-1]))) if dst.size else np.zeros(0, int)
        spot = np.arange(dst.size) - np.repeat(start, np.diff(np.append(start, dst.size))) + filled[dst]
        fits = spot < degree
        table[dst[fits], degree + spot[fits]] = src[fits]
        np.add.at(filled, dst[fits], 1)

    def _starts(self, q: np.ndarray, layer: int, first: np.ndarray) -> np.ndarray:
        """Where a search of a layer begins: what a descent through the layers above it finds."""
        top = len(self.layers) - 1
        if layer == top:
            return np.tile(first, (len(q), 1))
        starts = np.tile(self.layers[top][0][: 4 * DEGREE], (len(q), 1))
        for at in range(top, layer, -1):
            starts = self._beam(q, at, starts, 16)[0]
        return starts

    def _beam(self, q: np.ndarray, layer: int, starts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        nodes, table = self.layers[layer]
        m = len(q)
        width = min(width, nodes.size)
        seen = np.zeros((m, len(self.x) + 1), bool)
        ids = np.full((m, width), -1, np.int64)
        sims = np.full((m, width), -3.0, np.float32)
        done = np.ones((m, width), bool)

        def offer(who: np.ndarray, cand: np.ndarray) -> None:
            cand = np.sort(cand, axis=1)
            cand[:, 1:][cand[:, 1:] == cand[:, :-1]] = -1
            fresh = (cand >= 0) & ~seen[who[:, None], cand]
            seen[who[:, None], np.where(fresh, cand, len(self.x))] = True
            keep = fresh.sum(1).max() if fresh.size else 0
            if not keep:
                return
            cand = np.take_along_axis(np.where(fresh, cand, -1), np.argsort(~fresh, axis=1, kind="stable")[:, :keep], 1)
            s = np.einsum("qwd,qd->qw", self.x[np.maximum(cand, 0)], q[who])
            s = np.where(cand >= 0, s, -3.0)
            all_s = np.concatenate([sims[who], s], 1)
            top = np.argpartition(-all_s, width - 1, axis=1)[:, :width] if all_s.shape[1] > width else np.tile(np.arange(all_s.shape[1]), (len(who), 1))
            sims[who] = np.take_along_axis(all_s, top, 1)
            ids[who] = np.take_along_axis(np.concatenate([ids[who], cand], 1), top, 1)
            done[who] = np.take_along_axis(np.concatenate([done[who], cand < 0], 1), top, 1)

        offer(np.arange(m), np.atleast_2d(starts).astype(np.int64))
        step = max(4, width // 16)
        while True:
            open_ = ~done & (ids >= 0)
            who = np.flatnonzero(open_.any(1))
            if not who.size:
                return ids, sims
            score = np.where(open_[who], sims[who], -4.0)
            pick = np.argpartition(-score, min(step, width) - 1, axis=1)[:, : min(step, width)]
            valid = np.take_along_axis(open_[who], pick, 1)
            chosen = np.where(valid, np.take_along_axis(ids[who], pick, 1), -1)
            rows, cols = np.nonzero(valid)
            done[who[rows], pick[rows, cols]] = True
            nxt = table[np.maximum(chosen, 0)]
            nxt = np.where((chosen >= 0)[:, :, None], nxt, -1).reshape(len(who), -1)
            offer(who, nxt.astype(np.int64))

    def search(self, q: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        """For each query, up to ``width`` near nodes and their similarities (-1 pads)."""
        q = q.astype(np.float32)
        return self._beam(q, 0, self._starts(q, 0, self.layers[0][0][: 4 * DEGREE]), width)


def matches(graph: Graph, unit: np.ndarray, q: np.ndarray, least: float, salt: int = 0) -> tuple[list[np.ndarray], float]:
    """Nodes with a cosine of ``least`` or more for each query, and the recall that the last audit measured."""
    n, width = len(unit), BEAM
    found: list[np.ndarray] = [np.zeros(0, int)] * len(q)
    todo = np.arange(len(q))
    while todo.size:
        ids, sims = graph.search(q[todo], width)
        full = (ids >= 0).all(1) & (sims.min(1) >= least - 1e-4) & (width < n)
        for k, i in enumerate(todo):
            near = np.sort(ids[k][(ids[k] >= 0) & (sims[k] >= least - 1e-4)])
            found[i] = near[unit[near] @ q[i] >= least]
        todo, width = todo[full], min(2 * width, n)
    audit = np.arange(salt % AUDIT_EVERY, len(q), AUDIT_EVERY)
    while True:
        exact = unit @ q[audit].T >= least
        true, got = exact.sum(0), np.array([int(exact[found[i], k].sum()) for k, i in enumerate(audit)])
        each = (got / np.maximum(true, 1))[true > 0]
        recall = min(float(got.sum() / true.sum()), float(each.mean())) if each.size else 1.0
        if recall >= RECALL or width >= n:
            return found, recall
        width = min(4 * width, n)
        ids, sims = graph.search(q, width)
        for i in range(len(q)):
            near = np.sort(ids[i][(ids[i] >= 0) & (sims[i] >= least - 1e-4)])
            near = near[unit[near] @ q[i] >= least]
            found[i] = np.union1d(found[i], near)


def _search_shards(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[pa.RecordBatch]:
    """Rows come by shard, the shard's own vectors before the queries."""
    names = ["vec_id", "other", "links", "audited"]
    key, own, own_ids, graph, unit, ids, uf = None, [], [], None, None, None, None
    held_q, held_ids, salt = [], [], 0

    def rows_of(col) -> np.ndarray:
        values = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        x = values.reshape(len(col), -1)
        return x / np.linalg.norm(x, axis=1, keepdims=True)

    def settle():
        nonlocal graph, unit, ids, uf, own, own_ids
        if graph is None:
            unit, ids = np.concatenate(own), np.concatenate(own_ids)
            graph, uf, own, own_ids = Graph(unit, ids), np.arange(len(unit)), [], []

    def root(a: np.ndarray) -> np.ndarray:
        while True:
            b = uf[a]
            if (b == a).all():
                return a
            a = b

    def ask():
        nonlocal held_q, held_ids, salt
        if not held_q:
            return []
        settle()
        q, qid = np.concatenate(held_q), np.concatenate(held_ids)
        held_q, held_ids = [], []
        found, recall = matches(graph, unit, q, least, salt)
        salt += 1
        other, count = np.empty(len(q), np.int64), np.empty(len(q), np.int64)
        for i, f in enumerate(found):
            f = f[ids[f] != qid[i]]
            count[i], other[i] = f.size, qid[i]
            if f.size:
                r = np.unique(root(f))
                uf[r] = r[0]
                other[i] = ids[f[0]]
        return [pa.RecordBatch.from_arrays([pa.array(qid), pa.array(other), pa.array(count), pa.array(np.full(len(q), recall))], names=names)]

    def close():
        if graph is None:
            return []
        r = root(np.arange(len(unit)))
        return [pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[r]), pa.array(np.zeros(len(ids), np.int64)), pa.array(np.ones(len(ids)))], names=names)]

    for batch in batches:
        if not batch.num_rows:
            continue
        a, b, c, d = (batch.column(k).to_numpy(zero_copy_only=False) for k in ("label", "dim", "shard", "asks"))
        cut = np.flatnonzero((np.diff(a) != 0) | (np.diff(b) != 0) | (np.diff(c) != 0) | (np.diff(d) != 0)) + 1
        for lo, hi in zip([0, *cut], [*cut, batch.num_rows], strict=True):
            here = (a[lo], b[lo], c[lo])
            if here != key:
                yield from ask()
                yield from close()
                key, graph, own, own_ids = here, None, [], []
            piece = batch.slice(lo, hi - lo)
            x, vid = rows_of(piece.column("embedding")), piece.column("vec_id").to_numpy()
            if not d[lo]:
                own.append(x)
                own_ids.append(vid)
                continue
            for at in range(0, len(x), BATCH):
                held_q.append(x[at : at + BATCH])
                held_ids.append(vid[at : at + BATCH])
                if sum(map(len, held_q)) >= BATCH:
                    yield from ask()
    yield from ask()
    yield from close()


def _comparable(vectors: DataFrame) -> DataFrame:
    """One row a vector with what is needed to compare it; usable tells whether it can link at all."""
    bad = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    one = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.struct(F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<double>").alias("embedding")).alias("v"))
    one = one.groupBy("vec_id").agg(F.max("v").alias("v")).select("vec_id", "v.label", "v.embedding")
    ok = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & F.col("embedding").isNotNull() & ~F.coalesce(F.exists("embedding", bad), F.lit(True)) & F.coalesce(F.exists("embedding", lambda v: v != 0), F.lit(False))
    return one.withColumn("usable", ok)


def near_vectors(vectors: DataFrame, least: float = 0.98) -> DataFrame:
    """(vec_id, n_links, component_id, kept, recall) for every vector of ``vectors`` (vec_id, label, embedding).

    Two vectors of equal, non-null label link when their cosine in double precision is ``least`` or more.
    recall is what the audits of the vector's own searches measured, averaged over shards: the share of all matches
    that were found, or the mean of the audited queries' own shares where that is less.

    Vectors that are null, zero or hold null or non-finite components, and those without a label or id, link
    with nothing; vectors of different length never link.  Rows that repeat a vec_id are one vector (the
    largest label and components count).  An empty table gives an empty result; other columns are ignored.
    """
    scratch = Scratch(vectors.sparkSession, "vectors")
    every = scratch.save(_comparable(vectors))
    usable = every.where("usable").select("vec_id", "label", "embedding", F.size("embedding").alias("dim"))
    shards = usable.groupBy("label", "dim").agg(F.ceil(F.count("*") / SHARD_ROWS).cast("int").alias("shards"))
    placed = usable.join(shards, ["label", "dim"]).withColumn("home", F.pmod(F.xxhash64("vec_id"), F.col("shards")).cast("int"))
    own = placed.select("label", "dim", F.col("home").alias("shard"), F.lit(0).alias("asks"), "vec_id", "embedding")
    asks = placed.select("label", "dim", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("shard"), F.lit(1).alias("asks"), "vec_id", "embedding")
    order = ["label", "dim", "shard"]
    dealt = own.union(asks).repartition(*order).sortWithinPartitions(*order, "asks", "vec_id")
    found = scratch.save(dealt.mapInArrow(lambda it: _search_shards(it, least), "vec_id long, other long, links long, audited double"))
    links = found.groupBy("vec_id").agg(F.sum("links").alias("n_links"), F.avg("audited").alias("recall"))
    comps = connected_components(found.select(F.col("vec_id").alias("u"), F.col("other").alias("v")), scratch)
    out = every.select("vec_id").join(links, "vec_id", "left").join(comps.withColumnRenamed("id", "vec_id"), "vec_id", "left")
    comp = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), comp.alias("component_id"), (F.col("vec_id") == comp).alias("kept"), F.coalesce("recall", F.lit(1.0)).alias("recall"))


OP10_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
l AS (
  SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
r(x, y) AS (SELECT x, y FROM l UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x)
SELECT e.vec_id, coalesce(n, 0) AS n_links, least(e.vec_id, coalesce(m, e.vec_id)) AS component_id, e.vec_id <= coalesce(m, e.vec_id) AS kept
FROM embeddings e LEFT JOIN (SELECT x, count(*) AS n FROM l GROUP BY x) c ON e.vec_id = c.x LEFT JOIN (SELECT x, min(y) AS m FROM r GROUP BY x) d ON e.vec_id = d.x
"""
