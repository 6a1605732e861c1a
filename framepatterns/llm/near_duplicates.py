"""Near-duplicate documents by SetSketch registers.

Each text's shingle set becomes 96 registers: the register is the smallest of the set's exponentially
distributed hash values, rounded to a step of an exponential scale and truncated to 16 bits.  Registers of a
union are register-wise maxima, and two sets agree in a register with a probability that follows their
similarity.  Candidates share the registers of a band; the similarity of a candidate pair is tested by the
joint likelihood of its registers (how many are above, below, equal) given both set sizes; what passes is
verified on the full shingle sets.

Nothing grows with the square of a group.  Equal sets are merged first.  Every band, alone and joined with its
neighbours, links its members to one pivot; the verified links are contracted to components.  What is left are
band buckets with several components.  They are compared block by block, members of the largest component only
with the others, and the full sets are verified inside the block, so that no pair leaves it but links that join
two components.  So every candidate pair is either verified, or rejected by its likelihood, or already inside
one component, and the rows that travel are the open buckets' members, not their pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.llm.components import connected_components
from framepatterns.llm.scratch import Scratch, bitmap, few_pieces, map_batches, pieces, test_bits
from framepatterns.llm.words import hashed_rows, shingle_set

REGISTERS, BAND = 96, 4
BASE, RATE, TOP = 1.001, 20.0, (1 << 16) - 2
_MUL = np.random.default_rng(11).integers(1, 1 << 32, 768, dtype=np.uint32)[:REGISTERS] | np.uint32(1)
_ADD = np.random.default_rng(12).integers(0, 1 << 32, 768, dtype=np.uint32)[:REGISTERS]
#: A pair is rejected unverified when its best similarity below the threshold is e**9 times likelier than the threshold.
REJECT = 9.0
#: Members of a bucket and bytes of their sets on one side of a block.
BLOCK_ROWS, BLOCK_BYTES = 512, 8 << 20
#: Bytes of a sketched class or a result row with its overhead; a class has a key a band and one a group of three bands.
ROW_BYTES, KEYS = 320, REGISTERS // BAND + REGISTERS // (3 * BAND)
#: Documents that are picked by a bit set (of 8 bits each); more are picked by a join.
FEW = 1 << 24


def registers(shingles: np.ndarray) -> np.ndarray:
    """SetSketch registers of a set of 64-bit shingle hashes (all zero for the empty set); any prefix is a sketch."""
    if shingles.size == 0:
        return np.zeros(REGISTERS, np.uint16)
    h = (shingles >> np.uint64(32)).astype(np.uint32)
    low = np.full(REGISTERS, (1 << 32) - 1, np.uint32)
    for at in range(0, h.size, 2048):
        v = h[None, at : at + 2048] * _MUL[:, None]
        v += _ADD[:, None]
        np.minimum(low, v.min(axis=1), out=low)
    x = -np.log1p(-(low.astype(np.float64) + 0.5) / 2.0**32)
    return np.clip(np.floor(1 - np.log(x / RATE) / np.log(BASE)), 0, TOP + 1).astype(np.uint16)


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union of two sets."""
    return np.maximum(a, b)


def _log_likelihood(j, above, below, n1, n2, count=REGISTERS):
    """Log-likelihood of similarity j, given how many registers of the first set are above or below the second's."""
    u, v = n1 / (n1 + n2), n2 / (n1 + n2)
    p = lambda x: np.clip(-np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE), 1e-6, 1)
    up, down = p(u - v * j), p(v - u * j)
    same = np.clip(1 - up - down, 1e-6, 1)
    return above * np.log(up) + below * np.log(down) + (count - above - below) * np.log(same)


def likely(above: np.ndarray, below: np.ndarray, n1: np.ndarray, n2: np.ndarray, percent: int) -> np.ndarray:
    """False where the registers all but exclude a similarity of ``percent`` or more."""
    at = _log_likelihood(percent / 100, above, below, n1, n2)
    best = at
    for j in np.linspace(0, percent / 100, 33)[:-1]:
        best = np.maximum(best, _log_likelihood(j, above, below, n1, n2))
    return best - at <= REJECT


def estimate(a: np.ndarray, b: np.ndarray, n1: int, n2: int) -> float:
    """Maximum-likelihood similarity of two sketched sets of known sizes."""
    grid = np.linspace(0, min(n1, n2) / max(n1, n2), 501)
    return float(grid[np.argmax(_log_likelihood(grid, int((a > b).sum()), int((a < b).sum()), n1, n2, a.size))])


def _name(s: np.ndarray) -> tuple[np.uint64, np.uint64]:
    """Two hashes that, with the size, name a set."""
    return np.add.reduce(s * np.uint64(0xD6E8FEB86659FD93)).astype(np.uint64), np.bitwise_xor.reduce(s) if s.size else np.uint64(0)


def _sketch(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, fa, fb, regs = [], [], [], []
        for row, end, h, w in hashed_rows(batch.column("text"), lower=True):
            for i in range(end - row):
                s = shingle_set(h[w[i] : w[i + 1]], k)
                n.append(s.size)
                a, b = _name(s)
                fa.append(a)
                fb.append(b)
                regs.append(registers(s).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), _as_long(fa), _as_long(fb), pa.array(regs, pa.binary())], names=["doc_id", "n", "fa", "fb", "regs"])


def _as_long(x) -> pa.Array:
    return pa.array(np.array(x, np.uint64).view(np.int64))


def _sets(batches: Iterator[pa.RecordBatch], k: int, wanted) -> Iterator[pa.RecordBatch]:
    """(n, fa, fb, s): the full sets of the wanted documents."""
    for batch in batches:
        if wanted is not None:
            batch = batch.filter(pa.array(test_bits(wanted.value, batch.column("key").to_numpy().view(np.uint64))))
        for at in range(0, batch.num_rows, 512):
            part, out = batch.slice(at, 512), []
            for row, end, h, w in hashed_rows(part.column("text"), lower=True):
                out += [shingle_set(h[w[i] : w[i + 1]], k) for i in range(end - row)]
            names = [_name(s) for s in out]
            yield pa.RecordBatch.from_arrays([pa.array([s.size for s in out], pa.int64()), _as_long([a for a, _ in names]), _as_long([b for _, b in names]), pa.array([s.tobytes() for s in out], pa.binary())], names=["n", "fa", "fb", "s"])


def _verify(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x, y = batch.column("ux").to_numpy(), batch.column("uy").to_numpy()
        sx, sy = batch.column("sx"), batch.column("sy")
        rx, ry = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint16).reshape(-1, REGISTERS) for c in ("rx", "ry"))
        nx, ny = batch.column("nx").to_numpy(), batch.column("ny").to_numpy()
        keep = np.zeros(x.size, bool)
        for i in np.flatnonzero(likely((rx > ry).sum(1), (rx < ry).sum(1), nx, ny, percent)):
            a, b = np.frombuffer(sx[i].as_buffer(), np.uint64), np.frombuffer(sy[i].as_buffer(), np.uint64)
            if a.size > b.size:
                a, b = b, a
            at = np.searchsorted(b, a)
            common = int((b[np.minimum(at, b.size - 1)] == a).sum())
            keep[i] = 100 * common >= percent * (a.size + b.size - common)
        yield pa.RecordBatch.from_arrays([pa.array(x[keep]), pa.array(y[keep])], names=["u", "v"])


def _runs(batches: Iterator[pa.RecordBatch], names: list[str]) -> Iterator[pa.Table]:
    """Consecutive rows with equal values in the columns ``names``, whole runs at a time."""
    held: list[pa.RecordBatch] = []

    def cut(table: pa.Table):
        if not table.num_rows:
            return []
        change = np.zeros(table.num_rows - 1, bool)
        for c in names:
            v = table.column(c).to_numpy()
            change |= v[1:] != v[:-1]
        bounds = [0, *(np.flatnonzero(change) + 1), table.num_rows]
        out = [table.slice(a, b - a) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        return out

    for batch in batches:
        if batch.num_rows == 0:
            continue
        held.append(batch)
        pieces = cut(pa.Table.from_batches(held).combine_chunks())
        yield from pieces[:-1]
        held = pieces[-1].to_batches()
    if held:
        yield from cut(pa.Table.from_batches(held).combine_chunks())


def _cross_links(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """(u, v): links that join components, between the members with home i and those with home j of every block.

    A pair is looked at in its first common band only.  Components that a link joins are one from then on, so a
    block emits fewer links than it has components.
    """
    for t in _runs(batches, ["key", "i", "j"]):
        ids, nodes, comp, n, band, home = (t.column(c).to_numpy() for c in ("id", "node", "comp", "n", "band", "home"))
        i, j, b = int(t.column("i")[0].as_py()), int(t.column("j")[0].as_py()), int(band[0])
        left, right = np.flatnonzero(home == i), np.flatnonzero(home == j)
        if not left.size or not right.size:
            continue
        regs = np.frombuffer(b"".join(t.column("regs").to_pylist()), np.uint16).reshape(-1, REGISTERS)
        shingles = np.frombuffer(b"".join(t.column("s").to_pylist()), np.uint64)
        end = np.cumsum(n)
        universe, code = np.unique(shingles, return_inverse=True)
        mark, root = np.zeros(universe.size, bool), np.unique(comp, return_inverse=True)[1]
        us, vs = [], []
        for r in left:
            c = right[(root[right] != root[r]) & (100 * np.minimum(n[right], n[r]) >= percent * np.maximum(n[right], n[r]))]
            if i == j:
                c = c[ids[c] > ids[r]]
            if b and c.size:
                same = regs[c, : b * BAND] == regs[r, : b * BAND]
                c = c[~same.reshape(c.size, -1, BAND).all(2).any(1)]
            if c.size:
                c = c[likely((regs[r] > regs[c]).sum(1), (regs[r] < regs[c]).sum(1), np.full(c.size, n[r]), n[c], percent)]
            if not c.size:
                continue
            own = code[end[r] - n[r] : end[r]]
            mark[own] = True
            starts = np.concatenate(([0], np.cumsum(n[c])[:-1]))
            common = np.add.reduceat(mark[np.concatenate([code[end[x] - n[x] : end[x]] for x in c])].astype(np.int64), starts)
            mark[own] = False
            for x in c[100 * common >= percent * (n[r] + n[c] - common)]:
                if root[x] != root[r]:
                    us.append(nodes[r])
                    vs.append(nodes[x])
                    root[root == root[x]] = root[r]
        if us:
            yield pa.RecordBatch.from_arrays([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])


def _band_keys(width: int) -> list:
    """Hashes of groups of ``width`` neighbouring bands."""
    size = 2 * BAND * width
    return [F.xxhash64(F.lit(width * 1000 + i), F.substring("regs", i * size + 1, size)) for i in range(REGISTERS // (BAND * width))]


_CLASS = F.xxhash64  # of n, fa, fb: the id of a class of equal sets
#: Nodes from here on are classes without any doc_id.
NAMELESS = 1 << 62


def _open_blocks(members: DataFrame, sets: DataFrame) -> DataFrame:
    """Blocks of the band buckets that hold several components: key, i, j, home and a member with its set.

    A bucket's members outside its largest component are cut into parts, and so are the others.  Parts of the
    former meet each other and the latter; members of the largest component never meet.
    """
    size = F.col("n") * 8
    rows = members.select("id", "comp", "n", F.posexplode(F.array(*_band_keys(1))).alias("band", "key"))
    by_comp = rows.groupBy("key", "comp").agg(F.count("*").alias("c"), F.sum(size).alias("b"))
    per_key = by_comp.groupBy("key").agg(F.max(F.struct("c", "b", "comp")).alias("m"), F.sum("c").alias("c"), F.sum("b").alias("b")).where(F.col("c") > F.col("m.c"))
    parts = lambda c, b: F.greatest(F.ceil(c / BLOCK_ROWS), F.ceil(b / BLOCK_BYTES)).cast("long")
    open_ = per_key.select("key", F.col("m.comp").alias("major"), parts(F.col("c") - F.col("m.c"), F.col("b") - F.col("m.b")).alias("few"), parts(F.col("m.c"), F.col("m.b")).alias("many"))
    at = rows.join(open_, "key")
    draw, major = F.xxhash64(F.lit("home"), F.col("id")), F.col("comp") == F.col("major")
    at = at.withColumn("home", F.when(major, F.col("few") + F.pmod(draw, F.col("many"))).otherwise(F.pmod(draw, F.col("few"))))
    others = F.when(major, F.sequence(F.lit(0).cast("long"), F.col("few") - 1)).otherwise(F.sequence(F.lit(0).cast("long"), F.col("few") + F.col("many") - 1))
    meets = at.select("key", "band", "id", "comp", "home", F.explode(others).alias("o"))
    meets = meets.select("key", "band", "id", "comp", "home", F.least("home", "o").alias("i"), F.greatest("home", "o").alias("j"))
    return meets.join(sets.select("id", "node", "n", "regs", "s"), "id")


def near_duplicates(docs: DataFrame, shingle: int = 4, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs`` (columns doc_id and text).

    Words are lower-cased in A-Z; a text's set is its distinct ``shingle``-word shingles (the whole sequence
    where it has fewer words).  Two documents are linked when 100 * intersection >= percent * union, which is
    confirmed on the full sets (as 64-bit hashes).  component_id is the smallest doc_id reachable by links.

    Null and empty texts and texts without words have an empty set and link with nothing, also not with each
    other.  Texts are read whole, however long.  Rows that repeat a doc_id are one document: each comes back with
    its own text's n_shingles, and what one of its texts is linked with, the document is linked with.  A null
    doc_id names no component; ids are below 2**62.  An empty table gives an empty result; columns other than doc_id and text are
    ignored.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "near")
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sketches = scratch.save(map_batches(few_pieces(source), lambda it: _sketch(it, shingle), "doc_id long, n long, fa long, fb long, regs binary").withColumn("id", _CLASS("n", "fa", "fb")))
    rows = sketches.count()
    node = F.coalesce("rep", F.col("id").bitwiseAND(F.lit(NAMELESS - 1)) + NAMELESS)  # a class goes by its smallest doc_id
    classes = scratch.save(sketches.where("n > 0").groupBy("id").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("regs").alias("regs")).withColumn("node", node).coalesce(pieces(rows, rows * ROW_BYTES)))

    banded = classes.select("id", "n", F.explode(F.array(*_band_keys(1), *_band_keys(3))).alias("key"))
    pivots = banded.groupBy("key").agg(F.min("id").alias("pivot"), F.count("*").alias("c")).where("c > 1").select("key", "pivot")
    pairs = scratch.save(banded.join(pivots, "key").where("id <> pivot").select(F.col("id").alias("x"), F.col("pivot").alias("y")).distinct(), KEYS * rows)
    touched = scratch.save(pairs.select(F.explode(F.array("x", "y")).alias("id")).distinct(), rows)
    few, size = classes.join(touched, "id", "left_semi").agg(F.count("*"), F.coalesce(F.sum(8 * F.col("n") + ROW_BYTES), F.lit(0))).first()

    # one document of each touched class gives the class's set
    wanted = classes.join(touched, "id", "left_semi").select(F.xxhash64("rep").alias("key"))
    keyed = source.withColumn("key", F.xxhash64("doc_id"))
    if few <= FEW:
        bits = spark.sparkContext.broadcast(bitmap(wanted, "key", max(16, (8 * few).bit_length())))
        raw = map_batches(keyed, lambda it: _sets(it, shingle, bits), "n long, fa long, fb long, s binary")
    else:
        raw = map_batches(keyed.join(wanted.distinct(), "key", "left_semi"), lambda it: _sets(it, shingle, None), "n long, fa long, fb long, s binary")
    full = raw.select(_CLASS("n", "fa", "fb").alias("id"), "s").join(touched, "id").dropDuplicates(["id"])
    sets = scratch.save(full.join(classes.select("id", "node", "n", "regs"), "id").coalesce(pieces(few, size)))

    def confirmed(candidates: DataFrame) -> DataFrame:
        sx, sy = (sets.select(F.col("id").alias(v), F.col("node").alias("u" + v), F.col("s").alias("s" + v), F.col("n").alias("n" + v), F.col("regs").alias("r" + v)) for v in "xy")
        both = candidates.join(sx, "x").join(sy, "y").where(100 * F.least("nx", "ny") >= percent * F.greatest("nx", "ny"))
        return map_batches(both, lambda it: _verify(it, percent), "u long, v long")

    # a doc_id with several texts is a node beside those of its classes
    own = sketches.where("n > 0 and doc_id is not null").groupBy("doc_id").agg(F.min("id").alias("a"), F.max("id").alias("b")).where("a <> b").select("doc_id")
    repeated = sketches.where("n > 0").join(own, "doc_id").join(classes.select("id", "node"), "id").select(F.col("doc_id").alias("u"), F.col("node").alias("v"))
    n_pairs = pairs.count()
    verified = confirmed(pairs).coalesce(pieces(n_pairs, 2 * n_pairs * size // max(few, 1)))
    links = scratch.save(verified.union(repeated.coalesce(pieces(rows))))
    labels = connected_components(links, scratch, rows=n_pairs + rows)

    members = sets.select("id", "node", "n", "regs").join(labels.withColumnRenamed("id", "node"), "node", "left").select("id", "n", "regs", F.coalesce("component", "node").alias("comp"))
    blocks = _open_blocks(members, sets)
    crossing = map_batches(blocks.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j"), lambda it: _cross_links(it, percent), "u long, v long")
    final = connected_components(links.union(crossing), scratch, rows=KEYS * rows)

    of_class = classes.select("id", "node").join(final.withColumnRenamed("id", "node"), "node", "left").withColumn("c", F.coalesce("component", "node"))
    of_class = of_class.select("id", F.when(F.col("c") < NAMELESS, F.col("c")).alias("c"))
    out = sketches.select("doc_id", "n", "id").join(of_class, "id", "left").coalesce(pieces(rows, rows * ROW_BYTES))
    comp = F.coalesce("c", "doc_id")
    return out.select("doc_id", F.col("n").alias("n_shingles"), comp.alias("component_id"), (F.col("doc_id") == comp).alias("kept"))


OP2_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
s AS (
  SELECT doc_id, CASE WHEN len(w) >= 4 THEN list_distinct([array_to_string(w[i:i + 3], ' ') FOR i IN range(1, len(w) - 2)])
                      WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s
  FROM w),
g AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
l AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM g a JOIN g b ON a.g = b.g AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
r(x, y) AS (SELECT x, y FROM l UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x)
SELECT s.doc_id, CAST(len(s) AS BIGINT) AS n_shingles, least(s.doc_id, coalesce(m, s.doc_id)) AS component_id,
       s.doc_id <= coalesce(m, s.doc_id) AS kept
FROM s LEFT JOIN (SELECT x, min(y) AS m FROM r GROUP BY x) c ON s.doc_id = c.x
"""
