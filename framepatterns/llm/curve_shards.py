"""Sharding along a Hilbert curve over quantised metadata, with DataFrame functions only.

Each dimension is quantised to a few bits; the cells of the grid are visited in the order of the Hilbert
curve, so a run of consecutive cells is compact in every dimension and a file that holds a run has narrow
minima and maxima in all of them.  Rows are numbered along the curve and cut into shards of equal row counts.

Numbering never sorts the table in one place: a row's number is the rows of earlier cells, plus the rows of
earlier slices of its own cell, plus its place in its slice.  Cells are bounded by the grid; slices split a cell by
the hash of its rows' keys, at least SLICES and so many that a slice has about SLICE_ROWS rows at most.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.llm.scratch import Scratch, few_pieces, pieces, short_reads

SLICES, SLICE_ROWS = 64, 65_536
#: Bytes of documents that one task reads at least for their digests, however many cores are free.
READ_BYTES = 64 << 20


def log_scale(size: Column, bits: int) -> Column:
    """Quantise a count: its bit length and the bit below the first, so two steps for each doubling."""
    digits = F.bin(F.coalesce(size, F.lit(0)) + 2)
    return F.least(2 * F.length(digits) + F.substring(digits, 2, 1).cast("int") - 4, F.lit((1 << bits) - 1)).cast("int")


def category(value: Column, bits: int) -> Column:
    """Quantise a name by its checksum; null is a category of its own."""
    return F.pmod(F.crc32(F.coalesce(F.concat(F.lit("="), value.cast("string")), F.lit("")).cast("binary")), F.lit(1 << bits)).cast("int")


def once(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with ``value`` evaluated once a row, however often and in whatever inner function it is used."""
    return F.element_at(F.transform(F.array(value), use), 1)


def hilbert_index(dims: list[Column], bits: int) -> Column:
    """Position of a grid cell on the Hilbert curve through 2**bits cells a dimension.

    The coordinates are turned in place, bit plane by bit plane from the top, then Gray-coded and interleaved.
    """
    n = len(dims)
    steps = F.array(*[F.struct(F.lit(b).alias("b"), F.lit(i).alias("i")) for b in range(bits - 1, 0, -1) for i in range(n)])

    def turn(x: Column, step: Column) -> Column:
        i = step["i"]
        low = F.call_function("shiftleft", F.lit(1), step["b"]) - 1
        here = F.element_at(x, i + 1)
        first = F.element_at(x, F.lit(1))
        flip = F.call_function("shiftright", here, step["b"]).bitwiseAND(F.lit(1)) == 1
        swap = first.bitwiseXOR(here).bitwiseAND(low)
        return F.transform(
            x,
            lambda v, j: F.when(flip, F.when(j == 0, v.bitwiseXOR(low)).otherwise(v)).otherwise(F.when((j == 0) | (j == i), F.when(i == 0, v).otherwise(v.bitwiseXOR(swap))).otherwise(v)),
        )

    def low_bits(gray: Column) -> Column:
        return F.aggregate(
            F.array(*[F.lit(b) for b in range(bits - 1, 0, -1)]),
            F.lit(0),
            lambda t, b: F.when(F.call_function("shiftright", F.element_at(gray, -1), b).bitwiseAND(F.lit(1)) == 1, t.bitwiseXOR(F.call_function("shiftleft", F.lit(1), b) - 1)).otherwise(t),
        )

    def interleaved(final: Column) -> Column:
        return F.aggregate(places, F.lit(0).cast("long"), lambda acc, p: acc * 2 + F.call_function("shiftright", F.element_at(final, p["i"] + 1), p["b"]).bitwiseAND(F.lit(1)))

    places = F.array(*[F.struct(F.lit(b).alias("b"), F.lit(i).alias("i")) for b in range(bits - 1, -1, -1) for i in range(n)])
    turned = F.aggregate(steps, F.array(*[d.cast("int") for d in dims]), turn)
    gray = F.aggregate(turned, F.expr("cast(array() as array<int>)"), lambda acc, v: F.concat(acc, F.array(v.bitwiseXOR(F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit(0))))))
    return once(gray, lambda gray: once(low_bits(gray), lambda fix: once(F.transform(gray, lambda v: v.bitwiseXOR(fix)), interleaved)))


def document_dimensions(bits: int = 6) -> list[Column]:
    """Size, language and source of a document."""
    return [log_scale(F.octet_length("text"), bits), category(F.col("lang"), bits), category(F.col("source"), bits)]


def curve_shards(docs: DataFrame, shards: int = 24, dims: list[Column] | None = None, bits: int = 6, key: str = "doc_id", tie: Column | None = None, carry: list[str] | None = None) -> DataFrame:
    """Rows with curve (cell's index on the curve), shard and slot (place in its shard, from 0).

    Shard sizes differ by one row at most, the larger ones first.  Rows of one cell are in the order of a hash
    of ``key``, then ``key``, then ``tie``; rows equal in all of these are interchangeable.  ``carry`` names the
    columns to keep (default all).

    A null dimension counts as 0 and null keys come first; with fewer rows than shards the last shards are empty;
    an empty table gives an empty result; texts of any length only travel.  Columns named like a result are
    replaced.
    """
    dims = [F.coalesce(d, F.lit(0)) for d in (document_dimensions(bits) if dims is None else dims)]
    names = [f"_d{i}" for i in range(len(dims))]
    placed = [d.alias(n) for d, n in zip(dims, names, strict=True)]
    # cells with more rows than SLICES slices should hold: fewer than one for each SLICES * SLICE_ROWS rows
    large = docs.select(*placed).groupBy(*names).agg(F.count("*").alias("_m")).where(F.col("_m") > SLICES * SLICE_ROWS)
    large = F.broadcast(large.select(*[F.col(n).alias(f"_l{n}") for n in names], F.ceil(F.col("_m") / SLICE_ROWS).alias("_slices")))

    def sliced(df: DataFrame, by: str) -> DataFrame:
        same = reduce(lambda a, b: a & b, [F.col(n) == F.col(f"_l{n}") for n in names])
        slice_ = F.pmod(F.xxhash64(F.col(by)), F.coalesce(F.col("_slices"), F.lit(SLICES))).cast("int")
        return df.join(large, same, "left").withColumn("_slice", slice_).drop("_slices", *[f"_l{n}" for n in names])

    keep = [c for c in docs.columns if c not in ("curve", "shard", "slot")] if carry is None else carry
    tie = F.lit(0) if tie is None else tie
    rows = sliced(docs.select(F.struct(*keep).alias("_row"), *placed, F.col(key).alias("_key"), tie.alias("_tie")), "_key")
    parts = sliced(docs.select(*placed, F.col(key).alias("_key")), "_key").groupBy(*names, "_slice").agg(F.count("*").alias("_n"))
    in_cell = W.Window.partitionBy(*names).orderBy("_slice").rowsBetween(W.Window.unboundedPreceding, -1)
    parts = parts.withColumn("_before", F.coalesce(F.sum("_n").over(in_cell), F.lit(0)))
    cells = parts.groupBy(*names).agg(F.sum("_n").alias("_cell_n")).withColumn("curve", hilbert_index([F.col(n) for n in names], bits))
    along = W.Window.orderBy("curve").rowsBetween(W.Window.unboundedPreceding, -1)
    everything = W.Window.orderBy("curve").rowsBetween(W.Window.unboundedPreceding, W.Window.unboundedFollowing)
    cells = cells.select(*names, "curve", F.coalesce(F.sum("_cell_n").over(along), F.lit(0)).alias("_cell_before"), F.sum("_cell_n").over(everything).alias("_total"))
    offsets = parts.join(cells, names).select(*names, "_slice", "curve", (F.col("_before") + F.col("_cell_before")).alias("_offset"), "_total")
    place = F.row_number().over(W.Window.partitionBy(*names, "_slice").orderBy("_key", "_tie")) - 1
    at = rows.withColumn("_place", place).join(offsets, [*names, "_slice"])
    at = at.withColumn("_at", F.col("_offset") + F.col("_place"))
    base, extra = F.floor(F.col("_total") / shards), F.pmod(F.col("_total"), F.lit(shards))
    edge = extra * (base + 1)
    shard = F.when(F.col("_at") < edge, F.floor(F.col("_at") / (base + 1))).otherwise(extra + F.floor((F.col("_at") - edge) / F.greatest(base, F.lit(1))))
    at = at.withColumn("shard", shard.cast("int"))
    start = F.col("shard") * base + F.least(F.col("shard"), extra)
    return at.withColumn("slot", (F.col("_at") - start).cast("long")).select("_row.*", "curve", "shard", "slot")


def document_shards(docs: DataFrame, shards: int = 24, bits: int = 6) -> DataFrame:
    """Shards of all documents as digests: doc_id, size (bytes of the text plus 8), text_crc32, curve, shard, slot.

    Texts don't travel: they are read once, and only numbers are kept and shuffled.  The result has a partition for
    each ROWS_PER_FILE rows at most.  A null text has no bytes and the checksum of no bytes.
    """
    thin = few_pieces(docs, READ_BYTES, 0).select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        *[d.alias(f"dim{i}") for i, d in enumerate(document_dimensions(bits))],
    )
    with short_reads(docs.sparkSession):
        thin = Scratch(docs.sparkSession, "curve_shards").save(thin)
    done = curve_shards(thin, shards, [F.col(f"dim{i}") for i in range(3)], bits, tie=F.col("text_crc32"))
    return done.select("doc_id", "size", "text_crc32", "curve", "shard", "slot", "dim0", "dim1", "dim2").coalesce(pieces(thin.count()))


def shard_manifest(sharded: DataFrame, dims: list[str]) -> DataFrame:
    """Rows, and minimum and maximum of each dimension, of every shard: what a reader prunes files by."""
    ranges = [f(F.col(d)).alias(f"{n}_{d}") for d in dims for n, f in (("min", F.min), ("max", F.max))]
    return sharded.groupBy("shard").agg(F.count("*").alias("rows"), *ranges)


def write_shards(sharded: DataFrame, path: str, rows_per_file: int = 1_000_000) -> None:
    """Write one folder a shard, rows in slot order, in files of bounded length.

    A shard is written by as many tasks as it has files, so no shard has to fit into one task.
    """
    piece = F.floor(F.col("slot") / rows_per_file)
    placed = sharded.withColumn("_piece", piece)
    placed.repartition("shard", "_piece").sortWithinPartitions("shard", "slot").drop("_piece").write.option("maxRecordsPerFile", rows_per_file).partitionBy("shard").parquet(path)


def prune(manifest: DataFrame, bounds: dict[str, tuple]) -> DataFrame:
    """The shards whose ranges meet all bounds {dimension: (low, high)}."""
    tests = [(F.col(f"max_{d}") >= lo) & (F.col(f"min_{d}") <= hi) for d, (lo, hi) in bounds.items()]
    return manifest.where(reduce(lambda a, b: a & b, tests, F.lit(True)))
