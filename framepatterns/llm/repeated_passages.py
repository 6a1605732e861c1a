"""Substring de-duplication by level-wise doubling of repeated windows.

A level's candidates are the windows all of whose parts of half the length were repeated at the level before; only
these are hashed and compared.  Level one looks at windows of about half the target length.  Of the short windows
inside a target window only the one with the smallest hash is looked up, so a level-one pass moves about a
quarter of the positions, and two equal target windows always look up the same short window.  Target windows
around a short window that occurs twice are compared at the target length, which is all that ``remove_repeats``
needs; ``doubled_repeats`` goes on from its survivors to twice, four times ... that length, without reading the
texts again, until no candidate survives.

Two windows are equal when two independent hashes agree, 96 bits in all.

Hashes travel packed: a task sends one row for each hash bucket, not one for each window, and sends a window
once at most, for the first of its own documents that has it; its other documents are settled at once.  So a
passage that a third of all documents share costs one entry a task.  Buckets follow the number of shuffle
partitions and are read one at a time.

Which short windows are repeated is known to the tasks by a bit set of eight bits a window, as long as that takes
at most FILTER_BYTES.  Beyond it, every document gets its own repeated short windows by a join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.llm.packing import bucket_bits, bucket_runs
from framepatterns.llm.scratch import Scratch, bitmap, test_bits
from framepatterns.llm.words import grams, hashed_rows, mix, sliding_min

#: Bytes of the bit set that may be broadcast.
FILTER_BYTES = 1 << 24
#: Multiplier of the second hash, and those that join the hashes of two neighbouring windows.
_SECOND, _LEFT, _RIGHT = np.uint64(0xA24BAED4963EE407), np.uint64(0x9FB21C651E98DF25), np.uint64(0xD6E8FEB86659FD93)
#: Windows that a map task holds before it packs and sends them.
PACK = 1 << 19


def _by_bucket(bucket: np.ndarray) -> Iterator[tuple[int, slice]]:
    """Runs of equal values of a sorted array."""
    cut = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1], [True])))
    for lo, hi in zip(cut[:-1], cut[1:], strict=True):
        yield int(bucket[lo]), slice(lo, hi)


def _anchor_key(a: np.ndarray, bits: int) -> np.ndarray:
    """The part of a short window's hash that names it: its bucket and 32 bits more."""
    return a >> np.uint64(32 - bits)


def _anchors(batches: Iterator[pa.RecordBatch], short: int, length: int, bits: int) -> Iterator[pa.RecordBatch]:
    """(bucket, packed keys) of the short windows with the smallest hash of their target window.

    A key is sent once, or twice if two texts of this task have it.
    """
    held: list[np.ndarray] = []
    have = 0

    def pack() -> pa.RecordBatch:
        keys, n = np.unique(np.concatenate(held), return_counts=True)
        keys = np.repeat(keys, np.minimum(n, 2))
        runs = list(_by_bucket(keys >> np.uint64(32)))
        low = keys.astype(np.uint32)
        return pa.RecordBatch.from_arrays([pa.array([b for b, _ in runs], pa.int64()), pa.array([low[r].tobytes() for _, r in runs], pa.binary())], names=["bucket", "keys"])

    for batch in batches:
        for _, _, h, w in hashed_rows(batch.column("text")):
            g = grams(h, short)
            for i in np.flatnonzero(np.diff(w) >= length):
                a = np.unique(_anchor_key(sliding_min(g[w[i] : w[i + 1] - short + 1], length - short + 1), bits))
                held.append(a)
                have += a.size
            if have > PACK:
                yield pack()
                held, have = [], 0
    if have:
        yield pack()


def _repeated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Keys that came twice."""
    for bucket, rows in bucket_runs(batches):
        low = np.sort(np.frombuffer(b"".join(r["keys"] for r in rows), np.uint32))
        twice = np.unique(low[1:][low[1:] == low[:-1]]).astype(np.int64)
        if twice.size:
            yield pa.RecordBatch.from_arrays([pa.array(twice | (bucket << 32))], names=["a"])


def check_hash(h: np.ndarray, length: int) -> np.ndarray:
    """A second 32-bit hash of the windows, from other multiples of the words' hashes."""
    return grams(mix(h * _SECOND + np.uint64(1)), length).astype(np.uint32)


def _settle(h: np.ndarray, check: np.ndarray, doc: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, ...]:
    """Sort windows by their hashes, document and place; mark those that an earlier document has too."""
    order = np.lexsort((pos, doc, check, h))
    h, check, doc, pos = h[order], check[order], doc[order], pos[order]
    new = np.concatenate(([True], (h[1:] != h[:-1]) | (check[1:] != check[:-1])))
    first = doc[np.flatnonzero(new)][np.cumsum(new) - 1]
    return h, check, doc, pos, doc > first


def _removed(doc: np.ndarray, pos: np.ndarray) -> tuple[list[int], list[bytes]]:
    """Places by document, packed."""
    order = np.argsort(doc, kind="stable")
    doc, pos = doc[order], pos[order].astype(np.int32)
    runs = list(_by_bucket(doc)) if doc.size else []
    return [d for d, _ in runs], [pos[r].tobytes() for _, r in runs]


_PACKED = "bucket long, doc_id long, h binary, c binary, doc binary, pos binary"


def _packed(bucket, doc_id, *packs) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(bucket, pa.int64()), pa.array(doc_id, pa.int64()), *[pa.array(x, pa.binary()) for x in packs]], names=["bucket", "doc_id", "h", "c", "doc", "pos"])


def _pieces(runs, *columns) -> list[list[bytes]]:
    return [[x[r].tobytes() for _, r in runs] for x in columns]


def _windows(batches: Iterator[pa.RecordBatch], short: int, length: int, bits: int, repeated, settle: bool = True) -> Iterator[pa.RecordBatch]:
    """Packed target windows around a short window that may be repeated.

    Rows without doc_id hold windows of a bucket, with ``settle`` of the first document of this task that has
    them; rows with doc_id hold the places of windows that an earlier document of this task has too.  ``repeated``
    is a broadcast bit set; without one, the rows bring the document's own short windows (column anchors).
    """
    held: list[list[np.ndarray]] = [[], [], [], []]
    have = 0

    def pack() -> Iterator[pa.RecordBatch]:
        h, check, doc, pos, later = _settle(*[np.concatenate(x) for x in held])
        if settle:
            gone, where = _removed(doc[later], pos[later])
            if gone:
                none = [None] * len(gone)
                yield _packed([d & ((1 << bits) - 1) for d in gone], gone, none, none, none, where)
            h, check, doc, pos = h[~later], check[~later], doc[~later], pos[~later]
        runs = list(_by_bucket(h >> np.uint64(64 - bits)))
        yield _packed([b for b, _ in runs], [None] * len(runs), *_pieces(runs, h, check, doc, pos.astype(np.int32)))

    for batch in batches:
        known = np.asarray(batch.column("doc_id").is_valid())
        ids = batch.column("doc_id").fill_null(0).to_numpy()
        own = None if repeated is not None else batch.column("anchors")
        for row, _, h, w in hashed_rows(batch.column("text")):
            g, full = grams(h, short), grams(h, length)
            for i in np.flatnonzero((np.diff(w) >= length) & known[row : row + w.size - 1]):
                a = _anchor_key(sliding_min(g[w[i] : w[i + 1] - short + 1], length - short + 1), bits)
                if own is None:
                    at = np.flatnonzero(test_bits(repeated.value, a))
                else:
                    at = np.flatnonzero(np.isin(a, np.frombuffer(own[row + i].as_buffer(), np.uint64))) if own[row + i].is_valid else np.zeros(0, int)
                if at.size:
                    check = check_hash(h[w[i] : w[i + 1]], length)[at]
                    for kept, x in zip(held, (full[w[i] + at], check, np.full(at.size, ids[row + i]), at), strict=True):
                        kept.append(x)
                    have += at.size
            if have > PACK:
                yield from pack()
                held, have = [[], [], [], []], 0
    if have:
        yield from pack()


def _unpack(rows: list[dict]) -> tuple[np.ndarray, ...]:
    return tuple(np.frombuffer(b"".join(r[c] for r in rows if r["doc_id"] is None), t) for c, t in (("h", np.uint64), ("c", np.uint32), ("doc", np.int64), ("pos", np.int32)))


def _later_places(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """Windows that also start in an earlier document, packed by the bucket of their document."""
    docs, places, have = [], [], 0
    for _, rows in bucket_runs(batches):
        h, check, doc, pos = _unpack(rows)
        if h.size:
            _, _, doc, pos, later = _settle(h, check, doc, pos)
            doc, pos = doc[later], pos[later]
        for r in rows:
            if r["doc_id"] is not None:
                p = np.frombuffer(r["pos"], np.int32)
                docs.append(np.full(p.size, r["doc_id"]))
                places.append(p)
                have += p.size
        if doc.size:
            docs.append(doc)
            places.append(pos)
            have += doc.size
        if have > 2 * PACK:
            yield _by_document(np.concatenate(docs), bits, pos=np.concatenate(places).astype(np.int32))
            docs, places, have = [], [], 0
    if have:
        yield _by_document(np.concatenate(docs), bits, pos=np.concatenate(places).astype(np.int32))


def _places_by_document(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, packed places), one row a document."""
    for _, rows in bucket_runs(batches):
        doc, pos = (np.frombuffer(b"".join(r[c] for r in rows), t) for c, t in (("doc", np.int64), ("pos", np.int32)))
        d, p = _removed(doc, pos)
        yield pa.RecordBatch.from_arrays([pa.array(d, pa.int64()), pa.array(p, pa.binary())], names=["doc_id", "places"])


def later_places(docs: DataFrame, length: int = 13) -> DataFrame:
    """(doc_id, places): for each document with repeats, the packed 32-bit word positions of windows that an earlier document has."""
    bits = bucket_bits(docs.sparkSession)
    packed = _packed_windows(docs, length).mapInArrow(lambda it: _later_places(it, bits), "bucket long, doc binary, pos binary")
    return packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_places_by_document, "doc_id long, places binary")


def _cut(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts, starts = batch.column("text"), batch.column("starts")
        total, gone, kept = [], [], []
        for i in range(batch.num_rows):
            raw = texts[i].as_buffer()
            words = raw.to_pybytes().split() if raw is not None else []
            if starts[i].is_valid:
                edge = np.zeros(len(words) + 1, np.int32)
                p = np.frombuffer(starts[i].as_buffer(), np.int32)
                p = p[p < len(words)]  # places of another text of this doc_id may lie beyond the end
                np.add.at(edge, p, 1)
                np.add.at(edge, np.minimum(p + length, len(words)), -1)
                covered = np.cumsum(edge)[:-1] > 0
                gone.append(int(covered.sum()))
                total.append(len(words))
                words = [words[j] for j in np.flatnonzero(~covered)]
            else:
                gone.append(0)
                total.append(len(words))
            kept.append(b" ".join(words))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(total, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())], names=["doc_id", "n_words", "n_removed", "kept_text"])


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def _anchor_places(batches: Iterator[pa.RecordBatch], short: int, length: int, bits: int) -> Iterator[pa.RecordBatch]:
    """(bucket, keys, doc): short windows and their documents, packed by bucket."""
    held, docs, have = [], [], 0

    def pack() -> pa.RecordBatch:
        keys, doc = np.concatenate(held), np.concatenate(docs)
        order = np.argsort(keys, kind="stable")
        keys, doc = keys[order], doc[order]
        runs = list(_by_bucket(keys >> np.uint64(32)))
        low, doc = _pieces(runs, keys.astype(np.uint32), doc)
        return pa.RecordBatch.from_arrays([pa.array([b for b, _ in runs], pa.int64()), pa.array(low, pa.binary()), pa.array(doc, pa.binary())], names=["bucket", "keys", "doc"])

    for batch in batches:
        ids = batch.column("doc_id").to_numpy()
        for row, _, h, w in hashed_rows(batch.column("text")):
            g = grams(h, short)
            for i in np.flatnonzero(np.diff(w) >= length):
                a = np.unique(_anchor_key(sliding_min(g[w[i] : w[i + 1] - short + 1], length - short + 1), bits))
                held.append(a)
                docs.append(np.full(a.size, ids[row + i]))
                have += a.size
            if have > PACK:
                yield pack()
                held, docs, have = [], [], 0
    if have:
        yield pack()


def _by_document(doc: np.ndarray, bits: int, **columns: np.ndarray) -> pa.RecordBatch:
    """Entries packed by the bucket of their document."""
    bucket = mix(doc.view(np.uint64)) >> np.uint64(64 - bits)
    order = np.lexsort((doc, bucket))
    runs = list(_by_bucket(bucket[order]))
    packs = _pieces(runs, doc[order], *[x[order] for x in columns.values()])
    return pa.RecordBatch.from_arrays([pa.array([b for b, _ in runs], pa.int64()), *[pa.array(x, pa.binary()) for x in packs]], names=["bucket", "doc", *columns])


def _repeated_places(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """(bucket, doc, key): the short windows that came twice, packed by document."""
    for bucket, rows in bucket_runs(batches):
        low, doc = (np.frombuffer(b"".join(r[c] for r in rows), t) for c, t in (("keys", np.uint32), ("doc", np.int64)))
        key, at, n = np.unique(low, return_inverse=True, return_counts=True)
        twice = n[at] > 1
        if twice.any():
            yield _by_document(doc[twice], bits, key=low[twice].astype(np.uint64) | np.uint64(bucket << 32))


def _anchors_by_document(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for _, rows in bucket_runs(batches):
        doc, key = (np.frombuffer(b"".join(r[c] for r in rows), t) for c, t in (("doc", np.int64), ("key", np.uint64)))
        order = np.argsort(doc, kind="stable")
        runs = list(_by_bucket(doc[order]))
        yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in runs], pa.int64()), pa.array(_pieces(runs, key[order])[0], pa.binary())], names=["doc_id", "anchors"])


def _packed_windows(docs: DataFrame, length: int, settle: bool = True) -> DataFrame:
    """Packed target windows that survive level one, sorted by bucket."""
    spark, source, short = docs.sparkSession, _source(docs), (length + 1) // 2
    scratch, bits = Scratch(spark, "repeats"), bucket_bits(spark)
    anchors = source.mapInArrow(lambda it: _anchors(it, short, length, bits), "bucket long, keys binary")
    again = scratch.save(anchors.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_repeated, "a long"))
    few = again.count()
    if few <= FILTER_BYTES:  # eight bits a window
        repeated = spark.sparkContext.broadcast(bitmap(again, "a", max(16, (8 * few).bit_length())))
        windows = source.mapInArrow(lambda it: _windows(it, short, length, bits, repeated, settle), _PACKED)
    else:
        places = source.where("doc_id is not null").mapInArrow(lambda it: _anchor_places(it, short, length, bits), "bucket long, keys binary, doc binary")
        places = places.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(lambda it: _repeated_places(it, bits), "bucket long, doc binary, key binary")
        own = places.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_anchors_by_document, "doc_id long, anchors binary")
        windows = source.join(own, "doc_id").select("doc_id", "text", "anchors").mapInArrow(lambda it: _windows(it, short, length, bits, None, settle), _PACKED)
    return windows.repartition("bucket").sortWithinPartitions("bucket")


def remove_repeats(docs: DataFrame, length: int = 13) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_text): texts without the words that an earlier document has too.

    A word goes when it lies in a window of ``length`` consecutive words whose word sequence also starts in a
    document with a smaller doc_id.  Windows are judged on the input; kept words are joined by one space.

    Null and empty texts have no words and keep the empty text; texts shorter than a window stay whole, and very
    long texts are read whole.  Rows
    that repeat a doc_id are one document: they never remove each other's words, places that go in one of its
    texts go in all, and each row comes back.  A null doc_id neither removes nor loses words.  Columns other than doc_id and text are ignored.
    """
    joined = _source(docs).join(later_places(docs, length).withColumnRenamed("places", "starts"), "doc_id", "left")
    return joined.select("doc_id", "text", "starts").mapInArrow(lambda it: _cut(it, length), "doc_id long, n_words long, n_removed long, kept_text string")


def _shared(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """Windows that two or more documents have, packed by document; later tells whether an earlier one has it."""
    for _, rows in bucket_runs(batches):
        h, check, doc, pos, later = _settle(*_unpack(rows))
        new = np.concatenate(([True], (h[1:] != h[:-1]) | (check[1:] != check[:-1])))
        group = np.cumsum(new) - 1
        keep = (np.bincount(group, later) > 0)[group]
        if keep.any():
            yield _by_document(doc[keep], bits, pos=pos[keep].astype(np.int32), h=h[keep], c=check[keep], later=later[keep].astype(np.uint8))


_SHARED = "bucket long, doc binary, pos binary, h binary, c binary, later binary"


def _document_rows(rows: list[dict]) -> tuple[np.ndarray, ...]:
    """A bucket's entries by document and place, each once."""
    doc, pos, h, c, later = (np.frombuffer(b"".join(r[k] for r in rows), t) for k, t in (("doc", np.int64), ("pos", np.int32), ("h", np.uint64), ("c", np.uint32), ("later", np.uint8)))
    order = np.lexsort((c, h, pos, doc))
    doc, pos, h, c, later = doc[order], pos[order], h[order], c[order], later[order]
    new = np.concatenate(([True], (doc[1:] != doc[:-1]) | (pos[1:] != pos[:-1]) | (h[1:] != h[:-1]) | (c[1:] != c[:-1])))
    return doc[new], pos[new], h[new], c[new], later[new]


def _twice_as_long(batches: Iterator[pa.RecordBatch], width: int, bits: int) -> Iterator[pa.RecordBatch]:
    """Packed windows of twice the width both halves of which survived: their hashes come from the halves'."""
    for _, rows in bucket_runs(batches):
        doc, pos, h, c, _ = _document_rows(rows)
        # rows of one doc_id with different texts have several windows at a place: every pair of halves is a candidate
        place = np.rec.fromarrays([doc, pos.astype(np.int64)])
        wanted = np.rec.fromarrays([doc, pos.astype(np.int64) + width])
        lo, hi = np.searchsorted(place, wanted, "left"), np.searchsorted(place, wanted, "right")
        n = hi - lo
        a = np.repeat(np.arange(doc.size), n)
        b = np.repeat(lo, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        if a.size:
            long_ = mix(h[a] * _LEFT + h[b] * _RIGHT)
            check = (mix(c[a].astype(np.uint64) * _RIGHT + c[b].astype(np.uint64) * _LEFT + np.uint64(1)) >> np.uint64(32)).astype(np.uint32)
            order = np.argsort(long_, kind="stable")
            runs = list(_by_bucket(long_[order] >> np.uint64(64 - bits)))
            yield _packed([x for x, _ in runs], [None] * len(runs), *_pieces(runs, long_[order], check[order], doc[a][order], pos[a][order]))


def _later_positions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for _, rows in bucket_runs(batches):
        doc, pos, _, _, later = _document_rows(rows)
        yield pa.RecordBatch.from_arrays([pa.array(doc[later > 0]), pa.array(pos[later > 0])], names=["doc_id", "pos"])


def doubled_repeats(docs: DataFrame, length: int = 13, max_levels: int = 24) -> DataFrame:
    """(doc_id, pos, length): for each word position whose window is in an earlier document, its longest repeated level.

    Levels are ``length``, 2 * ``length``, 4 * ``length`` ...; a level's candidates are the windows both halves
    of which two documents have, and come from the level before, not from the texts.  Stops at the first level
    without survivors.  Edge cases are those of ``remove_repeats``.
    """
    spark = docs.sparkSession
    scratch, bits = Scratch(spark, "doubling"), bucket_bits(spark)
    in_order = lambda df: df.repartition("bucket").sortWithinPartitions("bucket")
    windows, found, width = _packed_windows(docs, length, settle=False), None, length
    for _ in range(max_levels):
        level = scratch.save(windows.mapInArrow(lambda it: _shared(it, bits), _SHARED))
        places = in_order(level).mapInArrow(_later_positions, "doc_id long, pos int").distinct().withColumn("length", F.lit(width))
        found = places if found is None else found.union(places)
        if level.isEmpty():
            break
        windows = in_order(in_order(level).mapInArrow(lambda it, w=width: _twice_as_long(it, w, bits), _PACKED))
        width *= 2
    return found.groupBy("doc_id", "pos").agg(F.max("length").alias("length"))


OP4_SQL = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
v AS (
  SELECT doc_id, i, array_to_string(w[i:i + 12], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM w)),
f AS (SELECT g, min(doc_id) AS first_doc FROM v GROUP BY g),
c AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS i FROM v JOIN f USING (g) WHERE doc_id > first_doc),
k AS (
  SELECT t.doc_id, string_agg(t.word, ' ' ORDER BY t.i) AS kept
  FROM (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM w) t ANTI JOIN c ON t.doc_id = c.doc_id AND t.i = c.i
  GROUP BY t.doc_id)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, coalesce(n.n, 0) AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256
FROM w LEFT JOIN (SELECT doc_id, count(*) AS n FROM c GROUP BY doc_id) n USING (doc_id) LEFT JOIN k USING (doc_id)
"""
