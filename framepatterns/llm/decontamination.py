"""Benchmark decontamination by BM25 with block-max WAND.

The test items form a small inverted index; the training passages are the queries.  An item is retrieved when its
score reaches a share of its score against itself, so every item has its own threshold; items are ordered by it and
cut into short blocks of neighbours.  A term's posting list names the items that have it, with their weights, and
for each block the largest weight.  For all passages of a batch at once the block maxima are added up; a block whose
sum stays below its smallest threshold is dead.  In the live blocks of a passage, cursors go over the posting
lists: in the order of their items their maxima are added until the sum reaches the threshold, which gives the
pivot; cursors before it skip to it, and only an item on which they meet is scored.

What is retrieved is verified by the words of the item that lie in a run of RUN words of the passage, for the item
as a whole and for its question and its answer.  A replaced word costs itself and not its neighbours' runs.

Passages are windows of twice the longest item's length that step by that length, so an item that occurs in a
text lies whole in one passage, and texts are read whole.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from framepatterns.llm.scratch import Scratch
from framepatterns.llm.toxicity import FOLD
from framepatterns.llm.words import grams, hashed_rows

K1, B = 1.2, 0.75
BLOCK, RUN = 4, 3
#: Items of one index; a larger benchmark is searched index by index, one after the other, with statistics of all items.
INDEX_ITEMS = 2048
#: Texts with items whose hashes may be replicated: 16 MB.
REPLICATED = 1_000_000


@dataclass
class Index:
    """An inverted index with block maxima, small enough to broadcast: at most INDEX_ITEMS items.

    Lists are stored one after the other: those of term t are [edge[t], edge[t + 1]).
    """

    ids: np.ndarray
    terms: np.ndarray
    post_edge: np.ndarray
    post_item: np.ndarray
    post_weight: np.ndarray
    block_edge: np.ndarray
    block: np.ndarray
    block_max: np.ndarray
    need: np.ndarray
    words: list  # per item: its words, and how many of them are the question
    longest: int


@dataclass
class Statistics:
    """Sorted terms, the number of items that have each, the items with words, their mean length and the longest's."""

    terms: np.ndarray
    seen: np.ndarray
    items: int
    mean: float
    longest: int


def _words(text: str) -> np.ndarray:
    return np.concatenate([h for _, _, h, _ in hashed_rows(pa.array([text], pa.string()), fold=FOLD)] or [np.zeros(0, np.uint64)])


def split_answer(text: str) -> int:
    """Words of the question: all before the last line, or before the last sentence of a single line."""
    body = text.strip()
    cut = body.rfind("\n")
    if cut < 0:
        cut = max(body[:-1].rfind(mark) for mark in ".?!")
    return _words(body[: cut + 1]).size if cut >= 0 else 0


def build_index(items: list[tuple[int, str]], share: float = 0.6, stats: Statistics | None = None) -> Index | None:
    """Index (id, text) pairs, weighted by ``stats`` or else by these items' own; items without words are left out."""
    words = [_words(t) for _, t in items]
    keep = [i for i, w in enumerate(words) if w.size]
    if not keep:
        return None
    items, words = [items[i] for i in keep], [words[i] for i in keep]
    terms, seen = np.unique(np.concatenate([np.unique(w) for w in words]), return_counts=True)
    total, mean = len(items), np.mean([w.size for w in words])
    if stats is not None:
        seen, total, mean = stats.seen[np.searchsorted(stats.terms, terms)], stats.items, stats.mean
    idf = np.log(1 + (total - seen + 0.5) / (seen + 0.5))
    own, need = [], []
    for w in words:
        t, tf = np.unique(np.searchsorted(terms, w), return_counts=True)
        own.append((t, idf[t] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * w.size / mean))))
        need.append(share * own[-1][1].sum())
    order = np.argsort(need, kind="stable")
    t = np.concatenate([own[j][0] for j in order])
    item = np.repeat(np.arange(len(items)), [own[j][0].size for j in order])
    weight = np.concatenate([own[j][1] for j in order])
    by = np.lexsort((item, t))
    t, item, weight = t[by], item[by], weight[by]
    new = np.flatnonzero(np.concatenate(([True], (t[1:] != t[:-1]) | (item[1:] // BLOCK != item[:-1] // BLOCK))))
    edges = lambda x: np.searchsorted(x, np.arange(terms.size + 1))
    ids = np.array([items[j][0] for j in order], np.int64)
    body = [(words[j], split_answer(items[j][1])) for j in order]
    return Index(ids, terms, edges(t), item, weight, edges(t[new]), item[new] // BLOCK, np.maximum.reduceat(weight, new), np.array(need)[order], body, max(w.size for w in words) if stats is None else stats.longest)


def _overlap(index: Index, j: int, passage: np.ndarray) -> tuple[float, float, float]:
    """Shares of the item's words, of its question's and of its answer's that lie in runs which the passage has."""
    own, question = index.words[j]
    run = min(RUN, own.size)
    have = np.isin(grams(own, run), grams(passage, run))
    edge = np.zeros(own.size + 1, int)
    edge[:-run] += have
    edge[run:] -= have
    covered = np.cumsum(edge)[:-1] > 0
    part = lambda x: float(x.mean()) if x.size else 1.0
    return part(covered), part(covered[:question]), part(covered[question:])


def wand(index: Index, terms: np.ndarray, first: int, end: int) -> list[tuple[int, float]]:
    """(item, score) of the items from ``first`` up to ``end`` that reach their threshold for a passage's terms."""
    cursors = []  # item, place in the list, end of the list's part, largest weight
    for t in terms:
        lo, hi = int(index.post_edge[t]), int(index.post_edge[t + 1])
        at = lo + int(np.searchsorted(index.post_item[lo:hi], first))
        stop = lo + int(np.searchsorted(index.post_item[lo:hi], end))
        if at < stop:
            cursors.append([int(index.post_item[at]), at, stop, float(index.post_weight[at:stop].max())])
    out = []
    while cursors:
        cursors.sort(key=lambda c: c[0])
        # thresholds grow along the items, so that of the first item holds for all later ones
        bound, pivot, least = 0.0, None, float(index.need[cursors[0][0]]) - 1e-9
        for c in cursors:
            bound += c[3]
            if bound >= least:
                pivot = c[0]
                break
        if pivot is None:
            break
        if cursors[0][0] == pivot:
            score = sum(float(index.post_weight[c[1]]) for c in cursors if c[0] == pivot)
            if score >= index.need[pivot] - 1e-9:
                out.append((pivot, round(score, 9)))  # equal passages tie, however their sums were rounded
            skip = pivot + 1
        else:
            skip = pivot
        for c in cursors:
            if c[0] < skip:
                c[1] += int(np.searchsorted(index.post_item[c[1] : c[2]], skip))
                c[0] = int(index.post_item[c[1]]) if c[1] < c[2] else -1
        cursors = [c for c in cursors if c[0] >= 0]
    return out


def _live_blocks(index: Index, group: np.ndarray, t: np.ndarray, groups: int) -> np.ndarray:
    """(groups, blocks): whether the block maxima of a passage's terms reach the smallest threshold of the block."""
    blocks = -(-index.need.size // BLOCK)
    n = index.block_edge[t + 1] - index.block_edge[t]
    entry = np.repeat(index.block_edge[t] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
    sums = np.bincount(np.repeat(group, n) * blocks + index.block[entry], index.block_max[entry], groups * blocks)
    return sums.reshape(groups, blocks) >= index.need[::BLOCK] - 1e-9


def search(index: Index, h: np.ndarray, w: np.ndarray, least: float, each: float) -> list[tuple[int, int, float, float, float, float]]:
    """(row, item position, score, overlap, question overlap, answer overlap) of verified hits of a batch of texts."""
    at = np.minimum(np.searchsorted(index.terms, h), index.terms.size - 1)
    term = np.where(index.terms[at] == h, at, -1)
    step, size = index.longest, index.terms.size
    n = np.diff(w)
    halves = np.maximum(-(-n // step), 1)
    first = np.concatenate(([0], np.cumsum(halves)))
    known = np.flatnonzero(term >= 0)
    if not known.size:
        return []
    row = np.searchsorted(w, known, side="right") - 1
    half = first[row] + (known - w[row]) // step
    # a passage is a half and the next one of the same text; it is named by its first half
    opens = (half < first[row + 1] - 1) | (halves[row] == 1)
    closes = half > first[row]
    keys = np.unique(np.concatenate([half[opens] * size + term[known[opens]], (half[closes] - 1) * size + term[known[closes]]]))
    passage, t = keys // size, keys % size
    new = np.flatnonzero(np.concatenate(([True], passage[1:] != passage[:-1])))
    edge = np.append(new, keys.size)
    best: dict[tuple[int, int], tuple] = {}
    for part in range(0, new.size, 128):  # bounded: passages x blocks
        some = slice(edge[part], edge[min(part + 128, new.size)])
        groups = min(128, new.size - part)
        live = _live_blocks(index, np.repeat(np.arange(groups), np.diff(edge[part : part + groups + 1])), t[some], groups)
        for g, block in zip(*np.nonzero(live), strict=True):
            p = int(passage[new[part + g]])
            r = int(np.searchsorted(first, p, side="right")) - 1
            start = w[r] + step * (p - first[r])
            for j, score in wand(index, t[edge[part + g] : edge[part + g + 1]], int(block) * BLOCK, min(int(block + 1) * BLOCK, index.need.size)):
                whole, question, answer = _overlap(index, j, h[start : min(start + 2 * step, w[r + 1])])
                if whole >= least and question >= each and answer >= each:
                    hit = (r, j, score, whole, question, answer)
                    if (r, j) not in best or hit[2:] > best[r, j][2:]:
                        best[r, j] = hit
    return list(best.values())


def _item_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(t, n, length, longest) a block of items: in how many each term occurs; a row without a term counts items and words."""
    for batch in batches:
        for _, _, h, w in hashed_rows(batch.column("text"), fold=FOLD):
            if not h.size:
                continue
            item = np.repeat(np.arange(w.size - 1), np.diff(w))
            order = np.lexsort((item, h))
            x, i = h[order], item[order]
            once = np.concatenate(([True], (x[1:] != x[:-1]) | (i[1:] != i[:-1])))
            t, n = np.unique(x[once], return_counts=True)
            terms = pa.array([*t.view(np.int64).tolist(), None], pa.int64())
            yield pa.RecordBatch.from_arrays([terms, pa.array([*n.tolist(), int((np.diff(w) > 0).sum())], pa.int64()), pa.array([*[0] * t.size, int(h.size)], pa.int64()), pa.array([*[0] * t.size, int(np.diff(w).max())], pa.int64())], names=["t", "n", "length", "longest"])


def _item_rows(benchmark: DataFrame) -> DataFrame:
    return benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("item_id is not null and text is not null").distinct()


def item_statistics(rows: DataFrame) -> DataFrame:
    """(t, n, length, longest): the items that have each term; the row without a term counts items with words, their words and the longest's."""
    found = rows.select("text").mapInArrow(_item_terms, "t long, n long, length long, longest long")
    return found.groupBy("t").agg(F.sum("n").alias("n"), F.sum("length").alias("length"), F.max("longest").alias("longest"))


def _indexes(benchmark: DataFrame, share: float, scratch: Scratch) -> Iterator[Index]:
    """Indexes over all items, one after the other; each holds INDEX_ITEMS items at most, and so do the rows that come to the driver."""
    rows = scratch.save(_item_rows(benchmark))
    total = rows.count()
    if not total:
        return
    table = scratch.save(item_statistics(rows))
    count = table.where("t is null").first()
    items = int(count.n) if count else 0
    parts = -(-total // (INDEX_ITEMS // 2)) if total > INDEX_ITEMS else 1
    for k in range(parts):  # by hash, so that no part outgrows the bound
        own = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k)
        seen = table.where("t is not null") if parts == 1 else table.join(item_statistics(own).where("t is not null").select("t"), "t")
        found = seen.select("t", "n").toArrow()
        terms = found.column("t").to_numpy().view(np.uint64)
        order = np.argsort(terms)
        stats = Statistics(terms[order], found.column("n").to_numpy()[order], items, float(count.length) / max(items, 1) if count else 0.0, int(count.longest) if count else 0)
        piece = sorted(tuple(r) for r in own.collect())
        for a in range(0, len(piece), INDEX_ITEMS):
            if (index := build_index(piece[a : a + INDEX_ITEMS], share, stats)) is not None:
                yield index


_HITS = ["item_id", "score", "overlap", "question_overlap", "answer_overlap"]


def _search_texts(thin: DataFrame, index, least: float, each: float) -> DataFrame:
    """Hits of one index, which is broadcast, with all columns of ``thin`` but the text."""
    keep = [f for f in thin.schema.fields if f.name != "text"]
    schema = T.StructType([*keep, T.StructField("item_id", T.LongType()), *[T.StructField(c, T.DoubleType()) for c in _HITS[1:]]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, hits = [], []
            for row, _, h, w in hashed_rows(batch.column("text"), fold=FOLD):
                for hit in search(index.value, h, w, least, each):
                    rows.append(row + hit[0])
                    hits.append((int(index.value.ids[hit[1]]), *hit[2:]))
            if rows:
                names = [f.name for f in keep]
                yield pa.RecordBatch.from_arrays([*[batch.column(c).take(pa.array(rows)) for c in names], *[pa.array(c) for c in zip(*hits, strict=True)]], names=[*names, *_HITS])

    return thin.mapInArrow(run, schema)


def _all_hits(thin: DataFrame, benchmark: DataFrame, least: float, each: float, share: float) -> DataFrame:
    """Hits of all indexes.  One index is searched lazily; of several, only one is broadcast at a time and its hits are written."""
    spark = thin.sparkSession
    scratch, out, waiting = Scratch(spark, "items"), None, None
    for index in _indexes(benchmark, share, scratch):
        if waiting is not None:
            part = scratch.save(_search_texts(thin, waiting, least, each))
            waiting.destroy()
            out = part if out is None else out.union(part)
        waiting = spark.sparkContext.broadcast(index)
    if waiting is None:
        return thin.drop("text").where("false").select("*", F.lit(0).cast("long").alias("item_id"), *[F.lit(0.0).alias(c) for c in _HITS[1:]])
    last = _search_texts(thin, waiting, least, each)
    return last if out is None else out.union(last)


def contaminated(docs: DataFrame, benchmark: DataFrame, least: float = 0.8, each: float = 0.5, share: float = 0.6) -> DataFrame:
    """(doc_id, item_id, score, overlap, question_overlap, answer_overlap): texts that hold a benchmark item.

    One row for each document row and item whose best passage reaches ``share`` of the item's own BM25 score,
    covers ``least`` of its words in runs of RUN, and ``each`` of those of its question and of its answer.  Words
    are compared in lower case (A-Z) without ASCII punctuation.  An item of fewer words is one run.

    Null and empty texts and items match nothing; texts of any length are read whole; repeated items of one id
    count once if their text is equal; rows that repeat a doc_id come back each.  An empty table gives an empty
    result; other columns are ignored.
    """
    thin = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return _all_hits(thin, benchmark, least, each, share)


def decontaminate(docs: DataFrame, benchmark: DataFrame, least: float = 0.8, each: float = 0.5, share: float = 0.6) -> DataFrame:
    """The rows of ``docs``, with all columns, whose text holds no benchmark item (see ``contaminated``)."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "items")
    two = list(itertools.islice(_indexes(benchmark, share, scratch), 2))
    if len(two) < 2:
        index = spark.sparkContext.broadcast(two[0] if two else None)
        return docs.mapInArrow(lambda it: _without_items(it, index, least, each), docs.schema)
    text = F.col("text").cast("string")
    names = [F.xxhash64(text).alias("_v"), F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("_c")]  # texts by 96 bits
    gone = scratch.save(_all_hits(docs.select(*names, text.alias("text")), benchmark, least, each, share).select(F.col("_v").alias("_x"), F.col("_c").alias("_y")).distinct())
    few = gone.limit(REPLICATED + 1).count() <= REPLICATED
    rows = docs.select(F.struct(*docs.columns).alias("_row"), *names)
    return rows.join(F.broadcast(gone) if few else gone, (F.col("_v") == F.col("_x")) & (F.col("_c") == F.col("_y")), "left_anti").select("_row.*")


def _without_items(batches: Iterator[pa.RecordBatch], index, least: float, each: float) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        clean = np.ones(batch.num_rows, bool)
        for row, _, h, w in hashed_rows(batch.column("text"), fold=FOLD) if index.value is not None else ():
            for hit in search(index.value, h, w, least, each):
                clean[row + hit[0]] = False
        yield batch.filter(pa.array(clean))
