"""Toxicity by class-conditional Kneser-Ney language models.

Two word-pair models, one of toxic and one of ordinary texts, give every text a likelihood.  Both discount their
counts (in how many texts of the class a word or a pair occurs) and hand the freed mass to a shorter context: a
pair to the class's words, a word to continuation counts that both classes share.  The discount of a count is
D plus what the count would be if both classes were alike, with SPREAD standard deviations of room.  So an
expression that is rare, or as frequent in both classes, keeps no mass of its own; it gets the shared backoff in
both models, and both probabilities agree but for the freed mass.  Each model's probabilities sum to one.

The score is a logistic curve over one number: the difference of the two log-likelihoods divided by the text's
length.

The class counts come from a bounded sample of labelled rows, about ``rows_per_class`` a class, chosen by the
hash of doc_id; three quarters of it feed the counts and one quarter fits the two weights of the curve.  The
continuation counts, in how many different left contexts a word occurs in the whole corpus, cover every document;
they are kept a word, in a distributed table that grows with the vocabulary, and looked up for the words of the
models.  For any other word the shared backoff cancels in the difference.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from framepatterns.llm.packing import bucket_bits, bucket_runs
from framepatterns.llm.scratch import Scratch, bound_batches, map_batches
from framepatterns.llm.words import hashed_rows, mix

#: Pairs that a task holds before it sends them on, and words after which it drops the pairs that it has already.
HELD_PAIRS, MERGED_WORDS = 1 << 20, 1 << 18
#: Share of the sample's words from which a word's contexts are dealt by themselves and not by the word.
HOT = 1e-3
#: Low bits of a word's hash that the continuation counts do without.
CUT = 16
DISCOUNT, SPREAD = 1.0, 3.0
#: Unit of the difference a word, so that the weights of the curve are of moderate size.
UNIT = 0.01
_START = np.uint64(0x51_7C_C1_B7_27_22_0A_95)
#: Lower case, and ASCII punctuation as white space.
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
for _c in range(33, 127):
    if not chr(_c).isalnum():
        FOLD[_c] = 32


def _previous(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    prev = np.empty_like(h)
    prev[1:] = h[:-1]
    starts = w[:-1][w[:-1] < h.size]
    prev[starts] = _START
    return prev


def pair_key(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return mix(a * np.uint64(0x9E3779B97F4A7C15) + b)


def _long(x: np.ndarray) -> pa.Array:
    return pa.array(x.astype(np.uint64).view(np.int64))


def _text_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(h, w, t, o): in how many toxic and ordinary sample texts the word w occurs after h, or (h null) at all."""

    def counted(key: np.ndarray, text: np.ndarray, toxic: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        order = np.lexsort((text, key))
        k, d = key[order], text[order]
        new = np.concatenate(([True], k[1:] != k[:-1]))
        once = new | np.concatenate(([True], d[1:] != d[:-1]))
        at = np.flatnonzero(new)
        return order[at], np.add.reduceat((once & toxic[d]).astype(np.int64), at), np.add.reduceat((once & ~toxic[d]).astype(np.int64), at)

    for batch in batches:
        toxic = batch.column("toxic").to_numpy().astype(bool)
        for row, end, h, w in hashed_rows(batch.column("text"), fold=FOLD):
            if not h.size:
                continue
            text = np.repeat(np.arange(row, end), np.diff(w))
            prev = _previous(h, w)
            one, t1, o1 = counted(h, text, toxic)
            two, t2, o2 = counted(pair_key(prev, h), text, toxic)
            before = pa.array([None] * one.size, pa.int64()), _long(prev[two])
            yield pa.RecordBatch.from_arrays([pa.concat_arrays(before), _long(h[np.concatenate([one, two])]), pa.array(np.concatenate([t1, t2])), pa.array(np.concatenate([o1, o2]))], names=["h", "w", "t", "o"])


def _among(values: np.ndarray, few: np.ndarray) -> np.ndarray:
    """Which values are in the sorted array ``few``; np.isin sorts the values for this."""
    return few[np.minimum(np.searchsorted(few, values), few.size - 1)] == values if few.size else np.zeros(values.size, bool)


def _distinct(words: list[np.ndarray], pairs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The different pairs in order and the word of each; empties both lists, so that no array is held twice."""
    pair = np.concatenate(pairs)
    pairs.clear()
    order = np.argsort(pair, kind="stable")
    pair = pair[order]
    new = np.concatenate(([True], pair[1:] != pair[:-1]))
    pair, order = pair[new], order[new]
    word = np.concatenate(words)
    words.clear()
    return word[order], pair


def _contexts(batches: Iterator[pa.RecordBatch], bits: int, hot: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(bucket, words, counts, contexts): the different left contexts of the words of a bucket, packed.

    words (48 bits of a word's hash) and counts say whose contexts follow; a context is 40 bits of the pair's
    hash.  Words go to buckets by their hash, but the contexts of the words in ``hot`` by their own, so that those
    of a frequent word are not one task.
    """
    words, pairs, held = [], [], 0

    def pack(word: np.ndarray, pair: np.ndarray) -> pa.RecordBatch:
        bucket = mix(np.where(_among(word, hot), pair, word)) >> np.uint64(64 - bits)
        order = np.lexsort((word, bucket))
        bucket, word, pair = bucket[order], word[order], pair[order]
        del order
        word >>= np.uint64(CUT)
        pair >>= np.uint64(24)
        place = np.arange(word.size)
        new = np.concatenate(([True], (bucket[1:] != bucket[:-1]) | (word[1:] != word[:-1])))
        new |= (place - np.maximum.accumulate(np.where(new, place, 0))) % 255 == 0  # a count is one byte
        first = np.flatnonzero(new)
        del place, new
        counts = np.diff(np.append(first, word.size)).astype(np.uint8)
        of = bucket[first]
        run = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1], [True])))
        edges, ends = np.append(first, word.size), list(zip(run[:-1], run[1:], strict=True))
        del bucket
        own = np.ascontiguousarray(word[first].astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6])
        context = np.ascontiguousarray(pair.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5])
        del word, pair
        columns = [pa.array([x[a:b].tobytes() for a, b in ends], pa.binary()) for x in (own, counts)]
        columns.append(pa.array([context[edges[a] : edges[b]].tobytes() for a, b in ends], pa.binary()))
        return pa.RecordBatch.from_arrays([pa.array(of[run[:-1]].astype(np.int64)), *columns], names=["bucket", "words", "counts", "contexts"])

    for batch in batches:
        for _, _, h, w in hashed_rows(batch.column("text"), fold=FOLD):
            if not h.size:
                continue
            words.append(h)
            pairs.append(pair_key(_previous(h, w), h))
            held += h.size
            if held > MERGED_WORDS:
                words[:], pairs[:] = ([x] for x in _distinct(words, pairs))
                held = 0
                if pairs[0].size > HELD_PAIRS:
                    yield pack(words.pop(), pairs.pop())
    if words:
        yield pack(*_distinct(words, pairs))


def _wide(raw: bytes, width: int) -> np.ndarray:
    """Numbers of ``width`` bytes each."""
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(-1, width)
    return out.view("<u8").ravel()


def _continuations(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(k, n): the number of different contexts of each word of a bucket, from rows sorted by bucket."""
    for _, rows in bucket_runs(batches):
        joined = lambda c: b"".join(r[c] for r in rows)  # noqa: E731, B023
        word = np.repeat(_wide(joined("words"), 6), np.frombuffer(joined("counts"), np.uint8))
        context = _wide(joined("contexts"), 5)
        order = np.lexsort((context, word))
        word, context = word[order], context[order]
        k, n = np.unique(word[np.concatenate(([True], (word[1:] != word[:-1]) | (context[1:] != context[:-1])))], return_counts=True)
        yield pa.RecordBatch.from_arrays([_long(k), pa.array(n)], names=["k", "n"])


def continuation_counts(docs: DataFrame, hot: list[int] | None = None) -> DataFrame:
    """(k, n): in how many different left contexts each word occurs in all documents; k is its hash without the low CUT bits.

    ``hot`` lists hashes of frequent words, whose contexts are spread over all tasks.
    """
    bound_batches(docs.sparkSession)
    bits = bucket_bits(docs.sparkSession)
    many = np.sort(np.array(hot or [], np.int64).view(np.uint64))
    sent = map_batches(docs.select(F.col("text").cast("string").alias("text")), lambda it: _contexts(it, bits, many), "bucket long, words binary, counts binary, contexts binary")
    counted = map_batches(sent.repartition("bucket").sortWithinPartitions("bucket"), _continuations, "k long, n long")
    return counted.groupBy("k").agg(F.sum("n").alias("n"))


def _find(keys: np.ndarray, table: np.ndarray, wanted: np.ndarray, missing) -> np.ndarray:
    if not keys.size:
        return np.broadcast_to(np.asarray(missing, float), (wanted.size, table.shape[1])).copy()
    at = np.minimum(np.searchsorted(keys, wanted), keys.size - 1)
    return np.where((keys[at] == wanted)[:, None], table[at], missing)


@dataclass
class Model:
    """Sorted keys with columns (toxic, ordinary): what the discounts leave, as shares, and the freed mass.

    A word's probability is its share plus the class's freed mass times its continuation share; a pair's is its
    share of the context plus the context's freed mass times the word's probability.
    """

    words: np.ndarray
    word_shares: np.ndarray
    continuation: np.ndarray  # share of all continuations, for each of ``words``
    freed: np.ndarray  # of the class's words
    pairs: np.ndarray
    pair_shares: np.ndarray
    contexts: np.ndarray
    context_freed: np.ndarray
    weights: np.ndarray

    def probabilities(self, prev: np.ndarray, h: np.ndarray, continuation: np.ndarray) -> np.ndarray:
        """P(word | word before) in both classes, given the words' continuation shares."""
        one = _find(self.words, self.word_shares, h, 0.0) + self.freed * continuation[:, None]
        return _find(self.pairs, self.pair_shares, pair_key(prev, h), 0.0) + _find(self.contexts, self.context_freed, prev, 1.0) * one

    def differences(self, h: np.ndarray, w: np.ndarray) -> np.ndarray:
        """log P(word | toxic) - log P(word | ordinary) of every word of a batch.

        Words outside the table have only the shared backoff, which cancels, so their share may be any number.
        """
        share = _find(self.words, self.continuation[:, None], h, 1.0)[:, 0]
        p = np.log(np.maximum(self.probabilities(_previous(h, w), h, share), 1e-300))
        return p[:, 0] - p[:, 1]

    def features(self, h: np.ndarray, w: np.ndarray) -> np.ndarray:
        """Per text: one, and the difference of the log-likelihoods divided by the length (0 without words)."""
        n = np.diff(w)
        c = np.concatenate(([0.0], np.cumsum(self.differences(h, w)))) if h.size else np.zeros(1)
        return np.stack([np.ones(n.size), (c[w[1:]] - c[w[:-1]]) / np.maximum(n, 1) / UNIT], axis=1)

    def scores(self, col: pa.Array) -> np.ndarray:
        out = np.zeros(len(col))
        for row, end, h, w in hashed_rows(col, fold=FOLD):
            out[row:end] = 1 / (1 + np.exp(-np.clip(self.features(h, w) @ self.weights, -30, 30)))
        return out


def fit_weights(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, rounds: int = 50) -> np.ndarray:
    """Logistic regression by Newton steps; without both classes the score is the share of toxic rows."""
    w = np.zeros(x.shape[1])
    if y.size == 0 or y.min() == y.max():
        w[0] = np.log((y.sum() + 0.5) / (y.size - y.sum() + 0.5)) if y.size else -2.0
        return w
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * w
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(x.shape[1]), g)
        w -= np.clip(step, -3, 3)
        if np.abs(step).max() < 1e-6:
            break
    return w


def train(docs: DataFrame, labels: DataFrame, scratch: Scratch, rows_per_class: int = 4000) -> Model:
    """Fit the models on labelled rows whose crc32(doc_id as text) mod 5 is not 0."""
    split = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max((F.col("toxic") != 0).cast("int")).alias("toxic"))
    known = known.where(split != 0)
    counts = dict(known.groupBy("toxic").count().collect())
    draw = F.pmod(F.xxhash64(F.lit("sample"), F.col("doc_id")), F.lit(1 << 30))
    limit = F.when(F.col("toxic") == 1, F.lit((1 << 30) * min(1.0, rows_per_class / max(counts.get(1, 1), 1)))).otherwise(F.lit((1 << 30) * min(1.0, rows_per_class / max(counts.get(0, 1), 1))))
    chosen = F.broadcast(known.where(draw < limit))  # about 2 * rows_per_class rows, however many labels there are
    sample = scratch.save(docs.select("doc_id", F.col("text").cast("string").alias("text")).join(chosen, "doc_id").withColumn("part", F.pmod(F.xxhash64(F.lit("part"), F.col("doc_id")), F.lit(4))))
    counts_of = scratch.save(map_batches(sample.where("part > 0").select("text", "toxic"), _text_counts, "h long, w long, t long, o long").groupBy("h", "w").agg(F.sum("t").alias("t"), F.sum("o").alias("o")))

    num = lambda v: float(v or 0)
    one = counts_of.where("h is null")
    sums = [max(num(x), 1.0) for x in one.agg(F.sum("t"), F.sum("o")).first()]

    def kept(count: str, all_: Column, pooled: Column, of_both: Column) -> Column:
        """What the discount leaves of a class's count; ``all_`` is the class's total, ``of_both`` that of both classes."""
        alike = all_ * pooled / of_both
        return F.greatest(F.col(count) - DISCOUNT - alike - SPREAD * F.sqrt(alike), F.lit(0.0))

    total = [F.lit(x) for x in sums]
    both, all_both = F.col("t") + F.col("o"), F.lit(sum(sums))
    words = one.select("w", *[kept(c, n, both, all_both).alias(f"k{c}") for c, n in zip("to", total, strict=True)]).where("kt + ko > 0")
    two = counts_of.where("h is not null")
    context = two.groupBy(F.col("h").alias("_h")).agg(F.sum("t").alias("ct"), F.sum("o").alias("co"))
    pairs = two.join(context, F.col("h") == F.col("_h")).select("h", "w", "ct", "co", *[kept(c, F.col(f"c{c}"), both, F.col("ct") + F.col("co")).alias(f"k{c}") for c in "to"]).where("kt + ko > 0")
    # what is left of counts over a bounded sample is bounded, and fits the driver
    pairs, words = pairs.toArrow(), scratch.save(words)
    hot = [r[0] for r in one.where((F.col("t") + F.col("o")) > HOT * sum(sums)).select("w").collect()]  # 1 / HOT words at most
    continuations = scratch.save(continuation_counts(docs, hot))
    all_continuations = max(num(continuations.agg(F.sum("n")).first()[0]), 1.0)
    # from an Arrow table; rows of a Python list go through a second pool of workers, which stay beside the others
    known = scratch.spark.createDataFrame(pa.table({"w": pairs.column("w").unique()})).join(words, "w", "full")
    table = known.join(continuations, F.shiftrightunsigned("w", CUT) == F.col("k"), "left").select("w", "kt", "ko", "n").na.fill(0).toArrow()

    as_key = lambda t, c: t.column(c).to_numpy().view(np.uint64)
    both_of = lambda t, a, b: np.stack([t.column(a).to_numpy().astype(np.float64), t.column(b).to_numpy().astype(np.float64)], 1)
    order = np.argsort(as_key(table, "w"))
    word_shares = both_of(table, "kt", "ko")[order] / np.array(sums)
    pair_shares = both_of(pairs, "kt", "ko") / np.maximum(both_of(pairs, "ct", "co"), 1)
    contexts, at = np.unique(as_key(pairs, "h"), return_inverse=True)
    used = np.zeros((contexts.size, 2))
    np.add.at(used, at, pair_shares)
    keys = pair_key(as_key(pairs, "h"), as_key(pairs, "w"))
    by_key = np.argsort(keys)
    model = Model(as_key(table, "w")[order], word_shares, table.column("n").to_numpy()[order] / all_continuations, 1 - word_shares.sum(0), keys[by_key], pair_shares[by_key], contexts, 1 - used, np.zeros(2))
    ship = scratch.spark.sparkContext.broadcast(model)

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.concatenate([ship.value.features(h, w) for _, _, h, w in hashed_rows(batch.column("text"), fold=FOLD)]) if batch.num_rows else np.zeros((0, 2))
            yield pa.RecordBatch.from_arrays([batch.column("toxic"), pa.array(x[:, 1])], names=["toxic", "a"])

    fit = map_batches(sample.where("part = 0").select("text", "toxic"), measure, "toxic int, a double").toArrow()
    x = np.stack([np.ones(fit.num_rows), fit.column("a").to_numpy()], 1)
    y = fit.column("toxic").to_numpy().astype(np.float64)
    share = counts.get(1, 0) / max(sum(counts.values()), 1)
    order = np.lexsort((x[:, 1], y))  # summation order does not depend on the partitions
    model.weights = fit_weights(x[order], y[order])
    if 0 < y.sum() < y.size:  # the sample evens out the classes; the score is for the population
        model.weights[0] += np.log(share / (1 - share)) - np.log(y.mean() / (1 - y.mean()))
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """All rows and columns of ``docs`` with toxicity, a double between 0 and 1 (texts without words: the prior)."""
    bound_batches(docs.sparkSession)
    ship = docs.sparkSession.sparkContext.broadcast(model)
    base = docs.drop("toxicity")
    schema = T.StructType([*base.schema.fields, T.StructField("toxicity", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ship.value.scores(batch.column("text")))], names=[*batch.schema.names, "toxicity"])

    return map_batches(base, run, schema)


def toxicity(docs: DataFrame, labels: DataFrame, rows_per_class: int = 4000) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of ``docs``.

    Only labels of rows with crc32(doc_id as text) mod 5 <> 0 are learnt from, those with a null label are
    left out, and of several labels of a document the toxic one counts.  Null and empty texts have the score
    of a text without words; without labels every text has the same score.  Labels, language, source and id
    are no inputs of a score.  Texts are read whole, a long one like others.  Rows that repeat a doc_id come back each; other columns are ignored.
    """
    scratch = Scratch(docs.sparkSession, "toxicity")
    model = train(docs, labels, scratch, rows_per_class)
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    scored = score(docs.select("doc_id", F.col("text").cast("string").alias("text")), model)
    return scored.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"))
