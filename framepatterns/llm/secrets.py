"""Secret scans with DataFrame functions only.

Known shapes are found by pattern.  Other long tokens go through a battery of randomness tests over the
alphabet of their inferred encoding: chi-squared uniformity of the letters, runs above and below the middle
letter, serial correlation of neighbours, and how much likelier the letters are in ordinary strings than evenly
drawn.  Their deviations add up to one distance from randomness.

What is reported has to be bounded, so the hypothesis that is rejected is that a token is ordinary.  Ordinary tokens
are drawn for each encoding and length from fixed letter frequencies, in stretches of one case or of digits, and
go through the same battery.  How far a token's distance lies below theirs gives its p-value as an ordinary string,
with no assumption on the tests' tails at short lengths.  Over all tokens of the corpus a step-up procedure, weighted
by length because long tokens carry more evidence, rejects at a false-discovery rate of FDR.  What it rejects is
reported as a secret.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from framepatterns.llm.scratch import Scratch

ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"  # a run that is too short holds no longer one
HEX = r"[0-9a-f]{16,}"
TOKEN = r"[A-Za-z0-9+/_-]{20,}={0,2}"  # '=' only as padding: what follows NAME= is a token of its own
FDR, BINS_PER_E, MAX_BIN = 0.05, 20, 700

#: Encodings in the order in which they are tried: pattern and alphabet.
ENCODINGS = (
    (r"^[0-9a-f]+$", "0123456789abcdef"),
    (r"^[0-9A-F]+$", "0123456789ABCDEF"),
    (r"^[A-Z2-7]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    (r"^[0-9a-z]+$", "0123456789abcdefghijklmnopqrstuvwxyz"),
    (r"^[0-9A-Z]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    (r"^[0-9A-Za-z]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"),
    (r"^[0-9A-Za-z_-]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_"),
    (r"^[0-9A-Za-z+/_-]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"),
)


#: Letters of English text by how often they occur in a thousand.
LETTERS = {"e": 127, "t": 91, "a": 82, "o": 75, "i": 70, "n": 67, "s": 63, "h": 61, "r": 60, "d": 43, "l": 40, "c": 28, "u": 28, "m": 24, "w": 24, "f": 22, "g": 20, "y": 20, "p": 19, "b": 15, "v": 10, "k": 8, "j": 2, "x": 2, "q": 1, "z": 1}
#: Shares of stretches of lower case, upper case, digits and signs in ordinary tokens (of those that an encoding has),
#: and of digits where it has one case only or is hexadecimal; stretches end after one letter in STRETCH, signs stand alone.
LOWER, UPPER, DIGITS, SIGNS, ONE_CASE, HEXADECIMAL, STRETCH = 60, 12, 14, 14, 15, 50, 6
#: Lengths at which ordinary tokens are drawn, how many of each, and letters in an urn.
DRAWN, DRAWS, URN = (20, 24, 28, 32, 40, 48, 64, 96), 300, 300


def ordinary_urns(alphabet: str) -> list[tuple[int, str]]:
    """Kinds of stretches of an ordinary token over the alphabet: share in a hundred, and letters in proportion to their use."""
    kinds = ["".join(c for c in alphabet if f(c)) for f in (str.islower, str.isupper, str.isdigit, lambda c: not c.isalnum())]
    shares = [LOWER, UPPER, DIGITS, SIGNS]
    if not (kinds[0] and kinds[1]):
        digits = HEXADECIMAL if len(alphabet) == 16 else ONE_CASE
        shares = [(100 - digits) * bool(kinds[0]), (100 - digits) * bool(kinds[1]), digits, 0]
    whole = sum(LETTERS[c] for c in LETTERS if c in alphabet.lower())
    urn = lambda k: "".join(c * max(1, round(URN * LETTERS[c.lower()] / whole)) if c.isalpha() else c for c in k)
    return [(s, urn(k)) for s, k in zip(shares, kinds, strict=True) if s and k]


def letter_weights(alphabet: str) -> list[float]:
    """Logarithm of how much likelier each letter is in ordinary tokens than evenly drawn, at most 4 either way."""
    kinds = ordinary_urns(alphabet)
    whole = sum(s for s, _ in kinds)
    share = {c: s / whole * u.count(c) / len(u) for s, u in kinds for c in set(u)}
    return [max(-4.0, min(4.0, math.log(share[c] * len(alphabet)))) for c in alphabet]


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


CHUNK = 64


def running(values: Column, combine: Callable[[Column, Column], Column], zero: Column) -> Column:
    """Accumulated values of an array, each with all before it, in chunks: the work does not grow with the square."""

    def step(acc: Column, x: Column) -> Column:
        return F.concat(acc, F.array(combine(F.element_at(acc, -1), x)))

    def chunked(v: Column) -> Column:
        count = F.floor((F.size(v) - 1) / CHUNK)
        own = F.transform(F.sequence(F.lit(0).cast("long"), count), lambda c: F.slice(F.aggregate(F.slice(v, (c * CHUNK + 1).cast("int"), F.lit(CHUNK)), F.array(zero), step), F.lit(2), F.lit(CHUNK)))
        return let(own, joined)

    def joined(parts: Column) -> Column:
        before = F.aggregate(F.transform(parts, lambda p: F.element_at(p, -1)), F.array(zero), step)
        return F.flatten(F.zip_with(parts, F.slice(before, F.lit(1), F.size(parts)), lambda p, e: F.transform(p, lambda x: combine(e, x))))

    return let(values, lambda v: F.when(F.size(v) > 0, chunked(v)).otherwise(v))


def located(text: Column, pattern: str) -> Column:
    """Leftmost non-overlapping matches as an array of (start, end, s); positions are code points, end exclusive."""
    marked = F.regexp_replace(F.translate(text, "\u0001\u0002", "\u0003\u0003"), F.lit(pattern), F.lit("\u0001$0\u0002"))
    none = F.expr("cast(array() as array<struct<start:int,end:int,s:string>>)")

    def spans(pieces: Column) -> Column:
        ends = running(F.transform(pieces, F.length), lambda a, b: a + b, F.lit(0))
        all_ = F.zip_with(pieces, ends, lambda s, e: F.struct((e - F.length(s)).alias("start"), e.alias("end"), s.alias("s")))
        return F.filter(all_, lambda _, i: i % 2 == 1)  # what is between the marks

    return F.when(F.regexp(text, F.lit(pattern)), let(F.split(marked, "[\u0001\u0002]", -1), spans)).otherwise(none)


def without_overlap(tokens: Column, base: Column) -> Column:
    """The tokens (start, end, ...) that touch no span of ``base`` (start, end, ...), by one walk over both in order."""
    place = lambda kind: lambda t, i: F.struct(t["start"].alias("start"), t["end"].alias("end"), F.lit(kind).alias("base"), i.alias("i"))
    far = F.lit((1 << 31) - 1)

    def walk(both: Column) -> Column:
        ends = running(F.transform(both, lambda x: F.when(x["base"], x["end"]).otherwise(F.lit(0))), F.greatest, F.lit(0))
        starts = F.reverse(running(F.transform(F.reverse(both), lambda x: F.when(x["base"], x["start"]).otherwise(far)), F.least, far))
        near = F.zip_with(ends, starts, lambda e, s: F.struct(e.alias("e"), s.alias("s")))
        free = F.zip_with(both, near, lambda x, y: F.when(~x["base"] & (y["e"] <= x["start"]) & (y["s"] >= x["end"]), x["i"]))
        return F.transform(F.filter(free, lambda i: i.isNotNull()), lambda i: F.element_at(tokens, i + 1))

    in_order = F.array_sort(F.concat(F.transform(tokens, place(False)), F.transform(base, place(True))))
    return F.when((F.size(tokens) == 0) | (F.size(base) == 0), tokens).otherwise(let(in_order, walk))


def two_sided(z: Column) -> Column:
    """p-value of a standard normal deviation (rational approximation of the error function)."""

    def tail(v: Column) -> Column:
        x, t = v["x"], v["t"]
        poly = t * (0.254829592 + t * (-0.284496736 + t * (1.421413741 + t * (-1.453152027 + t * 1.061405429))))
        return F.greatest(F.least(poly * F.exp(-x * x), F.lit(1.0)), F.lit(1e-9))

    return let(F.abs(z) / math.sqrt(2), lambda x: let(F.struct(x.alias("x"), (1 / (1 + 0.3275911 * x)).alias("t")), tail))


def encoding(token: Column) -> Column:
    """The place in ENCODINGS of the first encoding that fits the token without its padding, else null."""
    bare = F.regexp_replace(token, "=+$", "")
    return F.coalesce(*[F.when(F.regexp(bare, F.lit(p)), F.lit(k)) for k, (p, _) in enumerate(ENCODINGS)])


def battery(token: Column) -> Column:
    """How far the token is from uniformly random in its encoding, in standard deviations; null for ordinary words.

    The sum of the excess of chi-squared, the sizes of the deviations of runs and serial correlation, and the
    letters' log-likelihood ratio of ordinary to even letters over the root of their number.

    A token of one letter case without digits is a word, not an encoding.
    """
    bare = F.regexp_replace(token, "=+$", "")
    classes = sum((F.regexp(bare, F.lit(c)).cast("int") for c in ("[a-z]", "[A-Z]", "[0-9]")), F.lit(0))

    def tests(v: Column) -> Column:
        x, k = v["x"], v["k"].cast("double")
        n = F.size(x).cast("double")
        count = lambda test: F.size(F.filter(x, test)).cast("double")
        pairs = F.zip_with(F.slice(x, F.lit(1), F.size(x) - 1), F.slice(x, F.lit(2), F.size(x) - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b")))

        def chi(squares: Column) -> Column:
            df = k - 1
            return (k / n * squares - n - df) / F.sqrt(2 * df * (n - 1) / n)

        def runs(c: Column) -> Column:
            both = 2 * c["high"] * (n - c["high"])
            spread = both * (both - n) / (n * n * (n - 1))
            return F.when(spread > 0, (c["changes"] - both / n) / F.sqrt(spread)).otherwise(6.0)

        def serial(mean: Column) -> Column:
            around = F.aggregate(x, F.lit(0.0), lambda acc, c: acc + (c - mean) * (c - mean))
            along = F.aggregate(pairs, F.lit(0.0), lambda acc, p: acc + (p["a"] - mean) * (p["b"] - mean))
            return let(F.struct(around.alias("around"), along.alias("along")), lambda s: F.when(s["around"] > 0, (s["along"] / s["around"] + 1 / n) * F.sqrt(n)).otherwise(6.0))

        squares = F.aggregate(F.array_distinct(x), F.lit(0.0), lambda acc, c: acc + F.pow(count(lambda y: y == c), F.lit(2.0)))
        changes = F.size(F.filter(pairs, lambda p: (2 * p["a"] >= k) != (2 * p["b"] >= k))).cast("double")
        counts = F.struct(count(lambda c: 2 * c >= k).alias("high"), changes.alias("changes"))
        total = F.aggregate(x, F.lit(0.0), lambda acc, c: acc + c)
        letters = F.aggregate(x, F.lit(0.0), lambda acc, c: acc + F.element_at(v["w"], c + 1)) / F.sqrt(n)
        return let(squares, chi) + F.abs(let(counts, runs)) + F.abs(let(total / n, serial)) + letters

    def coded(e: Column) -> Column:
        alphabet = F.element_at(F.array(*[F.lit(a) for _, a in ENCODINGS]), e + 1)
        codes = F.filter(F.transform(F.split(bare, ""), lambda c: F.call_function("instr", alphabet, c) - 1), lambda c: c >= 0)
        weights = F.element_at(F.array(*[F.array(*map(F.lit, letter_weights(a))) for _, a in ENCODINGS]), e + 1)
        return F.struct(codes.alias("x"), F.length(alphabet).alias("k"), weights.alias("w"))

    return F.when((classes >= 2) & (F.length(bare) >= 20), let(let(encoding(token), lambda e: F.when(e.isNotNull(), coded(e))), lambda v: F.when(F.size(v["x"]) >= 16, tests(v))))


def ordinary_tokens(spark: SparkSession) -> DataFrame:
    """(length, token): DRAWS ordinary tokens for each encoding and length, the same in every run."""
    kinds = [ordinary_urns(a) for _, a in ENCODINGS]
    urns = F.array(*[F.array(*[F.lit(u) for _, u in k]) for k in kinds])
    picks = F.array(*[F.array(*[F.lit(i) for i, (s, _) in enumerate(k) for _ in range(s)]) for k in kinds])
    pick = lambda values, e: F.element_at(values, (e + 1).cast("int"))
    rows = spark.range(len(ENCODINGS) * len(DRAWN) * DRAWS).withColumn("e", F.col("id") % len(ENCODINGS))
    rows = rows.select("id", pick(urns, F.col("e")).alias("urn"), pick(picks, F.col("e")).alias("picks"), pick(F.array(*map(F.lit, DRAWN)), F.floor(F.col("id") / len(ENCODINGS)) % len(DRAWN)).alias("length"))
    draw = lambda what, j, n: F.pmod(F.xxhash64(F.lit(what), "id", j), n).cast("int")

    def letter(acc: Column, j: Column) -> Column:
        fresh = (j == 1) | (acc["kind"] == 3) | (draw("end", j, F.lit(STRETCH)) == 0)  # kind 3: signs, which stand alone
        kind = F.when(fresh, F.element_at(F.col("picks"), draw("kind", j, F.size("picks")) + 1)).otherwise(acc["kind"])
        return let(F.struct(acc["s"].alias("s"), kind.alias("kind"), F.element_at(F.col("urn"), kind + 1).alias("u")), lambda x: F.struct(F.concat(x["s"], F.substring(x["u"], draw("letter", j, F.length(x["u"])) + 1, F.lit(1))).alias("s"), x["kind"].alias("kind")))

    token = F.aggregate(F.sequence(F.lit(1), F.col("length")), F.struct(F.lit("").alias("s"), F.lit(0).alias("kind")), letter)["s"]
    return rows.select("length", token.alias("token"))


def calibration(spark: SparkSession) -> list[tuple[int, int, float, float]]:
    """(encoding, length, mean, spread) of the battery's distance for ordinary tokens: one row for each pair."""
    tried = ordinary_tokens(spark).select("length", encoding(F.col("token")).alias("enc"), battery(F.col("token")).alias("x")).where("x is not null")
    found = tried.groupBy("enc", "length").agg(F.avg("x").alias("mean"), F.stddev_pop("x").alias("spread"), F.count("*").alias("c")).where(F.col("c") >= DRAWS // 10)
    return sorted((r.enc, r.length, r["mean"], max(r.spread, 0.5)) for r in found.collect())


def as_ordinary(value: Column, enc: Column, length: Column, table: list[tuple[int, int, float, float]]) -> Column:
    """p-value of the hypothesis that a token is ordinary: how far its distance lies below theirs, for its encoding and length.

    The length drawn next below the token's counts; ordinary tokens that are longer lie further away.  Where
    nothing was drawn the value is 1.
    """
    known = {(k, n): (mean, spread) for k, n, mean, spread in table}
    row = [known.get((k, n)) for k in range(len(ENCODINGS)) for n in DRAWN]
    means, spreads = (F.array(*[F.lit(r[i]) if r else F.lit(None).cast("double") for r in row]) for i in (0, 1))
    below = F.size(F.filter(F.array(*map(F.lit, DRAWN)), lambda n: n <= length))
    at = F.when((below > 0) & enc.isNotNull(), enc * len(DRAWN) + below)
    z = let(at, lambda i: (F.element_at(means, i) - value) / F.element_at(spreads, i))
    return let(z, lambda x: F.coalesce(F.when(x > 0, two_sided(x) / 2), F.lit(1.0)))


def _bin(q: Column) -> Column:
    return F.greatest(F.least(F.floor(-F.ln(F.greatest(q, F.lit(1e-15))) * BINS_PER_E), F.lit(MAX_BIN)), F.lit(0))


def step_up(tokens: DataFrame, fdr: float = FDR) -> int:
    """The lowest bin of p/weight whose tokens are rejected, from a histogram of bounded size; MAX_BIN + 1 for none.

    ``tokens`` has the columns p and n (length).  p/weight is rounded up to a bin's edge before the step-up rule
    is applied, so rounding never rejects more than exact values would.
    """
    total = tokens.agg(F.count("*"), F.avg("n")).first()
    if not total[0]:
        return MAX_BIN + 1
    bins = tokens.select(_bin(F.col("p") / (F.col("n") / F.lit(float(total[1])))).alias("b")).groupBy("b").count()
    counts, below, best = dict(bins.collect()), 0, MAX_BIN + 1
    for b in range(MAX_BIN, -1, -1):
        below += counts.get(b, 0)
        if counts.get(b, 0) and math.exp(-b / BINS_PER_E) <= below * fdr / total[0]:
            best = b
    return best


def _named(rank: int, kind: str) -> Column:
    return F.transform(kind, lambda m: F.struct(m["start"].alias("start"), F.lit(rank).alias("rank"), m["end"].alias("end"), F.lit(kind).alias("kind")))


def find_secrets(docs: DataFrame, fdr: float = FDR) -> DataFrame:
    """(doc_id, spans) with spans an array of (start, rank, end, kind) in order of start, then kind.

    Kinds are assign, access and hex by pattern, and random by the battery; a random span never overlaps one
    of the others.  Positions count code points, end exclusive.  Null and empty texts have no spans; very long texts
    are read whole, and the work follows their length and their number of spans; rows that repeat a doc_id come back each; an empty table gives an empty result.  Other columns are ignored.
    """
    scratch = Scratch(docs.sparkSession, "secrets")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    assign = F.filter(located(text, ASSIGN), lambda m: F.length(F.regexp_extract(m["s"], ASSIGN, 2)) >= 12)
    found = docs.select("doc_id", assign.alias("assign"), located(text, ACCESS).alias("access"), located(text, HEX).alias("hex"), located(text, TOKEN).alias("token"))
    found = scratch.save(found)
    table = calibration(docs.sparkSession)
    base = [_named(r, k).alias(k) for r, k in enumerate(("assign", "access", "hex"))]
    free = found.select("doc_id", *base, "token").withColumn("base", F.concat("assign", "access", "hex")).select("doc_id", "base", without_overlap(F.col("token"), F.col("base")).alias("token"))
    valued = F.filter(F.transform("token", lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), F.length(m["s"]).alias("n"), F.length(F.regexp_replace(m["s"], "=+$", "")).alias("bare"), encoding(m["s"]).alias("enc"), battery(m["s"]).alias("v"))), lambda m: m["v"].isNotNull())
    tried = F.transform(valued, lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), m["n"].alias("n"), as_ordinary(m["v"], m["enc"], m["bare"], table).alias("p")))
    tested = scratch.save(free.select("doc_id", "base", tried.alias("token")))
    each = tested.select(F.explode("token").alias("t")).select("t.n", "t.p")
    stats = each.agg(F.avg("n")).first()[0] or 1.0
    lowest = step_up(each, fdr)
    kept = F.filter("token", lambda t: _bin(t["p"] / (t["n"] / F.lit(float(stats)))) >= lowest)
    added = F.transform(kept, lambda t: F.struct(t["start"].alias("start"), F.lit(3).alias("rank"), t["end"].alias("end"), F.lit("random").alias("kind")))
    return tested.select("doc_id", F.array_sort(F.concat("base", added)).alias("spans"))


def secret_digest(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every document."""
    s = find_secrets(docs)
    written = lambda a: F.array_join(F.transform(a, lambda m: F.concat_ws(":", m["kind"], m["start"].cast("string"), m["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda m: m["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("spans", lambda m: m["rank"] < 3)
    return s.select("doc_id", count("assign"), count("access"), count("hex"), F.sha2(written(base), 256).alias("base_sha256"), written(F.col("spans")).alias("spans"))
