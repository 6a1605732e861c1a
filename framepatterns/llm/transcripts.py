"""Chat formatting: roles of a raw transcript by a hidden Markov model, then canonical turns.

A transcript is a sequence of lines.  Hidden states are the three roles, each as the first line of a turn or
a later one.  A line shows a speaker marker or none, whether a blank line came before, whether it ends in a
question mark, and how long it is.  All probabilities, of markers and blank lines too, are counted on the lines
of labelled transcripts; Viterbi's path gives every line its role and tells where turns begin.

Decoding changes no text: only the marker that opens a turn of its own role is taken off, lines that look like
markers elsewhere stay, and blank lines inside a turn stay too.

Decoding streams over the lines of a conversation: as soon as all surviving paths agree on a prefix, it is
written out, so a very long conversation needs no more memory than the stretch that is still open.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROLES = ("system", "user", "assistant")
#: Words that mark a role at the start of a line, with optional brackets or hashes before and a sign after.
MARKERS = {"system": "system|instructions?", "user": "user|human|customer|question|q", "assistant": "assistant|ai|bot|model|answer|a"}
LENGTHS = (40, 120, 300)
FEATURES = 8
#: Pseudo-counts of an observation that a state has never shown.
SMOOTH = 0.5
MARKS = len(ROLES) + 1


def _marked(role: str) -> str:
    return rf"^\s*(?i:[#\[<*]*\s*(?:{MARKERS[role]})\s*[\]>*]*\s*[:>\]-]\s?)"


def marker(line: Column) -> Column:
    """0 for a line without marker, else 1 + the role's position in ROLES."""
    out = F.lit(0)
    for i, role in enumerate(ROLES):
        out = F.when(F.regexp(line, F.lit(_marked(role))), i + 1).otherwise(out)
    return out.cast("int")


def bare(line: Column) -> Column:
    """The line without its marker."""
    out = line
    for role in ROLES:
        out = F.when(F.regexp(line, F.lit(_marked(role))), F.regexp_replace(line, _marked(role), "")).otherwise(out)
    return out


def line_feature(line: Column) -> Column:
    """Question mark and length class of a line's content, as one small number."""
    n = F.length(F.trim(line))
    length = F.when(n < LENGTHS[0], 0).when(n < LENGTHS[1], 1).when(n < LENGTHS[2], 2).otherwise(3)
    return (length * 2 + F.coalesce(F.regexp(line, F.lit(r"\?\s*$")).cast("int"), F.lit(0))).cast("int")


def is_blank(line: Column) -> Column:
    return F.trim(line) == ""


@dataclass(frozen=True)
class Model:
    """Log-probabilities: role after role (row 0: the first role), staying in a turn, and observations by state."""

    trans: np.ndarray  # 4 x 3
    stay: np.ndarray  # 3
    marks: np.ndarray  # 6 x MARKS
    blanks: np.ndarray  # 6 x 2
    feats: np.ndarray  # 6 x FEATURES


def _log(counts: np.ndarray) -> np.ndarray:
    return np.log(counts / counts.sum(-1, keepdims=True))


def fit(transcripts: DataFrame) -> Model:
    """Counts on labelled transcripts: one row a turn (conv_id, turn, role, lines), the separating blank line first.

    A first line is the first line after the separator that is not blank.  Rows with an unknown role are left out.
    """
    known = transcripts.where(F.col("role").isin(*ROLES))
    after = known.select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("role").alias("before"))
    trans = np.full((MARKS, 3), SMOOTH)
    for before, role, n in known.select("conv_id", "turn", "role").join(after, ["conv_id", "turn"], "left").groupBy("before", "role").count().collect():
        trans[ROLES.index(before) + 1 if before else 0, ROLES.index(role)] += n
    shown = F.filter(F.transform("lines", lambda x, i: F.struct(x.alias("line"), (i > 0).alias("any"), F.when(i > 0, is_blank(F.element_at("lines", F.greatest(i, F.lit(1))))).otherwise(False).alias("blank"))), lambda x: ~is_blank(x["line"]))
    lines = known.select("role", F.posexplode(shown).alias("k", "x"))
    seen = lines.groupBy("role", (F.col("k") > 0).cast("int").alias("later"), marker(F.col("x.line")).alias("m"), F.col("x.blank").cast("int").alias("b"), line_feature(F.col("x.line")).alias("f")).count()
    marks, blanks, feats, stay = np.full((6, MARKS), SMOOTH), np.full((6, 2), SMOOTH), np.full((6, FEATURES), SMOOTH), np.full((3, 2), SMOOTH)
    for role, later, m, b, f, n in seen.collect():  # one row for each state and observation at most
        state = ROLES.index(role) + 3 * later
        marks[state, m] += n
        blanks[state, b] += n
        feats[state, f] += n
        stay[ROLES.index(role), later] += n
    return Model(_log(trans), _log(stay)[:, 1], _log(marks), _log(blanks), _log(feats))


class Decoder:
    """Viterbi over a stream of observations; ``push`` returns the states that are settled so far."""

    def __init__(self, model: Model, lag: int = 256):
        self.lag = lag
        self.emit = (model.marks.T[:, None, None] + model.blanks.T[None, :, None] + model.feats.T[None, None]).astype(np.float64)  # marker, blank, feature, state
        step = np.full((6, 6), -50.0)
        for a in range(6):
            step[a, :3] = model.trans[a % 3 + 1] + np.log1p(-np.exp(model.stay[a % 3]))
            step[a, 3 + a % 3] = model.stay[a % 3]
        self.step, self.start = step, np.concatenate([model.trans[0], np.full(3, -50.0)])
        self.reset()

    def reset(self) -> None:
        self.score, self.back = None, []

    def push(self, m: int, b: int, f: int) -> list[int]:
        e = self.emit[m, b, f]
        if self.score is None:
            self.score = self.start + e
            self.back.append(np.arange(6))
            return []
        total = self.score[:, None] + self.step
        came = total.argmax(0)
        self.score = total[came, np.arange(6)] + e
        self.score = self.score - self.score.max()
        self.back.append(came)
        return self._settled() if len(self.back) % self.lag == 0 else []

    def _settled(self) -> list[int]:
        alive, at = np.arange(6), len(self.back) - 1
        while at > 0:
            alive = np.unique(self.back[at][alive])
            at -= 1
            if alive.size == 1:
                path = self._path(int(alive[0]), at)
                self.back = self.back[at + 1 :]
                return path
        return []

    def _path(self, state: int, at: int) -> list[int]:
        path = [state]
        for k in range(at, 0, -1):
            state = int(self.back[k][state])
            path.append(state)
        return path[::-1]

    def finish(self) -> list[int]:
        path = self._path(int(self.score.argmax()), len(self.back) - 1) if self.back else []
        self.reset()
        return path


def parse_lines(lines: DataFrame, model: Model) -> DataFrame:
    """(conv_id, pos, content, role, turn) for the lines of ``lines`` (conv_id, pos, line) but the blank ones between turns.

    role is the recovered role, turn counts the recovered turns from 0.  The marker of a turn's first line is
    taken off if it names the recovered role.  Of the blank lines before a turn the last is the separator and
    goes; earlier ones belong to the turn before, those before the first turn to the first.

    Lines come in the order of pos, then of the line; a null line is blank; conversations with a null id are
    one conversation; a conversation of blank lines has no turns.  An empty table gives an empty result; other
    columns are ignored.  Memory does not grow with the number or the length of a conversation's lines, but for
    one line's text.
    """
    clean = lines.select(F.col("conv_id").cast("long"), F.col("pos").cast("long"), F.coalesce(F.col("line").cast("string"), F.lit("")).alias("line"))
    seen = clean.select("conv_id", "pos", "line", marker(F.col("line")).alias("m"), is_blank(F.col("line")).alias("blank"), line_feature(F.col("line")).alias("f"))
    dealt = seen.repartition("conv_id").sortWithinPartitions("conv_id", "pos", "line")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = Decoder(model)
        conv, turn = object(), -1
        open_rows: list[tuple] = []  # lines whose state is not settled, with the blank lines before each
        pending: list[tuple] = []
        out: list[tuple] = []

        def settle(states: list[int]) -> None:
            nonlocal turn, open_rows
            for (row, blanks), s in zip(open_rows, states, strict=False):
                opens = s < 3 or turn < 0
                before = turn
                turn += opens
                kept = blanks[:-1] if opens else blanks
                out.extend((*x, settle.role if before >= 0 else s % 3, max(before, 0), False) for x in kept)
                settle.role = s % 3
                out.append((*row, s % 3, turn, opens))
            open_rows = open_rows[len(states) :]

        def close() -> None:
            nonlocal pending
            settle(decoder.finish())
            if turn >= 0:
                out.extend((*x, settle.role, turn, False) for x in pending)
            pending = []

        def flush():
            nonlocal out
            rows, out = out, []
            types = (pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=["conv_id", "pos", "line", "state", "turn", "opens"])

        settle.role = 0
        for batch in batches:
            for c, pos, line, m, is_blank_, f in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                if c != conv:
                    close()
                    conv, turn = c, -1
                if is_blank_:
                    pending.append((c, pos, line))
                    continue
                open_rows.append(((c, pos, line), pending))
                settle(decoder.push(m, 1 if pending else 0, f))
                pending = []
            if out:
                yield flush()
        close()
        if out:
            yield flush()

    decoded = dealt.mapInArrow(run, "conv_id long, pos long, line string, state int, turn long, opens boolean")
    own = F.col("opens") & (marker(F.col("line")) == F.col("state") + 1)
    role = F.element_at(F.array(*map(F.lit, ROLES)), F.col("state") + 1)
    return decoded.select("conv_id", "pos", F.when(own, bare(F.col("line"))).otherwise(F.col("line")).alias("content"), role.alias("role"), "turn")


def render_turns(parsed: DataFrame) -> DataFrame:
    """(conv_id, turn, role, rendered): the canonical text of every turn."""
    turns = parsed.groupBy("conv_id", "turn", "role").agg(F.array_sort(F.collect_list(F.struct("pos", "content"))).alias("l"))
    body = F.array_join(F.transform("l", lambda x: x["content"]), "\n")
    return turns.select("conv_id", "turn", "role", F.concat(F.lit("<|"), "role", F.lit("|>\n"), body, F.lit("\n<|end|>")).alias("rendered"))


def written_turns(turns: DataFrame) -> DataFrame:
    """(conv_id, turn, role, lines): each turn as a transcript shows it, after a blank line, in one of four marker styles, one marker in five lost."""
    style = F.pmod(F.xxhash64("conv_id"), F.lit(4))
    lost = F.pmod(F.xxhash64("conv_id", "turn"), F.lit(5)) == 0
    name = F.when(style < 2, F.col("role")).otherwise(F.when(F.col("role") == "user", "human").when(F.col("role") == "assistant", "bot").otherwise(F.col("role")))
    mark = F.when(style == 0, F.concat(F.initcap(name), F.lit(": "))).when(style == 1, F.concat(F.lit("["), name, F.lit("] - "))).when(style == 2, F.concat(F.lit("### "), F.initcap(name), F.lit(": "))).otherwise(F.concat(F.upper(name), F.lit("> ")))
    body = F.split(F.coalesce(F.col("text"), F.lit("")), "\n")
    lines = F.concat(F.array(F.lit("")), F.transform(body, lambda x, i: F.when((i == 0) & ~lost, F.concat(mark, x)).otherwise(x)))
    return turns.select("conv_id", "turn", "role", lines.alias("lines"))


def raw_transcripts(turns: DataFrame) -> DataFrame:
    """Undo the formatting of labelled turns: (conv_id, pos, line) of ``written_turns``."""
    width = F.lit(1 << 20)
    return written_turns(turns).select("conv_id", "turn", F.posexplode("lines").alias("k", "line")).select("conv_id", (F.col("turn") * width + F.col("k")).alias("pos"), "line")


def held_out(conv_id: Column) -> Column:
    """One conversation in five is never learnt from."""
    return F.pmod(F.xxhash64(F.lit("held out"), conv_id), F.lit(5)) == 0


def format_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, turn, role, rendered): conversations parsed again from their raw transcripts.

    ``turns`` has conv_id, turn, role and text.  Role names are only used to fit the model, on four
    conversations in five, and to write markers, of which one in five is lost; boundaries and roles of all
    conversations are recovered by the model.

    A null or empty text whose marker is lost is a blank line and goes to the turn before; null or unknown roles
    are written as markers but not learnt from; rows that repeat (conv_id, turn) are further lines of that
    place; lines of any length and turns of any number stay whole; an empty table gives an empty result; other
    columns are ignored.
    """
    known = turns.select("conv_id", F.coalesce("turn", F.lit(0)).alias("turn"), F.coalesce("role", F.lit("user")).alias("role"), "text")
    return render_turns(parse_lines(raw_transcripts(known), fit(written_turns(known.where(~held_out(F.col("conv_id")))))))
