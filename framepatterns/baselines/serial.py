"""One-thread baseline: a serial dataframe library on the driver over Arrow files, or in a worker over one part of a frame."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq

#: Rows that the library takes at once from a part, and that a part should hold.
PIECE = 1_000_000


def load(sf_dir: str, table: str, columns: list[str] | None = None) -> pd.DataFrame:
    return pq.read_table(f"{sf_dir}/{table}.parquet", columns=columns).to_pandas()


def scalar_add(df: pd.DataFrame, value: int) -> pd.DataFrame:
    return df + value


def column_sum(df: pd.DataFrame) -> pd.Series:
    return df.sum()


def group(df: pd.DataFrame, key: str, value: str) -> pd.DataFrame:
    return df.groupby(key)[value].agg(["sum", "mean", "std"]).reset_index()


def sums(df: pd.DataFrame, key: str, value: str) -> pd.DataFrame:
    """(key, sum) as SQL has them: a null key is a group, a sum of nothing but nulls is null."""
    return df.groupby(key, dropna=False, sort=False)[value].sum(min_count=1).reset_index()


def sums_of_pieces(batches: Iterator[pa.RecordBatch], piece: int = PIECE) -> Iterator[pa.Table]:
    """One table of sums for every ``piece`` rows or more of a stream of (key, value), both 64-bit integers."""
    held, n = [], 0

    def grouped() -> pa.Table:
        t = pa.Table.from_batches(held)
        out = sums(t.to_pandas(types_mapper={pa.int64(): pd.Int64Dtype()}.get), *t.schema.names)
        return pa.Table.from_pandas(out, preserve_index=False).cast(t.schema)

    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= piece:
            yield grouped()
            held, n = [], 0
    if n:
        yield grouped()


def partial_sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Before rows are dealt: a key once for every piece, so that a hot key does not fill a part."""
    for t in sums_of_pieces(batches):
        yield from t.to_batches(max_chunksize=1 << 16)


def total_sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of all rows of a part, one a key; holds a piece and the part's keys so far."""
    total = None
    for t in sums_of_pieces(batches):
        total = t if total is None else next(sums_of_pieces([*total.to_batches(), *t.to_batches()], total.num_rows + t.num_rows))
    if total is not None:
        yield from total.to_batches(max_chunksize=1 << 16)


def join(a: pd.DataFrame, b: pd.DataFrame, key: str) -> pd.DataFrame:
    return a.merge(b, on=key)


def seconds(fn: Callable[[], object], reps: int = 3) -> float:
    best = float("inf")
    for _ in range(reps):
        began = time.perf_counter()
        fn()
        best = min(best, time.perf_counter() - began)
    return best
