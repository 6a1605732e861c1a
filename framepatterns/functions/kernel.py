"""Local kernels: the part of an operator that runs inside a partition, in one of three languages behind one interface."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame

from framepatterns.model import Arbitrary
from framepatterns.patterns import Frame, as_frame


@dataclass(frozen=True)
class SqlKernel:
    """Expressions by name, which stay inside the engine; columns not named pass through."""

    columns: dict[str, Column]

    def run(self, df: DataFrame) -> DataFrame:
        return df.withColumns(self.columns)


@dataclass(frozen=True)
class ArrowKernel:
    """A function on Arrow tables, batch by batch, and the schema of its result."""

    fn: Callable[[pa.Table], pa.Table]
    schema: str

    def run(self, df: DataFrame) -> DataFrame:
        fn = self.fn

        def batches(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in found:
                yield from fn(pa.Table.from_batches([b])).to_batches()

        return df.mapInArrow(batches, self.schema)


@dataclass(frozen=True)
class PandasKernel:
    """A function of a serial dataframe library, batch by batch, and the schema of its result."""

    fn: Callable[[pd.DataFrame], pd.DataFrame]
    schema: str

    def run(self, df: DataFrame) -> DataFrame:
        fn = self.fn
        return df.mapInPandas(lambda found: map(fn, found), self.schema)


LocalKernel = SqlKernel | ArrowKernel | PandasKernel


def local(x: Frame | DataFrame, kernel: LocalKernel) -> Frame:
    """Apply a kernel in every partition.  Nothing moves; the result's layout is arbitrary, since a kernel may rewrite keys."""
    f = as_frame(x)
    return f.with_df(kernel.run(f.df), Arbitrary(), f"row-local: {type(kernel).__name__}")
