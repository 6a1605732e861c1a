"""User-defined functions: scalar, Arrow partition, and table functions."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def scalar(fn: Callable[[pd.Series], pd.Series], returns: str):
    """A vectorised scalar function; batches travel as Arrow."""

    def call(s: pd.Series) -> pd.Series:
        return fn(s)

    return pandas_udf(call, returns)


@udtf(returnType="word string, length int")
class Tokens:
    """The words of a text with their lengths."""

    def eval(self, text: str) -> Iterator[tuple[str, int]]:
        for w in (text or "").split():
            yield w, len(w)


def missing_filled(c, value):
    """Null and NaN replaced."""
    return F.coalesce(F.nanvl(c, F.lit(None).cast("double")), F.lit(value))
