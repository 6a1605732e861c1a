"""Distributed dataframe: a DataFrame, its row-label columns, and where its rows are."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame


def whole_input(df: DataFrame, name: str) -> DataFrame:
    """``df``, refused if it is a stream: ``name`` needs all rows before it can give the first result."""
    if df.isStreaming:
        raise NotImplementedError(f"{name} needs the whole input and does not run on a stream")
    return df


@dataclass(frozen=True)
class Arbitrary:
    """Rows lie anywhere."""

    partitions: int | None = None


@dataclass(frozen=True)
class Hashed:
    """Rows with equal keys lie in one of ``partitions`` partitions (Spark's own hash partitioning)."""

    keys: tuple[str, ...]
    partitions: int


@dataclass(frozen=True)
class Ordered:
    """Partition i holds the keys from pivot i-1 up to pivot i; a key that is a pivot may lie on both sides of it.

    Pivots are numbers for one numeric key, else tuples of one value a key; ``hot`` tells that one of them is the
    key of many rows.
    """

    keys: tuple[str, ...]
    pivots: tuple
    partitions: int
    ascending: bool = True
    hot: bool = False


@dataclass(frozen=True)
class Blocked:
    """Partition i holds the global positions from offset i up to offset i+1."""

    offsets: tuple[int, ...]


@dataclass(frozen=True)
class Replicated:
    """A scalar or small frame that every executor may hold whole."""


Layout = Arbitrary | Hashed | Ordered | Blocked | Replicated


@dataclass(frozen=True)
class Frame:
    """A distributed dataframe.

    ``labels`` names the columns that hold the row labels (none: the default label is the global position).
    ``why`` keeps, for explain, which pattern made the frame and what it cost.
    """

    df: DataFrame
    labels: tuple[str, ...] = ()
    layout: Layout = field(default_factory=Arbitrary)
    why: tuple[str, ...] = ()

    @property
    def schema(self):
        return self.df.schema

    def with_df(self, df: DataFrame, layout: Layout | None = None, note: str | None = None) -> Frame:
        return replace(self, df=df, layout=self.layout if layout is None else layout, why=self.why + ((note,) if note else ()))

    def co_located(self, keys: tuple[str, ...]) -> bool:
        """Whether rows with equal ``keys`` already lie together."""
        return isinstance(self.layout, Hashed) and set(self.layout.keys) <= set(keys)

    def to_labels(self, *cols: str, check: bool = False) -> Frame:
        """Promote columns to row labels; ``check`` raises if they are not unique (one shuffle)."""
        missing = set(cols) - set(self.df.columns)
        if missing:
            raise ValueError(f"no such columns: {sorted(missing)}")
        if check and not self.df.groupBy(*cols).count().where("count > 1").isEmpty():
            raise ValueError(f"labels {cols} are not unique")
        return replace(self, labels=cols)

    def from_labels(self, order: list | None = None, name: str = "label") -> Frame:
        """Demote labels to plain columns; with ``order`` add the default label, the global position."""
        out = replace(self, labels=())
        if order:
            from framepatterns.layout.rebalance import with_position

            out = replace(out, df=with_position(self.df, order, name), labels=(name,))
        return out

    def rename(self, names: dict[str, str]) -> Frame:
        return replace(self, df=self.df.withColumnsRenamed(names), labels=tuple(names.get(x, x) for x in self.labels), layout=Arbitrary())

    def explain(self) -> str:
        from framepatterns.plans.explain import explain_frame

        return explain_frame(self)
