"""Layouts beside the data: how the files are dealt, for later jobs."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import SparkSession

from framepatterns import model

KINDS = {c.__name__: c for c in (model.Arbitrary, model.Hashed, model.Ordered, model.Blocked, model.Replicated)}


def save_layout(spark: SparkSession, path: str, layout: model.Layout) -> None:
    """Write the layout as one JSON line in a folder of its own next to the data."""
    text = json.dumps({"kind": type(layout).__name__, "is": asdict(layout)}, default=str)
    spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path.rstrip('/')}.layout")


def load_layout(spark: SparkSession, path: str) -> model.Layout:
    d = json.loads(spark.read.text(f"{path.rstrip('/')}.layout").first()[0])
    frozen = lambda v: tuple(map(frozen, v)) if isinstance(v, list) else v
    return KINDS[d["kind"]](**{k: frozen(v) for k, v in d["is"].items()})
