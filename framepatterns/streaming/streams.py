"""Streams over files: row-local, windowed aggregation, stream-static joins, de-duplication.

Global sorts, windows without a key and transposes need the whole input and refuse a stream.  Results go to
files, never to the driver.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from framepatterns.session import shared_root


def file_stream(spark: SparkSession, path: str, schema, fmt: str = "parquet", files_per_batch: int | None = None) -> DataFrame:
    r = spark.readStream.format(fmt).schema(schema)
    return (r.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else r).load(path)


def table_stream(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables as a stream of files."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    return spark.readStream.format("parquet").schema(schema).option("pathGlobFilter", f"{table}.parquet").load(sf_dir)


def tumbling(df: DataFrame, ts: str, width: str, keys: list[str], aggs: list[Column], late: str = "1 hour") -> DataFrame:
    return df.withWatermark(ts, late).groupBy(F.window(ts, width), *keys).agg(*aggs)


def sliding(df: DataFrame, ts: str, width: str, step: str, keys: list[str], aggs: list[Column], late: str = "1 hour") -> DataFrame:
    return df.withWatermark(ts, late).groupBy(F.window(ts, width, step), *keys).agg(*aggs)


def session(df: DataFrame, ts: str, gap: str, keys: list[str], aggs: list[Column], late: str = "1 hour") -> DataFrame:
    return df.withWatermark(ts, late).groupBy(F.session_window(ts, gap), *keys).agg(*aggs)


def deduplicated(df: DataFrame, keys: list[str], ts: str, late: str = "1 hour") -> DataFrame:
    return df.withWatermark(ts, late).dropDuplicatesWithinWatermark(keys)


def with_static(stream: DataFrame, static: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    """Join with a static table; its rows travel, not the stream's."""
    return stream.join(static, on, how)


def rolling_by_key(stream: DataFrame, key: str, order: str, value: str, k: int, idle_ms: int | None = None) -> DataFrame:
    """(key, order, rolled): the sum of each key's last k values, kept as state across micro-batches.

    The state is the key's last k - 1 values; with ``idle_ms`` a key that is silent for longer is forgotten and
    starts anew.  Rows of a micro-batch are taken in the order of ``order``; rows that come in a later batch count
    as later.  All columns are longs.
    """

    def step(keys: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        held = list(state.get[0]) if state.exists else []
        rows = pd.concat(list(frames)).sort_values(order)
        rolled = []
        for v in rows[value]:
            held = [*held, int(v)][-k:]
            rolled.append(sum(held))
        state.update((held[-(k - 1) :] if k > 1 else [],))
        if idle_ms:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({key: keys[0], order: rows[order].to_numpy(), "rolled": rolled})

    thin = stream.select(F.col(key).cast("long").alias(key), F.col(order).cast("long").alias(order), F.col(value).cast("long").alias(value))
    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout
    return thin.groupBy(key).applyInPandasWithState(step, f"{key} long, {order} long, rolled long", "held array<long>", "append", timeout)


def to_files(stream: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, checkpoint: str | None = None) -> None:
    """Append everything that is there now to files, each row once, in folders by ``by``; for append-mode streams."""
    w = stream.writeStream.format(fmt).outputMode("append").option("checkpointLocation", checkpoint or _state(stream.sparkSession))
    (w.partitionBy(*by) if by else w).trigger(availableNow=True).start(path).awaitTermination()


def run_to_end(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Process all that is there now and return the result table, read from files.

    Appended rows are written by the file sink.  In complete mode every micro-batch writes the whole result so
    far to a folder of its own, and the last one counts.
    """
    spark, path = stream.sparkSession, f"{_state(stream.sparkSession)}_out"
    if mode == "append":
        to_files(stream, path)
        return spark.read.schema(stream.schema).parquet(path)
    last: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/b{number}")
        last.append(number)

    q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", _state(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/b{last[-1]}") if last else spark.createDataFrame([], stream.schema)


def to_batches(stream: DataFrame, fn: Callable[[DataFrame, int], None]) -> None:
    """Hand every micro-batch to batch operators."""
    q = stream.writeStream.foreachBatch(fn).option("checkpointLocation", _state(stream.sparkSession)).trigger(availableNow=True).start()
    q.awaitTermination()


def _state(spark: SparkSession) -> str:
    return f"{shared_root(spark)}/stream_{uuid.uuid4().hex}"
