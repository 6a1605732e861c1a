"""Readers: even spread of files, custom assignment of files to workers, local reads."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from framepatterns.collectives import GATHER_ROWS, shuffle

#: Workers above which an explicit assignment is read by file names instead of by one plan node a worker.
MANY_WORKERS = 64


def read_partitioned(spark: SparkSession, paths: str | list[str], fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """Files in splits of even size.  Text formats need an explicit schema: inference would read the data twice."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(paths)


def assign_evenly(paths: list[str], workers: int) -> dict[int, list[str]]:
    """Worker to files, as even as counts allow, in the files' order."""
    out: dict[int, list[str]] = {w: [] for w in range(workers)}
    for i, p in enumerate(paths):
        out[i * workers // len(paths)].append(p)
    return out


def _qualified(spark: SparkSession, path: str) -> str:
    """The file's full name as its file system writes it, not encoded."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return _plain(p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(p).toString())


def _plain(name: str) -> str:
    return "file:/" + name[5:].lstrip("/") if name.startswith("file:") else name


def read_assigned(spark: SparkSession, assignment: dict[int, list[str]], fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """Read files so that partition w holds exactly the rows of worker w's files; adds the column worker.

    Every worker reads its own files and nothing moves.  With more than MANY_WORKERS workers, where a plan node
    for each would be too much, rows go to their worker by the full name of their file; a file that no worker has
    is an error.
    """
    owner = {_qualified(spark, p): w for w, ps in assignment.items() for p in ps}
    if sum(map(len, assignment.values())) != len(owner):
        raise ValueError("a file is assigned twice")
    workers = max(assignment) + 1
    if schema is None:
        schema = read_partitioned(spark, [p for ps in assignment.values() for p in ps], fmt, schema, **options).schema
    schema = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    if workers <= MANY_WORKERS:
        # the frame without partitions is dealt otherwise than the workers' single partitions: a union of equally
        # dealt frames is free to lay their partitions on top of each other
        none, last = (spark.createDataFrame(rdd, schema) for rdd in (spark.sparkContext.parallelize([], 1), spark.sparkContext.emptyRDD()))
        parts = [read_partitioned(spark, assignment[w], fmt, schema, **options).coalesce(1) if assignment.get(w) else none for w in range(workers)]
        return reduce(DataFrame.unionAll, [p.withColumn("worker", F.lit(w)) for w, p in enumerate([*parts, last])])
    df = read_partitioned(spark, [p for ps in assignment.values() for p in ps], fmt, schema, **options)
    table = spark.createDataFrame(list(owner.items()), "_name string, worker int")
    name = F.regexp_replace(F.url_decode(F.replace(F.col("_metadata.file_path"), F.lit("+"), F.lit("%2B"))), "^file:/+", "file:/")
    named = df.withColumn("_name", name).join(F.broadcast(table), "_name", "left")
    found = F.coalesce("worker", F.raise_error(F.concat(F.lit("no worker has the file "), F.col("_name"))).cast("int"))
    return shuffle(named.withColumn("worker", found), F.col("worker"), workers).select(*schema.names, "worker")


def read_local(spark: SparkSession, path: str, partitions: int | None = None) -> DataFrame:
    """Read one small local Parquet file at the driver and spread it; refused beyond GATHER_ROWS rows."""
    import pyarrow.parquet as pq

    if pq.ParquetFile(path).metadata.num_rows > GATHER_ROWS:
        raise MemoryError(f"{path} is too long for a local read")
    df = spark.createDataFrame(pq.read_table(path))
    return df.repartition(partitions) if partitions else df


def read_with(df_paths: DataFrame, fn, schema: T.StructType | str) -> DataFrame:
    """Read files of any kind: ``fn`` turns a path into an Arrow table; one task a partition of ``df_paths`` (path)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for p in b.column("path").to_pylist():
                yield from fn(p).to_batches()

    return df_paths.mapInArrow(run, schema)


def rows_to_frame(spark: SparkSession, rows: list, schema) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def number_range(spark: SparkSession, start: int, stop: int, step: int = 1, partitions: int | None = None) -> DataFrame:
    return spark.range(start, stop, step, partitions)
