"""Corpus pipeline: toxicity, near duplicates, decontamination, mixing, sharding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from framepatterns.llm import curve_shards, decontamination, near_duplicates, source_mixing, toxicity
from framepatterns.llm.scratch import Scratch

#: Ids that may be replicated: 16 MB.
BROADCAST_ROWS = 1_000_000
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity below one half, the columns of documents.

    Labels of a null doc_id or with a null label are not learnt from; without labels, or with labels of one kind
    only, all texts have one score.  Null and empty texts have the score of a text without words.  Rows that
    repeat a doc_id are judged each; texts of any length are read whole; other columns go.
    """
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), Scratch(spark, "pipeline"))
    return toxicity.score(docs.select(*COLUMNS), model).where("toxicity < 0.5").select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each group with five-word shingle similarity of 0.8 or more, the columns of documents.

    Texts without words are alike with nothing and stay.  Rows that repeat a doc_id are one document and stay or go
    together; a row without doc_id stays.  Texts of any length are read whole; other columns go.
    """
    found = near_duplicates.near_duplicates(docs, shingle=5)
    gone = Scratch(spark, "pipeline").save(found.where("not kept").select("doc_id").distinct())
    few = gone.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS  # beyond it, both sides are dealt by doc_id
    return docs.select(*COLUMNS).join(F.broadcast(gone) if few else gone, "doc_id", "left_anti").select(*COLUMNS)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item, the columns of documents.

    Null and empty texts and items match nothing; rows that repeat a doc_id are judged each by their text; texts of
    any length are read whole; without items all rows stay; other columns go.
    """
    return decontamination.decontaminate(docs.select(*COLUMNS), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, 0, 1 or 2 times, the columns of documents.

    A null text has no words and is taken like others of its source; a null source is a source of its own; equal
    doc_ids are taken or left together, so reruns and ties agree; an empty table stays empty; other columns go.
    """
    mixed = source_mixing.mix_sources(docs.select(*COLUMNS))
    return mixed.where("copies > 0").select(*COLUMNS, F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("copy")).select(*COLUMNS)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with curve, shard (0 to 23) and slot, shards equal in rows but for one.

    Rows of one cell of the curve are in the order of a hash of doc_id, then doc_id (null first), then the text's
    checksum; rows that are equal in these are interchangeable.  An empty table stays empty; other columns go.
    """
    return curve_shards.curve_shards(docs.select(*COLUMNS), 24, tie=F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix),
    ("sharding", shard),
]

#: SQL can express neither the language models nor the searches; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are written to the shared folder and read again."""
    scratch = Scratch(spark, "stages")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
