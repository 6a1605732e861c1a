"""The queries op1 .. op10 and pipeline: thin digests of this subpackage's operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.curve_shards import document_shards

    out = document_shards(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")


def op2_setsketch_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.near_duplicates import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "documents"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.toxicity import toxicity

    return toxicity(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op4_doubling_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.repeated_passages import remove_repeats

    out = remove_repeats(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def op5_chat_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.transcripts import format_conversations

    return format_conversations(_table(spark, sf_dir, "conversations"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.decontamination import contaminated

    return contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.licenses import document_paths, license_scan

    return license_scan(document_paths(_table(spark, sf_dir, "documents")))


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.secrets import secret_digest

    return secret_digest(_table(spark, sf_dir, "documents"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.source_mixing import mix_plan

    out = mix_plan(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op10_vector_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from framepatterns.llm.vector_graph import near_vectors

    return near_vectors(_table(spark, sf_dir, "embeddings")).drop("recall")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (op1_hilbert_shards, op2_setsketch_near_duplicates, op3_toxicity, op4_doubling_substrings, op5_chat_turns, op6_decontamination)
    named += (op7_license_scan, op8_secret_scan, op9_source_mix, op10_vector_near_duplicates, pipeline)
    return {f.__name__: f for f in named}


def oracles() -> dict[str, str]:
    """SQL for the contracts that SQL expresses; the other queries are held against brute force in tests/llm."""
    from framepatterns.llm.near_duplicates import OP2_SQL
    from framepatterns.llm.repeated_passages import OP4_SQL
    from framepatterns.llm.source_mixing import OP9_SQL
    from framepatterns.llm.vector_graph import OP10_SQL

    return {"op2_setsketch_near_duplicates": OP2_SQL, "op4_doubling_substrings": OP4_SQL, "op9_source_mix": OP9_SQL, "op10_vector_near_duplicates": OP10_SQL}
