"""The training-corpus pipeline: quality rules, near-duplicates, personal data, source mix, token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from virtcol.llm import bpe, mixing, pii, quality, simhash
from virtcol.llm.common import Scratch


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the likelihood ratio reject go.

    Null, empty and wordless texts fail the base rules; equal rows share a verdict; an empty table gives none.  Columns keep their names.
    """
    judged = quality.judge(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judged.where("kept").select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity 0.8) the document with the least id stays.

    Null and wordless texts are one group; of rows that share the least id one stays; ids may be null, such rows stay only where their group has no other.
    """
    return simhash.representatives(docs, words=5, radius=2, similarity=0.8).select(*docs.columns)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data gives way to surrogates.

    Null texts stay null; empty ones stay empty; repeated rows are rewritten alike; n_chars is counted anew.
    """
    return pii.replace(docs, pii.session_key(spark)).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents come as often as their source's target asks.

    A null source is one source; wordless texts come at their source's rate; equal ids draw alike; an empty table gives none.
    """
    return mixing.emit(mixing.mix(docs)).select(*docs.columns)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its ids (little-endian 32-bit) and their digests.

    Null and empty texts have no ids; every row stays.
    """
    return bpe.encode(docs, extra=("token_ids",), drop=("text",)).select("doc_id", "lang", "source", "n_tokens", "ids_sha256", "decoded_sha256", "token_ids")


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("source_mix", source_mix), ("token_ids", token_ids)]

#: SQL can express neither the likelihood ratio's hashes nor the encoder.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet and read again."""
    docs, scratch = spark.read.parquet(f"{sf_dir}/documents.parquet"), Scratch(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        docs = scratch.keep(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
