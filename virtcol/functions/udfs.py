"""semantic_match for plain SQL, the weighted mean as an aggregate, replies and transcripts as table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def judge_batches(df: DataFrame, source: str, phrase: str, client, out: str = "said") -> DataFrame:
    """df with the phrase's answer, in Arrow batches; `client()` is made once a task and answers (phrase, texts) at once."""

    @F.pandas_udf("boolean")
    def ask(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = client()
        for texts in batches:
            yield pd.Series(model(phrase, texts.fillna("").tolist()), dtype="boolean")

    return df.withColumn(out, ask(F.col(source).cast("string")))


def judge_partitions(df: DataFrame, id_col: str, source: str, phrase: str, client) -> DataFrame:
    """(id, said): the same through mapInPandas, for models that see whole rows."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = client()
        for b in batches:
            yield pd.DataFrame({"id": b[id_col], "said": model(phrase, b[source].fillna("").tolist())})

    return df.select(id_col, F.col(source).cast("string").alias(source)).mapInPandas(run, f"id {df.schema[id_col].dataType.simpleString()}, said boolean")


def weighted_moments(df: DataFrame, x: str, w: str, by: list[str]) -> DataFrame:
    """Weighted mean and variance per group from three sums, natively; null values do not count."""
    v, m = F.col(x).cast("double"), F.when(F.col(x).isNotNull(), F.col(w).cast("double"))
    n, s = F.nullif(F.sum(m), F.lit(0.0)), F.sum(m * v)
    return df.groupBy(*by).agg((s / n).alias("mean"), (F.sum(m * v * v) / n - (s / n) * (s / n)).alias("variance"))


def register(spark: SparkSession, answer) -> None:
    """SQL's semantic_match(text, phrase), by the given function of both; texts arrive in Arrow batches."""

    @F.pandas_udf("boolean")
    def semantic_match(text: pd.Series, phrase: pd.Series) -> pd.Series:
        return pd.Series([None if t is None else bool(answer(t, p)) for t, p in zip(text, phrase)], dtype="boolean")

    @F.pandas_udf("double")
    def weighted_mean(x: pd.Series, w: pd.Series) -> float:
        return float((x * w).sum() / w.sum()) if w.sum() else float("nan")

    @F.udtf(returnType="name string, description string, n int")
    class GroupTable:
        def eval(self, reply: str):
            from ..model.base import parse_group_table

            yield from parse_group_table(reply)

    @F.udtf(returnType="turn int, role string, text string")
    class Turns:
        def eval(self, transcript: str):
            for i, line in enumerate((transcript or "").splitlines()):
                role, _, text = line.partition(": ")
                yield i, role, text

    spark.udtf.register("transcript_turns", Turns)
    spark.udf.register("semantic_match", semantic_match)
    spark.udf.register("weighted_mean", weighted_mean)
    spark.udtf.register("group_table", GroupTable)
