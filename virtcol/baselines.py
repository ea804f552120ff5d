"""What the methods are compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .index.features import dot
from .index.sample import estimate, md5_key, uniform_sample


def full_scan(df: DataFrame, f: Column) -> DataFrame:
    """Every row judged: exact, given the model."""
    return df.where(F.coalesce(f, F.lit(False)))


def udf_count(df: DataFrame, id_col: str, f: Column, budget: int, seed: int = 0) -> DataFrame:
    """A uniform sample judged row by row, scaled up."""
    return estimate(uniform_sample(df, id_col, budget, seed), "count", f)


def udf_rows(df: DataFrame, id_col: str, f: Column, budget: int, seed: int = 0) -> DataFrame:
    return full_scan(uniform_sample(df, id_col, budget, seed).df, f)


def mips(vectors: DataFrame, id_col: str, vec_col: str, query: list[float], k: int) -> DataFrame:
    """The k rows with the largest inner product; ties to the smaller id. Nothing is judged."""
    return vectors.withColumn("score", dot(F.col(vec_col), F.lit([float(x) for x in query]))).orderBy(F.desc("score"), id_col).limit(k)


def mips_then_judge(vectors: DataFrame, id_col: str, vec_col: str, query: list[float], f: Column, budget: int, limit: int) -> DataFrame:
    return full_scan(mips(vectors, id_col, vec_col, query, budget), f).orderBy(F.desc("score"), id_col).limit(limit)


def packs(df: DataFrame, id_col: str, tokens: Column, limit: int, rows: int, seed: int = 0) -> DataFrame:
    """`rows` uniform rows laid into prompts of at most `limit` tokens, in md5 order: `pack`, `place` in it, `size` of it.

    A greedy layout is a fold over the order; the sample it folds over is bounded by `rows`.
    """
    picked = df.withColumns({"_key": md5_key(id_col, seed), "_tokens": F.least(tokens.cast("long"), F.lit(limit).cast("long"))}).orderBy("_key", id_col).limit(rows)
    step = lambda s, x: F.when(s["used"] + x["_tokens"] > limit, F.struct((s["pack"] + 1).alias("pack"), x["_tokens"].alias("used"), F.array_append(s["out"], s["pack"] + 1).alias("out"))).otherwise(F.struct(s["pack"].alias("pack"), (s["used"] + x["_tokens"]).alias("used"), F.array_append(s["out"], s["pack"]).alias("out")))
    folded = picked.agg(F.sort_array(F.collect_list(F.struct("_key", id_col, "_tokens"))).alias("all"))
    start = F.struct(F.lit(0).alias("pack"), F.lit(0).cast("long").alias("used"), F.array().cast("array<int>").alias("out"))
    laid = folded.select(F.explode(F.arrays_zip("all", F.aggregate("all", start, step)["out"].alias("p"))).alias("z")).select(F.col(f"z.all.{id_col}").alias("_id"), F.col("z.p").alias("pack"))
    by = Window.partitionBy("pack")
    return picked.join(laid, F.col(id_col) == F.col("_id")).drop("_id").withColumns({"place": F.row_number().over(by.orderBy("_key", id_col)), "size": F.count("*").over(by)}).drop("_key")


def packed_count(packed: DataFrame, hit: Column, population: int) -> DataFrame:
    """Each prompt's count scaled to the table, averaged over prompts."""
    each = packed.groupBy("pack").agg((F.sum(F.coalesce(hit, F.lit(False)).cast("int")) / F.count("*") * population).alias("e"))
    return each.agg(F.avg("e").alias("estimate"), F.count("*").alias("packs"))


def packed_rows(packed: DataFrame, hit: Column) -> DataFrame:
    return full_scan(packed, hit)


def packed_groups(packed: DataFrame, label: Column, population: int) -> DataFrame:
    each = packed.withColumn("label", label).groupBy("pack", "label").agg((F.count("*") / F.first("size") * population).alias("e"))
    n = packed.agg(F.countDistinct("pack").alias("packs"))
    return each.groupBy("label").agg(F.sum("e").alias("total")).crossJoin(F.broadcast(n)).select("label", (F.col("total") / F.col("packs")).alias("estimate"))
