"""Mixing sources to target weights.

Sizes are summed per source (a partial aggregate, so a hot source costs a row
per task), targets follow from the weights, and each document is then taken
floor(rate) times plus once more if a number drawn from a keyed hash of its id
is below the rate's fraction.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, bounded_broadcast, documents, text_or_empty

#: Sources that a broadcast may carry; with more, sources join by shuffle.
MOST_SOURCES = 100_000


def word_count(text_col: str) -> Column:
    return F.regexp_count(text_or_empty(text_col), F.lit(WORD)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: float = 3.0) -> DataFrame:
    """sizes (source, source_size) with target.

    Sources take the weights in turn, in order of code point, null last, and
    share the sum of all sizes by weight.  A target stops at `most` times its
    source's size and the excess is shared anew among the others, until none is
    above: so all others end at the same level per weight, and the capped ones
    are those with the lowest cap per weight.  Sorted by that, the level left
    for the rest is known from running sums.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    caps = sizes.withColumn("w", weight).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    by = Window.orderBy((F.col("cap") / F.col("w")).asc(), F.col("source").asc_nulls_last())
    before = by.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    levels = caps.withColumn("level", (F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("w").over(whole) - F.coalesce(F.sum("w").over(before), F.lit(0.0)))).withColumn("over", F.col("cap") / F.col("w") < F.col("level"))
    first = F.first(F.when(~F.col("over"), F.col("level")), ignorenulls=True).over(by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return levels.withColumn("first", first).select("source", "source_size", F.when(F.col("over"), F.col("cap")).otherwise(F.col("first") * F.col("w")).alias("target"))


def draw(id_col: str, seed: str) -> Column:
    """A number in [0, 1) that the id and the seed fix: the first 32 bits of a digest, which any SQL engine can compute too."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("null"))).cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def mix(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: float = 3.0, seed: str = "mix", id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """docs with size, source_size, target and copies (long).

    Null sources are one source; null and wordless texts have size 0 and are
    copied at their source's rate; equal ids draw alike.  Columns of docs with
    the result's names are replaced; an empty table gives no rows.
    """
    made = ("size", "source_size", "target", "copies", "__rate_source")
    sized = docs.drop(*made).withColumns({"size": word_count(text_col), "__rate_source": F.col(source_col)})
    sizes = sized.groupBy(F.col("__rate_source").alias("source")).agg(F.sum("size").alias("source_size"))
    of = bounded_broadcast(targets(sizes, weights, most).select(F.col("source").alias("__s"), "source_size", "target"), MOST_SOURCES)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    whole = F.floor("__rate").cast("long")
    return (
        sized.join(of, F.col("__rate_source").eqNullSafe(F.col("__s")))
        .withColumn("__rate", F.least(rate, F.lit(float(most))))
        .withColumn("copies", whole + (draw(id_col, seed) < F.col("__rate") - whole).cast("long"))
        .drop("__rate", "__s", "__rate_source")
    )


def emit(mixed: DataFrame) -> DataFrame:
    """Each document as often as it is taken."""
    return mixed.where("copies > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).drop("__copy")


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir).select("doc_id", "text", "source")).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


OP4_SQL = """
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
w AS (SELECT *, [5.0::DOUBLE, 2.0, 1.0][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT] AS w, source_size * 3.0::DOUBLE AS cap FROM s),
l AS (SELECT *, ((SELECT sum(source_size) FROM w) - coalesce(sum(cap) OVER before, 0)) / ((SELECT sum(w) FROM w) - coalesce(sum(w) OVER before, 0)) AS level
  FROM w WINDOW before AS (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size, CASE WHEN cap / w < level THEN cap ELSE w * (SELECT arg_min(level, cap / w) FROM l WHERE cap / w >= level) END AS target FROM l),
r AS (SELECT d.doc_id, d.size, t.source_size, t.target, least(CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END, 3.0::DOUBLE) AS rate,
  ('0x' || substr(md5('mix:' || coalesce(CAST(d.doc_id AS VARCHAR), 'null')), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u
  FROM sized d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, CAST(size * (floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM r
"""
