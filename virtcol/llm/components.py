"""Connected components by alternating star contractions, in DataFrame operations only.

Each round links every node's larger neighbours to the least node it knows
(large star), then its smaller ones (small star).  Minima are partial
aggregates, so a hub costs a row per map task; the join that hands a hub's
minimum to its neighbours is one that AQE may split.  Rounds end when the edge
set stops changing; about log n are needed.  Edges live in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _large(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small(edges: DataFrame) -> DataFrame:
    """edges have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, scratch: Scratch, most_rounds: int = 60) -> DataFrame:
    """(node, root) for each node of edges (u, v): root is the least node of its component.

    Nulls and loops are no edges; repeated edges count once; no edges: no rows.
    """
    now = scratch.keep(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    mark = _mark(now)
    for _ in range(most_rounds if mark[0] else 0):
        large = scratch.keep(_large(now), "large")
        small = scratch.keep(_small(large), "small")
        before, mark = mark, _mark(small)
        scratch.drop(now)
        scratch.drop(large)
        now = small
        if mark == before:
            break
    else:
        if mark[0]:
            raise RuntimeError("components did not settle")
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots)
