"""Strata, allocations, draws and estimators."""

from __future__ import annotations

from bisect import bisect_right
from dataclasses import dataclass
from hashlib import md5
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def md5_key(id_col: str, seed: int | str) -> Column:
    """The draw's order: any SQL engine computes the same one."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(id_col).cast("string")).cast("binary"))


def fast_key(id_col: str, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col(id_col))


@dataclass
class WeightedFrame:
    """A sample: its rows with a weight `_w` and a stratum `_stratum`, and the size of what it was drawn from."""

    df: DataFrame
    population: int
    sizes: dict
    drawn: dict


def strata_sizes(df: DataFrame, stratum_col: str) -> dict:
    """Rows of each stratum of the population that will be sampled (its filters applied)."""
    return {r[0]: r[1] for r in df.groupBy(stratum_col).count().collect()}  # a row per stratum


def _key(x):
    return (x is None, x)


def allocate(sizes: dict, budget: int, rule: str = "proportional", spread: dict | None = None) -> dict:
    """Rows to draw from each stratum; never more than it has, in all at most `budget`.

    proportional: by size, the rest by largest fraction, ties to the smaller stratum.  equal: the same for all.
    neyman: by size times the spread that a pilot found.  Each nonempty stratum gets one row if the budget allows; with
    fewer calls than strata only the largest get one.
    """
    live = {k: n for k, n in sorted(sizes.items(), key=lambda x: _key(x[0])) if n > 0}
    total = sum(live.values())
    out = dict.fromkeys(sizes, 0)
    if budget <= 0 or not live:
        return out
    if budget >= total:
        return out | live
    if budget <= len(live):
        for k in sorted(live, key=lambda k: (-live[k], _key(k)))[:budget]:
            out[k] = 1
        return out
    share = {k: 1.0 if rule == "equal" else n * (max((spread or {}).get(k, 0.5), 1e-6) if rule == "neyman" else 1.0) for k, n in live.items()}
    whole = sum(share.values())
    quota = {k: budget * s / whole if rule != "proportional" else budget * live[k] / total for k, s in share.items()}
    out |= {k: min(live[k], max(1, int(quota[k]))) for k in live}
    while (left := budget - sum(out.values())) != 0:
        if left > 0:
            open_ = [k for k in live if out[k] < live[k]]
            ranked = sorted(open_, key=lambda k: (-(quota[k] - out[k]), _key(k)))
            for k in ranked[:left]:
                out[k] += 1
        else:
            k = max((k for k in live if out[k] > 1), key=lambda k: (out[k], out[k] - quota[k]))
            out[k] -= 1
    return out


def draw(df: DataFrame, id_col: str, stratum_col: str, take: dict, seed: int = 0, key=md5_key) -> WeightedFrame:
    """The given number of rows of each stratum, those with the least keys, without replacement; each weighs its stratum's size over rows drawn."""
    sizes = strata_sizes(df, stratum_col)
    live = {k: min(n, sizes.get(k, 0)) for k, n in take.items() if n > 0 and sizes.get(k, 0) > 0}
    most = max(live.values(), default=0)
    by = Window.partitionBy("_stratum").orderBy("_key", id_col)
    ranked = df.withColumns({"_stratum": F.col(stratum_col), "_key": key(id_col, seed)}).withColumn("_rank", F.row_number().over(by)).where(F.col("_rank") <= most)
    keep, weight = F.lit(False), F.lit(None).cast("double")
    for k, n in live.items():
        here = F.col("_stratum").eqNullSafe(F.lit(k))
        keep, weight = keep | (here & (F.col("_rank") <= n)), F.when(here, F.lit(sizes[k] / n)).otherwise(weight)
    return WeightedFrame(ranked.where(keep).withColumn("_w", weight).drop("_key", "_rank"), sum(sizes.values()), sizes, live)


def stratified_sample(df: DataFrame, id_col: str, stratum_col: str, budget: int, seed: int = 0, rule: str = "proportional", spread: dict | None = None) -> WeightedFrame:
    return draw(df, id_col, stratum_col, allocate(strata_sizes(df, stratum_col), budget, rule, spread), seed)


def uniform_sample(df: DataFrame, id_col: str, n: int, seed: int = 0, key=md5_key) -> WeightedFrame:
    """n rows with the least keys: a top-k, no full sort."""
    population = df.count()
    n = min(n, population)
    rows = df.withColumn("_key", key(id_col, seed)).orderBy("_key", id_col).limit(n).drop("_key")
    return WeightedFrame(rows.withColumns({"_stratum": F.lit(0), "_w": F.lit(population / n if n else 0.0)}), population, {0: population}, {0: n})


def importance_sample(df: DataFrame, id_col: str, score: Column, n: int, seed: int = 0, floor: float = 0.0, rows: int = 200_000) -> DataFrame:
    """n draws with replacement, each row with probability in proportion to its floored score: rows with `_p` and `_draw`.

    Scores are summed per bucket of about `rows` rows, by a hash of the id; a draw finds its bucket by the buckets' running
    sum, and only buckets that a draw fell into are ordered, a task each.
    """
    s = F.greatest(F.coalesce(score.cast("double"), F.lit(0.0)), F.lit(float(floor)))
    base = df.withColumn("_s", s).where("_s > 0")
    buckets = max(64, base.count() // rows)
    base = base.withColumn("_bucket", F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit("bucket:"), F.col(id_col).cast("string")).cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(buckets)))
    totals = sorted((r[0], r[1]) for r in base.where("_bucket IS NOT NULL").groupBy("_bucket").agg(F.sum("_s")).collect())  # a row per bucket
    ends = list(accumulate(t for _, t in totals))
    if not ends:
        return base.limit(0).withColumns({"_p": F.lit(0.0), "_draw": F.lit(0)}).drop("_s", "_bucket")
    whole, found = ends[-1], []
    for k in range(n):
        u = int(md5(f"{seed}:draw:{k}".encode()).hexdigest()[:12], 16) / 16**12 * whole
        i = min(bisect_right(ends, u), len(ends) - 1)
        found.append((k, totals[i][0], u - (ends[i - 1] if i else 0.0)))
    draws = df.sparkSession.createDataFrame(found, "_draw int, _bucket long, _u double")  # n rows
    hit = base.join(F.broadcast(draws.select("_bucket").distinct()), "_bucket", "left_semi")
    placed = hit.withColumn("_hi", F.sum("_s").over(Window.partitionBy("_bucket").orderBy(id_col))).withColumn("_lo", F.col("_hi") - F.col("_s"))
    return placed.join(F.broadcast(draws), "_bucket").where("_lo <= _u AND _u < _hi").withColumn("_p", F.col("_s") / F.lit(whole)).drop("_s", "_bucket", "_hi", "_lo", "_u")


def importance_estimate(drawn: DataFrame, n: int, f: Column) -> DataFrame:
    """COUNT from importance draws: the mean of f over p."""
    return drawn.agg((F.sum(F.when(f, 1 / F.col("_p")).otherwise(0.0)) / F.lit(float(n))).alias("estimate"))


def optimal_count(df: DataFrame, id_col: str, f: Column, seed: int = 0) -> DataFrame:
    """One draw from the proposal in proportion to f itself: the exact count, with no variance. Needs f everywhere."""
    return importance_estimate(importance_sample(df, id_col, f.cast("int"), 1, seed), 1, f)


def estimate(sample: WeightedFrame, agg: str = "count", f: Column | None = None, value: Column | None = None, normalize: bool = True, by: list[str] | None = None) -> DataFrame:
    """COUNT, SUM or AVG under a condition, from a weighted sample: estimate and the rows it rests on.

    COUNT is the population times the weighted share; not normalised, the weighted sum.  AVG is a ratio, null without a hit.
    """
    f = F.lit(True) if f is None else F.coalesce(f, F.lit(False))
    hit = F.when(f, F.col("_w")).otherwise(0.0)
    x = F.lit(1.0) if value is None else value.cast("double")
    total = float(sample.population)
    if by:
        sums = sample.df.agg(F.sum("_w")).first()[0] or 1.0
        scale = F.lit(total / sums if normalize else 1.0)
        grouped = sample.df.where(f).groupBy(*by)
    else:
        scale = F.lit(total) / F.nullif(F.sum("_w"), F.lit(0.0)) if normalize else F.lit(1.0)
        grouped = sample.df.groupBy()
    made = {"count": scale * F.sum(hit), "sum": scale * F.sum(hit * F.coalesce(x, F.lit(0.0))), "avg": F.sum(hit * x) / F.nullif(F.sum(F.when(x.isNotNull(), hit)), F.lit(0.0))}[agg]
    return grouped.agg(made.alias("estimate"), F.count("*").alias("n"))


def standard_error(sample: WeightedFrame, f: Column, agg: str = "count", value: Column | None = None) -> float:
    """Of a stratified COUNT, SUM or AVG; strata with one drawn row take the pooled variance of the others (or of all rows)."""
    hit = F.when(F.coalesce(f, F.lit(False)), F.lit(1.0)).otherwise(0.0)
    x = F.lit(1.0) if value is None else F.coalesce(value.cast("double"), F.lit(0.0))
    y = hit * x
    scale = float(sample.population)
    if agg == "avg":
        row = sample.df.agg(F.sum(F.col("_w") * hit * x), F.sum(F.col("_w") * hit), F.sum("_w")).first()
        if not row[1]:
            return float("nan")
        y, scale = hit * (x - F.lit(row[0] / row[1])), row[2] / row[1]
    rows = sample.df.groupBy("_stratum").agg(F.count("*").alias("n"), F.var_samp(y).alias("s2"), F.avg(y).alias("m")).collect()
    known = [(r["n"], r["s2"]) for r in rows if r["n"] > 1]
    pooled = sum((n - 1) * s for n, s in known) / max(1, sum(n - 1 for n, _ in known)) if known else (sum((r["m"] - sum(q["m"] for q in rows) / len(rows)) ** 2 for r in rows) / max(1, len(rows) - 1))
    var = 0.0
    for r in rows:
        size, n = sample.sizes[r["_stratum"]], r["n"]
        var += (size / sample.population) ** 2 * (1 - n / size) * (r["s2"] if n > 1 else pooled) / n
    return scale * max(0.0, var) ** 0.5


def intervals(sample: WeightedFrame, agg: str = "count", f: Column | None = None, value: Column | None = None, by: list[str] | None = None, z: float = 1.96) -> DataFrame:
    """Estimate, standard error and normal bounds of a stratified COUNT or SUM, for each group in one pass.

    A row outside the group counts as 0 in its stratum, so groups need no draw of their own; a stratum with one drawn row
    takes the square of its value as variance.
    """
    by = by or []
    y = (F.lit(1.0) if value is None or agg == "count" else F.coalesce(value.cast("double"), F.lit(0.0))) * F.when(F.coalesce(f, F.lit(False)) if f is not None else F.lit(True), 1.0).otherwise(0.0)
    stratum = sample.df.schema["_stratum"].dataType
    shape = T.StructType([T.StructField("_k", stratum), T.StructField("_size", T.DoubleType()), T.StructField("_drawn", T.DoubleType())])
    strata = sample.df.sparkSession.createDataFrame([(k, float(sample.sizes[k]), float(n)) for k, n in sample.drawn.items()], shape)  # a row per stratum
    sums = sample.df.groupBy(*by, "_stratum").agg(F.sum(y).alias("_a"), F.sum(y * y).alias("_b"))
    each = sums.join(F.broadcast(strata), F.col("_stratum").eqNullSafe(F.col("_k")))
    n, size = F.col("_drawn"), F.col("_size")
    spread = F.when(n > 1, F.greatest(F.lit(0.0), F.col("_b") - F.col("_a") * F.col("_a") / n) / (n - 1)).otherwise(F.col("_b"))
    out = each.groupBy(*by).agg(F.coalesce(F.sum(size / n * F.col("_a")), F.lit(0.0)).alias("estimate"), F.coalesce(F.sqrt(F.sum(size * size * (1 - n / size) * spread / n)), F.lit(0.0)).alias("stderr"))
    return out.withColumns({"low": F.col("estimate") - z * F.col("stderr"), "high": F.col("estimate") + z * F.col("stderr")})
