"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def relative_error(estimate: Column, truth: Column) -> Column:
    """abs(estimate - truth) / truth; null for a truth of 0."""
    return F.when(truth != 0, F.abs(estimate - truth) / truth)


def f1_table(returned: DataFrame, positives: DataFrame, cap: int | None = None) -> DataFrame:
    """Of returned ids against true ones: precision, recall of all and of what a cap allows, and both F1; 0/0 counts as 0."""
    both = returned.select("id").distinct().withColumn("r", F.lit(1)).join(positives.select("id").distinct().withColumn("p", F.lit(1)), "id", "full")
    n = both.agg(F.count("r").alias("returned"), F.count("p").alias("positives"), F.count(F.when(F.col("r").isNotNull() & F.col("p").isNotNull(), 1)).alias("hits"))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    capped = F.least(F.lit(cap), F.col("positives")) if cap is not None else F.col("positives")
    n = n.withColumns({"precision": ratio(F.col("hits"), F.col("returned")), "recall_all": ratio(F.col("hits"), F.col("positives")), "recall_capped": ratio(F.col("hits"), capped)})
    harmonic = lambda r: F.when(F.col("precision") + F.col(r) > 0, 2 * F.col("precision") * F.col(r) / (F.col("precision") + F.col(r))).otherwise(0.0)
    return n.withColumns({"f1_all": harmonic("recall_all"), "f1_capped": harmonic("recall_capped")})


def positive_share(df: DataFrame, f: Column) -> DataFrame:
    """The random searcher's expected hit rate."""
    return df.agg(F.avg(f.cast("int")).alias("share"), F.count("*").alias("n"))


def hit_rate_curve(trace: DataFrame, window: int = 16) -> DataFrame:
    """trace (run, step, hit): the hit rate of the last `window` judged rows and the hits so far."""
    by = Window.partitionBy("run").orderBy("step")
    return trace.withColumns({"hit_rate": F.avg(F.col("hit").cast("int")).over(by.rowsBetween(1 - window, 0)), "hits": F.sum(F.col("hit").cast("int")).over(by.rowsBetween(Window.unboundedPreceding, 0))})


def curve_quartiles(curve: DataFrame) -> DataFrame:
    return curve.groupBy("step").agg(*(F.percentile("hit_rate", F.lit(q)).alias(n) for n, q in (("q25", 0.25), ("median", 0.5), ("q75", 0.75))))


def box(df: DataFrame, col: str, by: str) -> DataFrame:
    c = F.col(col)
    return df.groupBy(by).agg(F.min(c).alias("least"), *(F.percentile(c, F.lit(q)).alias(f"q{int(100 * q)}") for q in (0.25, 0.5, 0.75)), F.max(c).alias("most"), F.avg(c).alias("mean"), F.var_samp(c).alias("variance"))


def emd(left: list[tuple[str, float]], right: list[tuple[str, float]], distance: Callable[[str, str], float]) -> float:
    """Least cost of moving one list's normalised masses onto the other's, by successive shortest paths; small lists only."""
    left, right = [(a, m) for a, m in left if m > 0], [(b, m) for b, m in right if m > 0]
    if not left or not right:
        return 0.0 if not left and not right else 1.0
    supply = [m / sum(m for _, m in left) for _, m in left]
    demand = [m / sum(m for _, m in right) for _, m in right]
    cost = [[distance(a, b) for b, _ in right] for a, _ in left]
    n, m = len(left), len(right)
    flow = [[0.0] * m for _ in range(n)]
    total = 0.0
    while True:
        best = [0.0 if s > 1e-12 else float("inf") for s in supply] + [float("inf")] * m
        back = [-1] * (n + m)
        for _ in range(n + m):
            moved = False
            for i in range(n):
                for j in range(m):
                    if best[i] + cost[i][j] < best[n + j] - 1e-15:
                        best[n + j], back[n + j], moved = best[i] + cost[i][j], i, True
                    if flow[i][j] > 1e-15 and best[n + j] - cost[i][j] < best[i] - 1e-15:
                        best[i], back[i], moved = best[n + j] - cost[i][j], n + j, True
            if not moved:
                break
        ends = [j for j in range(m) if demand[j] > 1e-12 and best[n + j] < float("inf")]
        if not ends:
            return total
        j = min(ends, key=lambda j: best[n + j])
        path, at = [], n + j
        while back[at] >= 0:
            path.append((back[at], at))
            at = back[at]
        amount = min([supply[at], demand[j]] + [flow[b][a - n] for a, b in path if a >= n])
        for a, b in path:
            if a < n:
                flow[a][b - n] += amount
                total += amount * cost[a][b - n]
            else:
                flow[b][a - n] -= amount
                total -= amount * cost[b][a - n]
        supply[at] -= amount
        demand[j] -= amount


def repeat(run: Callable[[int], float | None], seeds=range(8)) -> tuple[float, float, list]:
    """Mean and sample standard deviation of a measure over seeds, and the values; nulls do not count."""
    got = [x for x in map(run, seeds) if x is not None]
    mean = sum(got) / len(got) if got else float("nan")
    return mean, (sum((x - mean) ** 2 for x in got) / (len(got) - 1)) ** 0.5 if len(got) > 1 else 0.0, got


class Spans:
    """Seconds by stage: `with spans("judge"): ...`; a stage's spans add up."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def __call__(self, stage: str):
        start = time.time()
        try:
            yield
        finally:
            self.seconds[stage] = self.seconds.get(stage, 0.0) + time.time() - start


def label_distance(a: str, b: str) -> float:
    """1 - cosine of two labels' counts of neighbouring letters."""
    one, two = (Counter(zip(x.lower(), x.lower()[1:])) if len(x) > 1 else Counter(x.lower()) for x in (a, b))
    norm = (sum(v * v for v in one.values()) * sum(v * v for v in two.values())) ** 0.5
    return 1.0 - sum(v * two[k] for k, v in one.items()) / norm if norm else float(a != b)


def kappa(a: Column, b: Column) -> tuple[Column, Column]:
    """Agreement of two boolean answers: the share of equal ones, and what chance would give."""
    pa, pb = F.avg(a.cast("int")), F.avg(b.cast("int"))
    return F.avg((a == b).cast("int")), pa * pb + (1 - pa) * (1 - pb)
