"""Row search by active learning under a budget of calls."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 1.0) -> np.ndarray:
    """Weights and intercept that minimise mean log-loss plus l2/(2n) of the squared weights, by Newton steps."""
    n, d = x.shape
    x1 = np.concatenate((x, np.ones((n, 1))), axis=1).astype(np.float64)
    w, pull = np.zeros(d + 1), np.concatenate((np.full(d, l2 / n), [0.0]))
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w, -35, 35)))
        g = x1.T @ (p - y) / n + pull * w
        if np.abs(g).max() < 1e-6:
            break
        h = (x1 * (p * (1 - p))[:, None]).T @ x1 / n + np.diag(pull + 1e-9)
        w -= np.linalg.solve(h, g)
    return w


def mean_difference(x: np.ndarray, y: np.ndarray, l2: float = 1.0) -> np.ndarray:
    return np.concatenate((x[y == 1].mean(axis=0) - x[y == 0].mean(axis=0), [0.0]))


SURROGATES = {"logistic": logistic, "mean_difference": mean_difference}


def uniform(id_col: str, *salt) -> Column:
    """A number in [0, 1) fixed by the id and the salt."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(":".join(map(str, salt)) + ":"), F.col(id_col).cast("string")).cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0


@dataclass
class SearchResult:
    hits: list
    trace: list = field(default_factory=list)  # (round, id, score, hit, calls)


def decay(kind: str, t: int, tau: float = 8.0) -> float:
    return {"none": 0.0, "inverse_t": 1 / (1 + t), "exponential": float(np.exp(-t / tau))}[kind]


def active_search(features: DataFrame, judge, budget: int = 256, batch: int = 16, surrogate: str = "logistic", noise: float = 0.0, schedule: str = "inverse_t", limit: int | None = None, seed: int = 0, prior: np.ndarray | None = None, l2: float = 1.0, state: dict | None = None, pool: int | None = None, refresh: int = 4, tokens: str | None = None, token_budget: int | None = None) -> SearchResult:
    """Judges at most `budget` rows, each round the unseen ones that the surrogate ranks highest, and returns the positives.

    features: (id, e).  judge: list of ids -> list of bool.  Before one hit and one miss are known scores are seeded
    random numbers, or the product with `prior`.  Stops at `limit` hits.  Only ids, answers and weights are kept between
    rounds (pass `state` to resume); a round's plan is scan, product, top-k, so lineage does not grow.

    pool: so many of the best rows come to the driver with their vectors, and `refresh` rounds rank them there before the
    next scan of all rows (pool is a bound, at least `batch`).  tokens: a column of features with each row's length;
    the search ends before the rows judged would pass token_budget.
    """
    held, age, spent = None, 0, sum(state.get("tokens", {}).values()) if state else 0
    state = state if state is not None else {}
    seen: dict = state.setdefault("seen", {})
    rows: dict = state.setdefault("vectors", {})
    result = SearchResult([i for i, y in seen.items() if y], state.setdefault("trace", []))
    w, t = None, len(result.trace) and result.trace[-1][0] + 1
    while len(seen) < budget and (limit is None or len(result.hits) < limit):
        answers = set(seen.values())
        if answers == {True, False}:
            x = np.array([rows[i] for i in seen], np.float64)
            w = SURROGATES[surrogate](x, np.array([seen[i] for i in seen], np.float64), l2)[:-1]
        elif prior is not None:
            w = np.asarray(prior, np.float64)
        if w is None:
            score = uniform("id", seed, "start")
        else:
            weights = w.copy()

            @F.pandas_udf("double")
            def product(e: pd.Series) -> pd.Series:
                return pd.Series(np.array(e.tolist(), np.float64).reshape(len(e), -1) @ weights if len(e) else [], dtype="float64")

            score = product("e")
        if noise:
            score = score + F.lit(noise * decay(schedule, t)) * (2 * uniform("id", seed, t) - 1)
        want = min(batch, budget - len(seen))
        if held is not None and age < refresh and w is not None:
            x = np.array([r["e"] for r in held], np.float64)
            rank = x @ w if len(x) else np.zeros(0)
            best = sorted((i for i, r in enumerate(held) if r["id"] not in seen), key=lambda i: (-rank[i], held[i]["id"]))[:want]
            picked = [held[i].asDict() | {"score": rank[i]} for i in best]
            age += 1
        else:
            picked = []
        if not picked:
            open_ = features.where(~F.col("id").isin(list(seen))) if seen else features  # at most `budget` ids
            held = open_.withColumn("score", score).orderBy(F.desc("score"), "id").limit(max(want, pool or 0)).collect()
            picked, age = held[:want], 1
            if pool is None or w is None:
                held = None
        if token_budget is not None:
            costs = np.cumsum([int(r[tokens] or 0) for r in picked]) + spent
            picked = picked[: int((costs <= token_budget).sum())]
            spent = int(costs[len(picked) - 1]) if picked else spent
            state.setdefault("tokens", {}).update({r["id"]: int(r[tokens] or 0) for r in picked})
        if not picked:
            break
        for r, y in zip(picked, judge([r["id"] for r in picked])):
            seen[r["id"]], rows[r["id"]] = bool(y), r["e"]
            if y:
                result.hits.append(r["id"])
            result.trace.append((t, r["id"], float(r["score"]), bool(y), len(seen)))
        t += 1
    if limit is not None:
        result.hits = result.hits[:limit]
    return result


def ordered_probe(df: DataFrame, id_col: str, sort_col: str, judge, want: int = 1, batch: int = 64, descending: bool = True) -> list:
    """Ids of the first `want` rows in sort order that hold: exact, for MAX and MIN and for ORDER BY with LIMIT. Pages by key, so no page is read twice."""
    hits, last = [], None
    c = F.col(sort_col)
    base = df.where(c.isNotNull() & F.col(id_col).isNotNull())
    while len(hits) < want:
        page = base
        if last is not None:
            beyond = (c < last[0]) if descending else (c > last[0])
            page = page.where(beyond | ((c == last[0]) & (F.col(id_col) > last[1])))
        rows = page.select(id_col, sort_col).orderBy(c.desc() if descending else c.asc(), id_col).limit(batch).collect()
        if not rows:
            break
        hits += [r[0] for r, y in zip(rows, judge([r[0] for r in rows])) if y]
        last = (rows[-1][1], rows[-1][0])
    return hits[:want]
