"""Row features and strata."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hashed_words(text: Column, width: int = 256) -> Column:
    """A text's signed word-hash vector of length one (zeros for a text without words)."""

    @F.pandas_udf("array<float>")
    def embed(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        from zlib import crc32

        for s in batches:
            out = []
            for t in s:
                h = np.array([crc32(w.encode()) for w in (t or "").lower().split()], np.int64)
                v = np.bincount(h % width, weights=1.0 - 2.0 * ((h >> 16) & 1), minlength=width) if len(h) else np.zeros(width)
                n = np.sqrt((v * v).sum())
                out.append((v / n if n else v).astype(np.float32))
            yield pd.Series(out)

    return embed(text)


def hashed_char_ngrams(text: Column, n: int = 3, width: int = 256) -> Column:
    """The same over character n-grams."""

    @F.pandas_udf("array<float>")
    def embed(s: pd.Series) -> pd.Series:
        from zlib import crc32

        def one(t):
            b = (t or "").lower().encode()
            h = np.array([crc32(b[i : i + n]) for i in range(len(b) - n + 1)], np.int64)
            v = np.bincount(h % width, weights=1.0 - 2.0 * ((h >> 16) & 1), minlength=width) if len(h) else np.zeros(width)
            m = np.sqrt((v * v).sum())
            return (v / m if m else v).astype(np.float32)

        return s.map(one)

    return embed(text)


def build_features(df: DataFrame, id_col: str, source: str, embedder: str = "hashed_words", width: int = 256, fn=None) -> DataFrame:
    """(id, e): one vector per row; `given` takes a stored vector column, `callable` a function from a pandas Series to vectors."""
    col = F.col(source)
    e = {"hashed_words": lambda: hashed_words(col, width), "hashed_char_ngrams": lambda: hashed_char_ngrams(col, 3, width), "given": lambda: col.cast("array<float>"), "callable": lambda: F.pandas_udf(fn, "array<float>")(col)}[embedder]()
    return df.select(F.col(id_col).alias("id"), e.alias("e"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def nearest_anchor(vectors: DataFrame, anchors: list[tuple[int, list[float]]], id_col: str, vec_col: str) -> DataFrame:
    """(id, stratum): the anchor with the largest product, ties to the smaller anchor id. The anchors are a parameter, so their number is small."""
    scored = F.array(*(F.struct(dot(F.col(vec_col), F.lit([float(x) for x in v])).alias("s"), F.lit(-i).alias("i")) for i, v in anchors))
    return vectors.select(F.col(id_col).alias("id"), (-F.array_max(scored)["i"]).alias("stratum"))


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.argmin((c * c).sum(1) - 2 * x @ c.T, axis=1)


def lloyd(x: np.ndarray, k: int, seed: int = 0, rounds: int = 20) -> np.ndarray:
    """At most k centroids of the rows of x, by k-means from distinct rows."""
    rng = np.random.default_rng(seed)
    first, picked = set(), []
    for i in rng.permutation(len(x)):  # k distinct rows; a zero has one sign
        key = (x[i] + 0.0).tobytes()
        if key not in first:
            first.add(key)
            picked.append(i)
        if len(picked) == k:
            break
    c, last = x[picked], None
    for _ in range(rounds if len(c) else 0):
        near = nearest(x, c)
        if last is not None and (near == last).all():
            break
        last, n = near, np.bincount(near, minlength=len(c))
        s = (near == np.arange(len(c))[:, None]).astype(np.float32) @ x
        c[n > 0] = s[n > 0] / n[n > 0, None]
    return c


def best_of(x: np.ndarray, k: int, seed: int = 0, starts: int = 8) -> np.ndarray:
    """lloyd() from several starts: the centroids with the least squared distances, the first such."""
    fits = [lloyd(x, k, s) for s in range(seed, seed + starts)]
    return min(fits, key=lambda c: float(((x - c[nearest(x, c)]) ** 2).sum())) if len(x) else fits[0]


def drawn(features: DataFrame, seed: int, sample: int) -> np.ndarray:
    """The vectors of at most `sample` rows, the first by a hash of the id."""
    rows = features.orderBy(F.xxhash64(F.lit(seed), F.col("id")), "id").limit(sample).select("e").toArrow().to_pandas()["e"]
    return np.array(rows.tolist(), np.float32) if len(rows) else np.zeros((0, 1), np.float32)


def fit_kmeans(features: DataFrame, k: int, seed: int = 0, sample: int = 20_000, rounds: int = 20) -> np.ndarray:
    """Centroids from at most `sample` rows (the first by a hash of the id)."""
    return lloyd(drawn(features, seed, sample), k, seed, rounds)


def assign(features: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(id, stratum) by nearest centroid: map only, the centroids travel with the task."""

    @F.pandas_udf("int")
    def near(e: pd.Series) -> pd.Series:
        x = np.array(e.tolist(), np.float32).reshape(len(e), -1)
        return pd.Series(np.argmin((centroids * centroids).sum(1) - 2 * x @ centroids.T, axis=1).astype(np.int32)) if len(e) else pd.Series([], dtype="int32")

    return features.select("id", near("e").alias("stratum"))


def two_level(features: DataFrame, k: int, k2: int, seed: int = 0, sample: int = 20_000) -> DataFrame:
    """(id, stratum): k coarse cells and within each at most k2 fine ones of its own; a row is compared with k + k2 centroids, not k * k2. Strata are numbered cell * k2 + fine."""
    x = drawn(features, seed, sample)
    coarse = best_of(x, k, seed)
    cell = nearest(x, coarse) if len(coarse) else np.zeros(0, int)
    fine = [lloyd(x[cell == c], k2, seed + 1 + c) for c in range(len(coarse))]

    @F.pandas_udf("int")
    def near(e: pd.Series) -> pd.Series:
        if not len(e):
            return pd.Series([], dtype="int32")
        v = np.array(e.tolist(), np.float32).reshape(len(e), -1)
        at = nearest(v, coarse)
        out = at * k2
        for c in np.unique(at):
            if len(fine[c]):
                out[at == c] += nearest(v[at == c], fine[c])
        return pd.Series(out.astype(np.int32))

    return features.select("id", near("e").alias("stratum"))


def silhouette(x: np.ndarray, label: np.ndarray) -> float:
    """Simplified: own centroid against the nearest other."""
    c = np.stack([x[label == k].mean(axis=0) for k in np.unique(label)])
    d = np.sqrt(np.maximum((x * x).sum(1)[:, None] + (c * c).sum(1) - 2 * x @ c.T, 0))
    d.sort(axis=1)
    return float(((d[:, 1] - d[:, 0]) / np.maximum(d[:, 1], 1e-9)).mean()) if len(c) > 1 else -1.0


def assign_strata(features: DataFrame, method: str = "kmeans", k: int = 10, seed: int = 0, **options) -> DataFrame:
    """(id, stratum) by kmeans, auto_k (k from `range` by silhouette on a subsample), two_level, anchors, column or single."""
    if method == "single":
        return features.select("id", F.lit(0).alias("stratum"))
    if method == "column":
        return features.select("id", F.col(options["column"]).alias("stratum"))
    if method == "anchors":
        return nearest_anchor(features, options["anchors"], "id", "e")
    if method == "auto_k":
        x = np.array(features.orderBy(F.xxhash64("id")).limit(2_000).toPandas()["e"].tolist(), np.float32)
        fits = [(silhouette(x, np.argmin((c * c).sum(1) - 2 * x @ c.T, axis=1)), -n, c) for n in options.get("range", (4, 8, 16)) for c in [fit_kmeans(features, n, seed)]]
        return assign(features, max(fits, key=lambda f: f[:2])[2])
    if method == "two_level":
        return two_level(features, k, options.get("k2", 10), seed)
    return assign(features, fit_kmeans(features, k, seed))


def manifest(strata: DataFrame) -> DataFrame:
    return strata.groupBy("stratum").agg(F.count("*").alias("n_rows"))
