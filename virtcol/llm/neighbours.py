"""Nearest neighbours: coarse cells, product-quantised residuals, exact reranking, bounds on what is left out.

Cells are k-means centroids fitted on a bounded sample; every vector is put in
its cell and its residual is coded by one byte per group of dimensions, with
the length of what the code misses beside it.  A query first visits its best
cells, then every other cell whose radius does not rule it out; there the
distance of every vector is read from the query's tables (asymmetric), and the
best are measured again on the original vectors in double precision, as is any
other vector that code and miss do not rule out.  So the sample decides the
work alone, never the result.  Vectors and queries meet in blocks of bounded
size, so a crowded cell becomes many tasks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, arrow_pass

SAMPLE = 20_000
CELLS = 32
PROBES = 22
GROUPS = 16
RERANK = 200
VECTORS_A_BLOCK = 4_096
QUERIES_A_BLOCK = 2_048


def kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 12) -> np.ndarray:
    """Plain Lloyd centroids of distinct rows; no more than there are."""
    rows = np.unique(x, axis=0)
    rng = np.random.default_rng(seed)
    c = rows[rng.permutation(len(rows))[:k]].astype(np.float32)
    for _ in range(rounds):
        near = np.argmin((c * c).sum(1)[None, :] - 2 * x @ c.T, axis=1)
        sums = np.zeros(c.shape)
        np.add.at(sums, near, x)
        n = np.bincount(near, minlength=len(c))
        c[n > 0] = (sums[n > 0] / n[n > 0, None]).astype(np.float32)
    return c


class Index:
    """Centroids and codebooks; their size is fixed by the parameters."""

    def __init__(self, sample: np.ndarray, cells: int, groups: int, seed: int = 7):
        self.dim = sample.shape[1]
        self.cells = kmeans(sample, cells, seed)
        self.cuts = np.array_split(np.arange(self.dim), min(groups, self.dim))
        rest = sample - self.cells[self.cell(sample)]
        self.books = [kmeans(np.ascontiguousarray(rest[:, g]), 256, seed + 1 + i, 8) for i, g in enumerate(self.cuts)]

    def cell(self, x: np.ndarray) -> np.ndarray:
        return np.argmin((self.cells * self.cells).sum(1)[None, :] - 2 * x @ self.cells.T, axis=1)

    def code(self, x: np.ndarray, cell: np.ndarray) -> np.ndarray:
        rest = x - self.cells[cell]
        return np.stack([np.argmin((b * b).sum(1)[None, :] - 2 * rest[:, g] @ b.T, axis=1) for g, b in zip(self.cuts, self.books)], axis=1).astype(np.uint8)

    def miss(self, x: np.ndarray, cell: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distances, in double precision, of vectors to their centroid and to what centroid and code say."""
        rest = x - self.cells[cell].astype(np.float64)
        far = np.sqrt((rest * rest).sum(1))
        for g, (cut, book) in enumerate(zip(self.cuts, self.books)):
            rest[:, cut] -= book[codes[:, g]]
        return far, np.sqrt((rest * rest).sum(1))

    def tables(self, q: np.ndarray, cell: int) -> list[np.ndarray]:
        """For each group, squared distances of every query's residual in a cell to its codebook; never a difference of large numbers."""
        rest = q - self.cells[cell].astype(np.float64)
        return [((rest[:, g][:, None, :] - b[None].astype(np.float64)) ** 2).sum(2).astype(np.float32) for g, b in zip(self.cuts, self.books)]


def matrix(col: pa.Array) -> np.ndarray:
    """Rows of a list column as a matrix of doubles."""
    flat = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(col), -1) if len(col) else flat.reshape(0, 0)


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows times powers of two, so that squares neither overflow nor vanish; cosines keep every bit."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1]) if x.size else x


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length one, in double precision."""
    x = scaled(x)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def slack(dim: int) -> float:
    """More than rounding can change a squared distance of unit vectors."""
    return 1e-12 + 1e-15 * dim


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(vec_id, embedding) of rows that take part: not null, of the commonest length, all components finite numbers, not all zero; null ids take no part."""
    v = F.col(vec_col)
    fine = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    good = vectors.where(fine & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), v.cast("array<double>").alias("embedding"))
    top = good.groupBy(F.size("embedding").alias("n")).count().orderBy(F.desc("count"), "n").first()
    return good.where(F.size("embedding") == (top[0] if top else 0))


def nearest(vectors: DataFrame, every: int = 50, k: int = 5, cells: int = CELLS, probes: int = PROBES, groups: int = GROUPS, rerank: int = RERANK, sample: int = SAMPLE, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest by cosine of each row whose id is divisible by `every`.

    A query's own row is no candidate for it (nor are rows that repeat its id); ties go to the smaller id.  Rows that
    cannot be measured take no part.  `probes` cells come first (more, if they hold too few candidates); their k-th best
    rules out other cells, or does not.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "neighbours")
    good = usable(vectors, id_col, vec_col)
    schema = "query_id long, rank int, vec_id long, score double"
    first = good.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toArrow()
    if not first.num_rows:
        return spark.createDataFrame([], schema)
    index = Index(unit(matrix(first.column("embedding").combine_chunks())).astype(np.float32), max(1, min(cells, first.num_rows // 40)), groups)
    shared = spark.sparkContext.broadcast(index)

    def coder():
        ix = shared.value

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            x = unit(matrix(b.column(1)))
            cell, codes, far, miss = np.zeros(0, np.int64), np.zeros((0, 1), np.uint8), np.zeros(0), np.zeros(0)
            if len(x):
                cell = ix.cell(x.astype(np.float32))
                codes = ix.code(x.astype(np.float32), cell)
                far, miss = ix.miss(x, cell, codes)
            return pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell, pa.int32()), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(far), pa.array(miss)], names=["vec_id", "embedding", "cell", "codes", "far", "miss"])

        return each

    coded = scratch.keep(arrow_pass(good, "vec_id long, embedding array<double>, cell int, codes binary, far double, miss double", coder), "coded")
    cells_in = {r[0]: (r[1], r[2]) for r in coded.groupBy("cell").agg(F.count("*"), F.max("far")).collect()}  # a row per cell
    filled = {c: n for c, (n, _) in cells_in.items()}
    n_queries = coded.where(F.col("vec_id") % every == 0).count()
    q_blocks = max(1, -(-n_queries // QUERIES_A_BLOCK))
    blocks = spark.sparkContext.broadcast({c: max(1, -(-n // VECTORS_A_BLOCK)) for c, n in filled.items()})
    counts = spark.sparkContext.broadcast(cells_in)

    def prober():
        ix = shared.value
        n_in, radius = (np.array([counts.value.get(c, (0, 0.0))[i] for c in range(len(ix.cells))]) for i in (0, 1))

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            x, probe = unit(matrix(b.column(1))), []
            for q, least in zip(x, b.column(2).to_pylist()):
                rest = q - ix.cells.astype(np.float64)
                far = np.sqrt((rest * rest).sum(1))
                order = np.argsort(far, kind="stable")
                need = max(probes, int((np.cumsum(n_in[order]) < 4 * k + 1).sum()) + 1)
                if least is None:  # the first visit
                    probe.append(order[:need].tolist())
                else:  # cells that were not visited and may hold a vector at `least` or better
                    left = order[need:]
                    probe.append(left[np.maximum(far[left] - radius[left] - 1e-12, 0.0) ** 2 <= 2 - 2 * least + slack(ix.dim)].tolist())
            return pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(probe, pa.list_(pa.int32()))], names=["query_id", "query", "least", "probe"])

        return each

    spread = F.create_map(*(F.lit(x) for c, n in blocks.value.items() for x in (c, n)))
    asking = coded.where(F.col("vec_id") % every == 0).select("vec_id", "embedding")

    def asked(queries: DataFrame) -> DataFrame:
        return (
            arrow_pass(queries, "query_id long, query array<double>, least double, probe array<int>", prober)
            .select("query_id", "query", "least", F.pmod(F.xxhash64("query_id"), F.lit(q_blocks)).cast("int").alias("part"), F.explode("probe").alias("cell"))
            .where(spread[F.col("cell")].isNotNull())
            .select("query_id", "query", "least", "part", "cell", F.explode(F.sequence(F.lit(0), spread[F.col("cell")] - 1)).alias("block"))
        )

    stored = coded.select("vec_id", "embedding", "codes", "miss", "cell", F.pmod(F.xxhash64("vec_id"), spread[F.col("cell")]).cast("int").alias("block"), F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))).alias("part"))

    def meet(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        ix = shared.value
        empty = pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not left.num_rows or not right.num_rows:
            return empty
        right = right.sort_by("vec_id")
        q, x = scaled(matrix(left.column("query").combine_chunks())), scaled(matrix(right.column("embedding").combine_chunks()))
        q_id, x_id, miss = left.column("query_id").to_numpy(), right.column("vec_id").to_numpy(), right.column("miss").to_numpy()
        least = left.column("least").to_numpy(zero_copy_only=False).astype(np.float64)  # null: not a number
        codes = np.frombuffer(b"".join(right.column("codes").to_pylist()), np.uint8).reshape(len(x), -1)
        q_len, x_len = np.sqrt((q * q).sum(1)), np.sqrt((x * x).sum(1))
        x_unit = x / x_len[:, None]
        out: list[tuple[int, int, float]] = []
        for at in range(0, len(q), 128):
            part = slice(at, at + 128)
            q_unit = q[part] / q_len[part, None]
            near = np.zeros((len(q_unit), len(x)), np.float32)
            for g, t in enumerate(ix.tables(q_unit, key[0].as_py())):
                near += t[:, codes[:, g]]
            cosine = None
            for i, row in enumerate(near):
                m = min(rerank + 1, len(x)) - 1
                best = np.flatnonzero(row <= np.partition(row, m)[m])  # ties at the cut stay
                best = best[x_id[best] != q_id[i + at]]
                rough = x_unit[best] @ q_unit[i]
                if m + 1 < len(x):  # what codes and their misses do not rule out is measured too
                    worst = max(np.partition(rough, len(rough) - k)[len(rough) - k] if len(rough) >= k else -1.0, least[i + at] if least[i + at] == least[i + at] else -1.0)
                    reach = (np.sqrt(2 - 2 * worst + slack(ix.dim)) + miss + 1e-12) * (1 + 1e-5)
                    more = np.flatnonzero((row <= reach * reach) & (x_id != q_id[i + at]))
                    if len(more) * 8 > len(x):
                        cosine = q_unit @ x_unit.T if cosine is None else cosine
                        best, rough = more, cosine[i, more]
                    else:
                        best, rough = more, x_unit[more] @ q_unit[i]
                if len(rough) > k:
                    top = rough >= np.partition(rough, len(rough) - k)[len(rough) - k] - slack(ix.dim)
                    best = best[top]
                exact = (x[best] * q[i + at]).sum(1) / (x_len[best] * q_len[i + at])  # row by row alike, so equal vectors tie
                for j in np.lexsort((x_id[best], -exact))[:k]:
                    out.append((int(q_id[i + at]), int(x_id[best[j]]), float(exact[j])))
        a, b, c = zip(*out) if out else ((), (), ())
        return pa.table({"query_id": pa.array(a, pa.int64()), "vec_id": pa.array(b, pa.int64()), "score": pa.array(c, pa.float64())})

    keys = ["cell", "block", "part"]
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")

    def visit(queries: DataFrame, name: str) -> DataFrame:
        return scratch.keep(asked(queries).groupBy(*keys).cogroup(stored.groupBy(*keys)).applyInArrow(meet, "query_id long, vec_id long, score double"), name)

    def ranked(found: DataFrame) -> DataFrame:
        return found.distinct().withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

    found = visit(asking.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("query"), F.lit(None).cast("double").alias("least")), "first")
    least = ranked(found).groupBy("query_id").agg(F.count("*").alias("n"), F.min("score").alias("score")).select(F.col("query_id").alias("vec_id"), F.when(F.col("n") >= k, F.col("score")).otherwise(-1.0).alias("least"))
    again = asking.join(least, "vec_id", "left").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("query"), F.coalesce("least", F.lit(-1.0)).alias("least"))
    return ranked(found.union(visit(again, "rest")))


def op10_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
