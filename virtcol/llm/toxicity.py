"""Toxicity by FTRL-proximal logistic regression on hashed n-grams and skip-grams.

A text's features are the set of its words, of pairs of neighbours, of pairs
one word apart and of the words' stems (first STEM letters), hashed into BINS
bins.  Training takes a bounded sample
of labelled rows (SAMPLE, the first by a hash of the id), one at a time, with a
learning rate per bin and an L1 pull that keeps most weights at zero; the
nonzero ones are broadcast.  Every text is scored whole.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import add_columns, arrow_pass, documents, text_or_empty

BITS = 20
BINS = 1 << BITS
SAMPLE = 6_000
EPOCHS = 3
THRESHOLD = 0.3
STEM = 5
EDGES = b".,;:!?'\"()[]{}<>|*$%&#@^~_+=/\\-"


class Features:
    """Bins of texts; a word is lower-cased (A-Z) and loses punctuation at its ends."""

    MOST = 500_000

    def __init__(self):
        from xxhash import xxh64_intdigest

        self.hash, self.known = xxh64_intdigest, {}

    def words(self, text: bytes) -> np.ndarray:
        """Hashes of the words and of their stems."""
        known, words = self.known, text.lower().split()
        if len(known) > self.MOST:
            known.clear()
        try:
            return np.array([known[w] for w in words], np.uint64).reshape(-1, 2)
        except KeyError:
            for w in words:
                if w not in known:
                    bare = w.strip(EDGES) or w
                    known[w] = (self.hash(bare, 11), self.hash(bare.decode("utf-8", "replace")[:STEM].encode(), 13))
            return np.array([known[w] for w in words], np.uint64).reshape(-1, 2)

    def bins(self, text: bytes) -> np.ndarray:
        """All bins, repeats included; a constant one comes first."""
        both = self.words(text)
        w, stems = both[:, 0], both[:, 1]
        near = (w[:-1] * np.uint64(0x9E3779B97F4A7C15)) ^ (w[1:] + np.uint64(0xA0761D6478BD642F))
        apart = (w[:-2] * np.uint64(0xE7037ED1A0B428DB)) ^ (w[2:] + np.uint64(0x8EBC6AF09C88C6E3))
        mixed = np.concatenate((w, near, apart, stems)) * np.uint64(0xD6E8FEB86659FD93)
        return np.concatenate(([0], (mixed >> np.uint64(64 - BITS)).astype(np.int64)))


def train(rows: list[tuple[np.ndarray, int]], alpha: float = 0.5, beta: float = 1.0, l1: float = 5.0, l2: float = 0.5, epochs: int = EPOCHS) -> np.ndarray:
    """Weights of all bins after some passes over (distinct bins, label) rows in the given order."""
    z, n = np.zeros(BINS), np.zeros(BINS)

    def weights(at):
        zi = z[at]
        return np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(n[at])) / alpha + l2))

    for _ in range(epochs):
        for at, y in rows:
            w = weights(at)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -35, 35))) - y
            root = np.sqrt(n[at])
            z[at] += g - (np.sqrt(n[at] + g * g) - root) / alpha * w
            n[at] += g * g
    return weights(slice(None))


def held_out(id_col: str) -> F.Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> np.ndarray:
    """Weights from labelled rows that are not held out: at most `sample` ids, whose features (not texts) come to the driver."""
    usable = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id"))
    known = usable.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).collect()
    shared = docs.sparkSession.sparkContext.broadcast({r[0]: r[1] for r in known})
    ids = docs.sparkSession.createDataFrame([(r[0],) for r in known], "__id long")

    def make():
        features = Features()

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            keys = b.column(0).to_pylist()
            bins = [np.unique(features.bins(t)).astype("<i4").tobytes() for t in b.column(1).cast(pa.binary()).to_pylist()]
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(bins, pa.binary())], names=["id", "bins"])

        return each

    chosen = docs.select(F.col(id_col), text_or_empty(text_col)).join(F.broadcast(ids), F.col(id_col) == F.col("__id"), "left_semi")
    rows = sorted((r["id"], bytes(r["bins"])) for r in arrow_pass(chosen, "id long, bins binary", make).collect())
    return train([(np.frombuffer(b, "<i4"), shared.value[i]) for i, b in rows])


def score(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD, text_col: str = "text", drop: tuple[str, ...] = ()) -> DataFrame:
    """docs, without the columns in `drop`, with score (0 to 1) and predicted. Null and empty texts score what the constant alone gives."""
    at = np.flatnonzero(weights)
    shared = docs.sparkSession.sparkContext.broadcast((at, weights[at]))

    def make():
        features, table = Features(), np.zeros(BINS)
        table[shared.value[0]] = shared.value[1]
        heavy = table != 0

        def one(text: bytes) -> float:
            bins = features.bins(text)
            bins = np.unique(bins[heavy[bins]])
            return float(1.0 / (1.0 + np.exp(-np.clip(table[bins].sum(), -35, 35))))

        def work(texts: list[bytes]) -> list:
            s = [one(t) for t in texts]
            return [s, [int(x >= threshold) for x in s]]

        return work

    return add_columns(docs, text_col, "score double, predicted int", make, drop=drop)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    weights = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, weights, drop=("text",)).select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")
