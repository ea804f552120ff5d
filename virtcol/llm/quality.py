"""Quality rules and a hashed n-gram log-likelihood ratio.

Words and word pairs are hashed into a fixed number of bins.  The trusted
target's and the raw corpus's bin counts make two smoothed multinomials; a
document's score is the mean over its n-grams of the log ratio between them.
Raw counts cover every document.  The target is the labelled good documents,
of which at most `trusted` are used, the first by a hash of their id.  The
threshold is the score below which the fraction `lost` of all labelled good
documents that pass the base rules lies.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, add_columns, arrow_pass, documents, text_or_empty

BINS = 1 << 16
TRUSTED = 20_000
LOST = 0.001
SYMBOLS = b"#*$%&|<>"
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
SPAN = 8


class Grams:
    """Words of texts as numbers, and their n-grams' bins."""

    MOST = 500_000

    def __init__(self):
        from xxhash import xxh64_intdigest

        self.hash, self.known = xxh64_intdigest, {}

    def words(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        if len(known) > self.MOST:
            known.clear()
        try:
            return np.array([known[w] for w in words], np.uint64)
        except KeyError:
            for w in words:
                if w not in known:
                    known[w] = self.hash(w, 7)
            return np.array([known[w] for w in words], np.uint64)

    def bins(self, words: np.ndarray) -> np.ndarray:
        """Bins of words and of pairs of neighbours."""
        pairs = (words[:-1] * np.uint64(0x9E3779B97F4A7C15)) ^ (words[1:] + np.uint64(0x632BE59BD9B4E019))
        both = np.concatenate((words, pairs)) * np.uint64(0xD6E8FEB86659FD93)
        return (both >> np.uint64(64 - BINS.bit_length() + 1)).astype(np.int64)


def repeated_words(codes: np.ndarray) -> int:
    """Words that lie in a window of SPAN words found twice or more in the text; words are told apart by 64-bit hashes, windows by a 64-bit mix of them."""
    n = len(codes) - SPAN + 1
    if n < 2:
        return 0
    mix = codes[:n] * np.uint64(0x9E3779B97F4A7C15)
    for k in range(1, SPAN):
        mix = (mix ^ (mix >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) + codes[k : n + k]
    order = np.argsort(mix, kind="stable")
    same = mix[order][1:] == mix[order][:-1]
    if not same.any():
        return 0
    starts = np.zeros(n, bool)
    starts[order[1:][same]] = True
    starts[order[:-1][same]] = True
    edge = np.zeros(len(codes) + 1, np.int64)
    np.add.at(edge, np.flatnonzero(starts), 1)
    np.add.at(edge, np.flatnonzero(starts) + SPAN, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def stats(text: bytes, words: list[bytes], codes: np.ndarray) -> tuple[int, int, int, int, int]:
    """Of a UTF-8 text: words, their code points, symbols, lines with a word that equal an earlier one, words in repeated windows."""
    joined = b"".join(words)
    chars = len(joined) if joined.isascii() else len(joined.decode("utf-8", "replace"))
    symbols = len(text) - len(text.translate(None, SYMBOLS))
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    return len(words), chars, symbols, len(lines) - len(set(lines)), repeated_words(codes)


def base_failed(n_words: int, n_repeat_words: int) -> bool:
    return n_words < 20 or 100 * n_repeat_words > 30 * n_words


def trusted_ids(labels: DataFrame, most: int = TRUSTED) -> list[int]:
    """Ids labelled good: at most so many, the first by a hash of the id."""
    rows = labels.where("quality = 1 AND doc_id IS NOT NULL").select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(most).collect()
    return [r[0] for r in rows]


def counts(docs: DataFrame, trusted: list[int], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(bin, raw, target): n-gram counts over all documents and over the trusted ones; a task adds its own up first."""
    shared = docs.sparkSession.sparkContext.broadcast(frozenset(trusted))

    def make():
        grams, total = Grams(), np.zeros((2, BINS), np.int64)

        def each(b: pa.RecordBatch):
            for i, t in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist()):
                got = np.bincount(grams.bins(grams.words(t.split())), minlength=BINS)
                total[0] += got
                if i in shared.value:
                    total[1] += got
            return ()

        def end():
            at = np.flatnonzero(total[0])
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[0, at]), pa.array(total[1, at])], names=["bin", "raw", "target"])

        each.end = end
        return each

    out = arrow_pass(docs.select(F.col(id_col), text_or_empty(text_col)), "bin long, raw long, target long", make)
    return out.groupBy("bin").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target"))


def ratios(rows: list) -> np.ndarray:
    """Log ratio of target to raw for each bin, both smoothed by half a count; zeros if there is no target."""
    raw, target = np.zeros(BINS), np.zeros(BINS)
    for b, r, t in rows:
        raw[b], target[b] = r, t
    if not target.any():
        return np.zeros(BINS, np.float32)
    smooth = lambda x: np.log((x + 0.5) / (x.sum() + 0.5 * BINS))
    return (smooth(target) - smooth(raw)).astype(np.float32)


def score(docs: DataFrame, model: np.ndarray, text_col: str = "text", drop: tuple[str, ...] = ()) -> DataFrame:
    """docs, without the columns in `drop`, with the base statistics, base_failed and llr, the mean log ratio (0 for a text without words)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        grams, table = Grams(), shared.value

        def work(texts: list[bytes]) -> list:
            rows = []
            for t in texts:
                words = t.split()
                codes = grams.words(words)
                got = stats(t, words, codes)
                rows.append((*got, base_failed(got[0], got[4]), float(table[grams.bins(codes)].mean(dtype=np.float64)) if words else 0.0))
            return list(zip(*rows)) if rows else [[]] * 7

        return work

    return add_columns(docs, text_col, ", ".join(f"{s} long" for s in STATS) + ", base_failed boolean, llr double", make, drop=drop)


def threshold(scored: DataFrame, labels: DataFrame, lost: float, id_col: str = "doc_id") -> float:
    """The percentile, between neighbours in proportion, over all labelled good documents that pass the base rules; only its share of the least scores is sorted out.

    Ids and scores alone are joined to the labels.
    """
    good = labels.where("quality = 1 AND doc_id IS NOT NULL").select(F.col("doc_id").alias("__good")).distinct()
    passed = scored.where(~F.col("base_failed")).select(F.col(id_col).alias("__id"), "llr")
    scratch = Scratch(scored.sparkSession, "quality")
    scores = scratch.keep(passed.join(good, F.col("__id") == F.col("__good"), "left_semi").select("llr"), "good")
    n = scores.count()
    if not n:
        return float("-inf")
    low, part = divmod(lost * (n - 1), 1)
    least = [r[0] for r in scores.orderBy("llr").limit(int(low) + 2).collect()[int(low) :]]
    scratch.drop(scores)
    return least[0] + part * (least[-1] - least[0])


def judge(docs: DataFrame, labels: DataFrame, trusted: int = TRUSTED, lost: float = LOST, id_col: str = "doc_id", text_col: str = "text", drop: tuple[str, ...] = ()) -> DataFrame:
    """docs, without the columns in `drop`, with the statistics, llr and kept: false if base_failed, else whether llr reaches the threshold.

    Null texts are empty and fail the base rules.  Equal rows get equal verdicts; columns with the result's names are replaced.
    Without labelled good documents the ratio is 0 and only the base rules reject.  Every document is scored once and written.
    """
    ids = trusted_ids(labels, trusted)
    model = ratios(counts(docs, ids, id_col, text_col).collect())  # at most BINS rows
    scored = Scratch(docs.sparkSession, "quality").keep(score(docs, model, text_col, drop), "scored")
    cut = threshold(scored, labels, lost, id_col)
    return scored.withColumn("kept", ~F.col("base_failed") & (F.col("llr") >= F.lit(cut)))


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = judge(documents(spark, sf_dir).select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet"), drop=("text",))
    return out.select("doc_id", *STATS, "base_failed", "kept", "llr")
