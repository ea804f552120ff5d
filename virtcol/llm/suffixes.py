"""Repeated byte strings by a depth-limited radix sort of suffixes.

Only whether two suffixes agree on their first WIDTH bytes matters, so the sort
stops at that depth, and a group of one is never looked at again.  Passes go
from the most significant digit of a suffix's window to the whole of it:

1. the window's anchor, its least GRAM-byte string by a hash.  Neighbouring
   windows mostly share it, so a run of windows is one row.  Runs whose anchor
   occurs once are done; runs that recur as a whole are repeated throughout.
2. the bytes that all windows of a slice of a run have in common (a slice is
   STEP windows at a fixed place about the anchor), and the slice as a whole.
3. the windows themselves.

Equal windows have equal digits at each pass, so nothing is missed; a group is
never gathered anywhere, only counted, so its size does not matter.  Digits are
hashes: 128 bits where a match decides, 64 where it only admits to the next
pass.  Every pass is a scan of texts, a partial count and a join by key.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, arrow_pass, bounded_broadcast, documents, row_key, text_or_empty

WIDTH = 400
GRAM = 64
SLICES = 8
#: Windows handled at once; places in a block fit the low bits that break ties between equal hashes.
BLOCK = 1 << 19
LOW = (1 << 20) - 1
#: A digit that more rows share is told to them by a broadcast of at most MOST_HOT such digits.
HOT = 5_000
MOST_HOT = 500_000


class Anchors:
    """Runs of windows with the same anchor."""

    def __init__(self, width: int, gram: int):
        rng = np.random.default_rng(20)
        self.width, self.gram, self.reach = width, gram, width - gram + 1
        self.letters = rng.integers(1, 1 << 63, 256, dtype=np.uint64)
        base = int(rng.integers(1, 1 << 62)) * 2 + 1
        self.base, self.back = np.uint64(base), np.uint64(pow(base, -1, 1 << 64))
        self.up = self.down = np.ones(0, np.uint64)

    def powers(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            grow = lambda x: np.multiply.accumulate(np.concatenate((np.ones(1, np.uint64), np.full(2 * n, x, np.uint64))))
            self.up, self.down = grow(self.base), grow(self.back)
        return self.up[:n], self.down[:n]

    def hashes(self, data: np.ndarray) -> np.ndarray:
        """A rolling hash of each gram, from differences of one running sum (arithmetic modulo 2^64 with an odd base)."""
        up, down = self.powers(len(data))
        total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(self.letters[data] * up)))
        h = (total[self.gram :] - total[: len(data) - self.gram + 1]) * down[: len(data) - self.gram + 1]
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x9E3779B97F4A7C15)
        return h ^ (h >> np.uint64(32))

    def runs(self, text: bytes):
        """(first window, last window, anchor's place, anchor's hash) arrays of a text."""
        found = []
        data = np.frombuffer(text, np.uint8)
        windows = len(data) - self.width + 1
        for at in range(0, max(0, windows), BLOCK):
            n = min(BLOCK, windows - at)
            h = self.hashes(data[at : at + n + self.width - 1])
            w = self.reach
            v = (h & np.uint64(~LOW & (1 << 64) - 1)) | np.arange(len(h), dtype=np.uint64)
            pad = np.full(-len(v) % w, (1 << 64) - 1, np.uint64)
            grid = np.concatenate((v, pad)).reshape(-1, w)
            left = np.minimum.accumulate(grid, axis=1).ravel()
            right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
            place = (np.minimum(right[:n], left[w - 1 : w - 1 + n]) & np.uint64(LOW)).astype(np.int64)
            first = np.concatenate(([0], np.flatnonzero(place[1:] != place[:-1]) + 1))
            last = np.concatenate((first[1:] - 1, [n - 1]))
            found.append((first + at, last + at, place[first] + at, h[place[first]].view(np.int64)))
        return [np.concatenate(x) for x in zip(*found)] if found else [np.zeros(0, np.int64)] * 4


def _spans(text: bytes, ranges: list[tuple[int, int]], width: int) -> tuple[int, int, str]:
    """Bytes removed, maximal runs removed, digest of the rest, when windows p0..p1 of each range go."""
    removed = spans = at = 0
    keep = hashlib.sha256()
    end = -1
    for a, b in sorted(ranges):
        b += width
        if a > end:
            if end >= 0:
                removed += end - at
            keep.update(text[max(end, 0) : a])
            spans, at, end = spans + 1, a, b
        else:
            end = max(end, b)
    if end >= 0:
        removed += end - at
    keep.update(text[max(end, 0) :])
    return removed, spans, keep.hexdigest()


def told(rows: DataFrame, key: str, made, hot: int, scratch: Scratch) -> DataFrame:
    """rows with aggregates of their key's rows beside each.

    Keys of more than `hot` rows, of which there are at most the rows' number divided by `hot`, are broadcast if that is
    not too many; so a key that many rows share lands in no single task.
    """
    made = made if isinstance(made, list) else [made]
    per_key = scratch.keep(rows.groupBy(key).agg(F.count("*").alias("__n"), *made), f"per_{key}")
    crowded = bounded_broadcast(per_key.where(F.col("__n") > hot).drop("__n"), MOST_HOT)
    return rows.join(crowded, key).unionByName(rows.join(crowded, key, "left_anti").join(per_key.where(F.col("__n") <= hot).drop("__n"), key))


def cut_repeats(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256) of every row: its UTF-8 bytes without those that a string of `width` bytes covers which also starts elsewhere.

    Matches lie within texts; strings are judged on the input.  Null texts are empty.  Rows equal in id and text are
    copies of each other like any two rows with the same text.
    """
    scratch = Scratch(docs.sparkSession, "suffixes")
    step = -(-(width - gram + 1) // SLICES)
    keyed = docs.select(row_key(id_col, text_col).alias("key"), text_or_empty(text_col).alias("text"))

    def find():
        from xxhash import xxh3_128_digest

        anchors = Anchors(width, gram)

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            keys, firsts, lasts, places, hashes, wholes, windows = [], [], [], [], [], [], []
            for key, text in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist()):
                first, last, place, h = anchors.runs(text)
                keys += [key] * len(first)
                windows += [len(text) - width + 1] * len(first)
                firsts.append(first), lasts.append(last), places.append(place), hashes.append(h)
                wholes += [xxh3_128_digest(text[x : y + width]) for x, y in zip(first.tolist(), last.tolist())]
            flat = [pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), k, safe=True) for x, k in ((firsts, pa.int32()), (lasts, pa.int32()), (places, pa.int32()), (hashes, pa.int64()))]
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), *flat, pa.array(wholes, pa.binary()), pa.array(windows, pa.int32())], names=["key", "p0", "p1", "at", "anchor", "whole", "windows"])

        return each

    runs = scratch.keep(arrow_pass(keyed.where(F.octet_length("text") >= width), "key binary, p0 int, p1 int, at int, anchor long, whole binary, windows int", find), "runs")
    met = scratch.keep(told(runs, "anchor", F.count("*").alias("again"), hot, scratch).where("again > 1").drop("again"), "met")
    whole = met.groupBy("anchor", "whole").agg(F.count("*").alias("n"), F.min(F.struct("key", "p0")).alias("one"))
    whole = scratch.keep(whole, "whole")
    marked = told(whole, "anchor", F.max(F.col("n") == 1).alias("has_open"), hot, scratch)
    judged = met.join(marked, ["anchor", "whole"]).select("key", "p0", "p1", "at", "windows", (F.col("n") > 1).alias("done"), (F.col("has_open") & ((F.col("n") == 1) | (F.struct("key", "p0") == F.col("one")))).alias("use"))
    lists = judged.groupBy("key").agg(F.max("windows").alias("windows"), F.collect_set(F.struct("p0", "p1", "at", "done", "use")).alias("runs"))
    covered = F.aggregate("runs", F.lit(0), lambda s, r: s + F.when(r["done"], r["p1"] - r["p0"] + 1).otherwise(0)) == F.col("windows")
    lists = scratch.keep(lists.select("key", "runs", (covered).alias("all")), "lists")
    texts = scratch.keep(keyed.join(lists.where(F.exists("runs", lambda r: r["use"]) | ~F.col("all")), "key").dropDuplicates(["key"]), "texts")

    def slices():
        from xxhash import xxh3_64_intdigest, xxh3_128_digest

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            rows = []
            for key, text, found in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), b.column(2).to_pylist()):
                for r in found:
                    if not r["use"]:
                        continue
                    at = r["at"]
                    low, high = at - r["p1"], at - r["p0"]
                    for j in range(low // step, high // step + 1):
                        a, z = at - min(high, j * step + step - 1), at - max(low, j * step)
                        core = text[at - j * step : at - j * step - step + 1 + width]
                        rows.append((key, a, z, int.from_bytes(xxh3_64_intdigest(core, j).to_bytes(8, "little"), "little", signed=True), xxh3_128_digest(text[a : z + width], j), not r["done"]))
            kinds = (pa.binary(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows) if rows else [[]] * 6, kinds)], names=["key", "p0", "p1", "core", "whole", "open"])

        return each

    parts = scratch.keep(arrow_pass(texts.select("key", "text", "runs"), "key binary, p0 int, p1 int, core long, whole binary, open boolean", slices), "slices")
    whole2 = parts.groupBy("core", "whole").agg(F.count("*").alias("n"), F.min(F.struct("key", "p0")).alias("one"), F.max("open").alias("any"))
    whole2 = scratch.keep(whole2, "whole_slices")
    cores = told(whole2, "core", [F.sum("n").alias("total"), F.max((F.col("n") == 1) & F.col("any")).alias("has_open")], hot, scratch).where("total > 1").drop("total")
    settled = scratch.keep(
        parts.join(cores, ["core", "whole"])
        .select("key", "p0", "p1", (F.col("open") & (F.col("n") > 1)).alias("hit"), (F.col("has_open") & ((F.col("n") == 1) | (F.struct("key", "p0") == F.col("one")))).alias("use"), (F.col("open") & (F.col("n") == 1)).alias("open"))
        .where("hit OR use"),
        "settled",
    )
    asked = settled.where("use").groupBy("key").agg(F.collect_set(F.struct("p0", "p1", "open")).alias("asked"))

    def windows():
        from xxhash import xxh3_128_digest

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            rows = []
            for key, text, found in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), b.column(2).to_pylist()):
                for r in found:
                    rows += [(key, p, xxh3_128_digest(text[p : p + width]), r["open"]) for p in range(r["p0"], r["p1"] + 1)]
            kinds = (pa.binary(), pa.int32(), pa.binary(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows) if rows else [[]] * 4, kinds)], names=["key", "p", "whole", "open"])

        return each

    single = scratch.keep(arrow_pass(texts.select("key", "text").join(asked, "key"), "key binary, p int, whole binary, open boolean", windows), "windows")
    twice = single.groupBy("whole").count().where("count > 1").select("whole")
    hits = single.where("open").join(twice, "whole", "left_semi").select("key", F.col("p").alias("p0"), F.col("p").alias("p1"))
    ranges = settled.where("hit").select("key", "p0", "p1").union(hits).groupBy("key").agg(F.collect_set(F.struct("p0", "p1")).alias("more"))

    def finish():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            out = []
            for text, found, more in zip(b.column(1).cast(pa.binary()).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()):
                out.append(_spans(text, [(r["p0"], r["p1"]) for r in found if r["done"]] + [(r["p0"], r["p1"]) for r in more or []], width))
            kinds = (pa.int64(), pa.int64(), pa.string())
            return pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x, k) for x, k in zip(zip(*out) if out else [[]] * 3, kinds))], names=["key", "n_removed", "n_spans", "kept_sha256"])

        return each

    partly = arrow_pass(texts.where("NOT all").join(ranges, "key", "left").select("key", "text", "runs", "more"), "key binary, n_removed long, n_spans long, kept_sha256 string", finish)
    wholly = lists.where("all").select("key", F.lit(-1).cast("long").alias("n_removed"), F.lit(1).cast("long").alias("n_spans"), F.lit(hashlib.sha256(b"").hexdigest()).alias("kept_sha256"))
    results = partly.union(wholly)
    text = text_or_empty(text_col)
    base = docs.select(F.col(id_col), row_key(id_col, text_col).alias("key"), F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text.cast("binary"), 256).alias("__sha"))
    pick = lambda c, other: F.coalesce(F.col(c), other).alias(c)
    return base.join(results, "key", "left").select(
        F.col(id_col), "n_bytes", F.when(F.col("n_removed") == -1, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0).cast("long"))).alias("n_removed"), pick("n_spans", F.lit(0).cast("long")), pick("kept_sha256", F.col("__sha"))
    )


def op7_repeated_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut_repeats(documents(spark, sf_dir)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
