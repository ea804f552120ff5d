"""SimHash fingerprints, linked through covering locality-sensitive hashing.

Bits of a fingerprint are dealt to the nonzero vectors of GF(2)^(radius+1); a
table keeps the bits whose vector has an odd product with the table's own
nonzero vector.  At most `radius` differing bits span less than the whole
space, so some table's vector is orthogonal to all of them: that table drops
every differing bit and the pair meets there.  No pair is missed.

A bucket of two is settled from its least and largest member, one of at most
SMALL by comparing its few.  No larger bucket is paired: its members go on to balls: for an even
radius 2t two fingerprints are within reach exactly if their balls of radius t
share a point, and a point's ball holds a fixed number of fingerprints.

No radius that can be afforded guarantees texts of similarity 0.8 to meet:
their fingerprints differ in about ten bits.  representatives() therefore takes
further candidates from bands of MinHash values and links any candidate only if
the exact similarity of the two shingle sets is high enough.  Members of a
crowded band are compared with a few of it first; those that are then still
apart meet through their rarest shingles, of which any pair alike enough
shares one.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, add_columns, arrow_pass, bounded_broadcast, documents, row_key
from .components import components

SEED = 42
BITS = 64
#: Buckets of up to so many fingerprints are compared pair by pair; larger ones by balls.
SMALL = 8
#: MinHash bands and values in each: texts of similarity 0.8 share a band with probability 0.9998.
BANDS, ROWS = 16, 4
#: Shares into which the pairs of one text are split where its shingles are joined to them.
SALTS = 32
#: Rows of 64 bits, one bit a document, that may be broadcast; beyond them Spark joins by shuffle.
BIT_WORDS = 2_000_000


def shingle_hashes(text: bytes, words: int, xxh64) -> np.ndarray:
    """Hashes of a UTF-8 text's shingles of so many words, A-Z lower-cased, repeats included; fewer words make one shingle, none makes none."""
    w = text.lower().split()
    if not w:
        return np.zeros(0, np.uint64)
    buf = b" ".join(w)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    k = min(words, len(w))
    return np.array([xxh64(buf[a:b], SEED) for a, b in zip(starts[: len(w) - k + 1].tolist(), ends[k - 1 :].tolist())], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """The bits that over half the hashes have; 0 for no hashes."""
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 32768):
        part = hashes[at : at + 32768].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes), bitorder="little").tobytes(), "little")


def fingerprint(text: bytes, words: int, xxh64) -> int:
    """SimHash of a UTF-8 text."""
    return majority(shingle_hashes(text, words, xxh64))


def fingerprints(docs: DataFrame, words: int = 5, text_col: str = "text", drop: tuple[str, ...] = ()) -> DataFrame:
    """docs, without the columns in `drop`, with simhash (the 64 bits as a signed long). Null and wordless texts: 0."""

    def make():
        from xxhash import xxh64_intdigest

        return lambda texts: [np.array([fingerprint(t, words, xxh64_intdigest) for t in texts], np.uint64).view(np.int64)]

    return add_columns(docs, text_col, "simhash long", make, drop=drop)


def masks(radius: int) -> list[int]:
    """The covering family: 2^(radius+1)-1 bit masks as signed longs."""
    n = (1 << (radius + 1)) - 1
    out = [sum(1 << bit for bit in range(BITS) if ((bit % n + 1) & v).bit_count() % 2) for v in range(1, n + 1)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in out]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(prints: DataFrame, radius: int, scratch: Scratch) -> DataFrame:
    """Edges (u, v) between distinct fingerprints (column simhash) whose components are those of all pairs within the radius."""
    if radius < 0 or radius % 2:
        raise ValueError("the radius is even")
    each = F.explode(F.array(*(F.struct(F.lit(t).alias("table"), F.col("simhash").bitwiseAND(F.lit(m)).alias("rest")) for t, m in enumerate(masks(radius)))))
    dealt = prints.select("simhash", each.alias("b")).select("simhash", "b.table", "b.rest")
    buckets = scratch.keep(dealt.groupBy("table", "rest").agg(F.count("*").alias("n"), F.min("simhash").alias("v"), F.max("simhash").alias("u")).where("n > 1"), "buckets")
    near = F.bit_count(F.col("u").bitwiseXOR(F.col("v"))) <= radius
    pairs = buckets.where(F.col("n") == 2).where(near).select("u", "v")
    few = dealt.join(buckets.where((F.col("n") > 2) & (F.col("n") <= SMALL)).select("table", "rest"), ["table", "rest"], "left_semi").groupBy("table", "rest").agg(F.sort_array(F.collect_set("simhash")).alias("all"))
    each_two = few.select("all", F.posexplode("all").alias("i", "u")).select("u", F.explode(F.slice("all", 1, F.col("i"))).alias("v")).where(near)
    pairs = pairs.union(each_two)
    crowded = dealt.join(buckets.where(F.col("n") > SMALL).select("table", "rest"), ["table", "rest"], "left_semi").select("simhash").distinct()
    flips = [signed(sum(1 << b for b in c)) for t in range(radius // 2 + 1) for c in combinations(range(BITS), t)]
    points = crowded.select("simhash", F.explode(F.transform(F.array(*map(F.lit, flips)), lambda x: F.col("simhash").bitwiseXOR(x))).alias("point"))
    shared = points.groupBy("point").agg(F.collect_set("simhash").alias("all")).where(F.size("all") > 1)  # a ball's size bounds the set
    stars = shared.select(F.array_min("all").alias("v"), F.explode("all").alias("u")).where("u <> v")
    return pairs.union(stars).distinct()


def groups(docs: DataFrame, scratch: Scratch, radius: int = 2, id_col: str = "doc_id") -> DataFrame:
    """docs (with simhash) and component_id: the least id among the documents its fingerprint reaches; null if all those ids are null.

    docs is read several times; give a table that was kept.
    """
    prints = docs.groupBy("simhash").agg(F.min(id_col).alias("__least"))
    roots = scratch.keep(components(links(prints.select("simhash"), radius, scratch), scratch), "roots")
    named = prints.join(roots.withColumnRenamed("node", "simhash"), "simhash", "left").select("simhash", "__least", F.coalesce("root", "simhash").alias("__root"))
    least = named.groupBy("__root").agg(F.min("__least").alias("component_id"))
    of = named.join(least, "__root").select("simhash", "component_id")
    return docs.drop("component_id").join(of, "simhash")


def near_duplicates(docs: DataFrame, words: int = 5, radius: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, simhash, component_id) of every row; equal rows give equal results, empty tables none."""
    scratch = Scratch(docs.sparkSession, "simhash")
    kept = scratch.keep(fingerprints(docs.select(id_col, text_col), words, text_col, (text_col,)).select(id_col, "simhash"), "prints")
    return groups(kept, scratch, radius, id_col)


def op2_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_duplicates(documents(spark, sf_dir), words=3, radius=2)
    return out.select("doc_id", F.lower(F.lpad(F.hex("simhash"), 16, "0")).alias("fingerprint"), "component_id")


def least_values(hashes: np.ndarray) -> np.ndarray:
    """BANDS * ROWS MinHash values of distinct hashes; zeros for none."""
    rng = np.random.default_rng(SEED)
    times = rng.integers(0, 1 << 63, (BANDS * ROWS, 1), np.uint64) * np.uint64(2) + np.uint64(1)
    plus = rng.integers(0, 1 << 63, (BANDS * ROWS, 1), np.uint64)
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max if len(hashes) else 0, np.uint64)
    for at in range(0, len(hashes), 2048):
        np.minimum(least, ((hashes[at : at + 2048] * times + plus) >> np.uint64(24)).min(axis=1), out=least)
    return least


def sketches(docs: DataFrame, words: int, text_col: str = "text") -> DataFrame:
    """docs without its text, with simhash, node (a 64-bit digest of the shingle set: equal sets, equal nodes), bands (MinHash band keys) and shingles (the set, 32 bits each, sorted)."""

    def make():
        from xxhash import xxh64_intdigest

        def work(texts: list[bytes]) -> list:
            prints, nodes, bands, sets = [], [], [], []
            for t in texts:
                hashes = shingle_hashes(t, words, xxh64_intdigest)
                prints.append(signed(majority(hashes)))
                hashes = np.unique(hashes)
                nodes.append(signed(xxh64_intdigest(hashes.tobytes(), SEED)))
                least = least_values(hashes).reshape(BANDS, ROWS)
                bands.append([signed(xxh64_intdigest(row.tobytes(), i)) for i, row in enumerate(least)])
                sets.append(np.unique((hashes >> np.uint64(32)).astype("<u4")).tobytes())
            return [prints, nodes, bands, sets]

        return work

    return add_columns(docs, text_col, "simhash long, node long, bands array<long>, shingles binary", make, drop=(text_col,))


def band_pairs(nodes: DataFrame, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """Candidates (u, v) from nodes (node, bands), and the members (node, band) of bands that are not paired in full.

    The members of a band of at most SMALL are paired.  In a larger one each
    member is paired with three: that whose bands are the most crowded, which
    in a group of altered copies is the text nearest to all, the least and the
    largest.  rest_pairs() finds what those miss.
    """
    dealt = scratch.keep(nodes.select("node", F.explode("bands").alias("band")), "bands")
    sizes = scratch.keep(dealt.groupBy("band").agg(F.count("*").alias("n"), F.min("node").alias("lo"), F.max("node").alias("hi")).where("n > 1"), "sizes")
    two = sizes.where("n = 2").select(F.col("hi").alias("u"), F.col("lo").alias("v"))
    few = dealt.join(sizes.where(F.col("n").between(3, SMALL)).select("band"), "band", "left_semi").groupBy("band").agg(F.sort_array(F.collect_set("node")).alias("all"))
    each_two = few.select("all", F.posexplode("all").alias("i", "u")).select("u", F.explode(F.slice("all", 1, F.col("i"))).alias("v"))
    crowded = scratch.keep(dealt.join(sizes.where(F.col("n") > SMALL), "band"), "crowded")
    weight = crowded.groupBy("node").agg(F.sum("n").alias("weight"))
    heads = crowded.select("node", "band").join(weight, "node").groupBy("band").agg(F.max_by("node", F.struct("weight", "node")).alias("head"))
    stars = crowded.join(heads, "band").select(F.explode(F.array_distinct(F.array("head", "lo", "hi"))).alias("u"), F.col("node").alias("v")).where("u <> v")
    return two.union(each_two).union(stars), crowded.select("node", "band")


def rest_pairs(crowded: DataFrame, roots: DataFrame, sets: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """Candidates (u, v) among members (node, band) of bands that hold more than one component of roots (node, root).

    Every pair of different components with that similarity is among them.  In an order of shingles that puts rare ones
    first, the first shingle that such a pair shares stands early in both: as many as must be shared come at or after it.
    Shingles of one set only are counted, not joined.
    """
    of = crowded.join(roots, "node", "left").select("node", "band", F.coalesce("root", "node").alias("root"))
    open_bands = of.groupBy("band").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("band")
    members = of.join(open_bands, "band", "left_semi").select("node", "root").distinct()

    def make():
        def each(batch: pa.RecordBatch):
            held, size = [], 0

            def out() -> pa.RecordBatch:
                heads = np.array([h[:2] for h in held], np.int64)
                lengths = np.array([len(h[2]) for h in held])
                columns = [np.repeat(heads[:, 0], lengths), np.repeat(heads[:, 1], lengths), np.repeat(lengths.astype(np.int32), lengths), np.concatenate([h[2] for h in held])]
                return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["node", "root", "size", "shingle"])

            for node, root, shingles in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                held.append((node, root, np.frombuffer(shingles.as_buffer(), "<i4")))
                size += len(held[-1][2])
                if size > 100_000:
                    yield out()
                    held, size = [], 0
            if size:
                yield out()

        return each

    given = sets.join(members, "node").select("node", "root", "shingles")
    dealt = scratch.keep(arrow_pass(given, "node long, root long, size int, shingle int", make), "dealt")
    often = dealt.groupBy("shingle").agg(F.count("*").alias("n"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("n > 1")
    per = Window.partitionBy("node")
    place = F.col("size") - F.count("*").over(per) + F.row_number().over(per.orderBy("n", "shingle"))  # from 1; shingles of one set only come first
    early = dealt.join(often, "shingle").withColumn("after", F.col("size") - place + 1).where("lo <> hi").where(F.col("after") >= similarity * F.col("size") - 1e-6)
    early = scratch.keep(early.select("shingle", "node", "root", "size", "after"), "early")
    a, b = (early.select("shingle", *(F.col(c).alias(f"{c}_{side}") for c in ("node", "root", "size", "after"))) for side in "uv")
    enough = F.least("after_u", "after_v") >= similarity / (1 + similarity) * (F.col("size_u") + F.col("size_v")) - 1e-6
    met = a.join(b, "shingle").where((F.col("node_u") > F.col("node_v")) & (F.col("root_u") != F.col("root_v")) & enough)
    return met.select(F.col("node_u").alias("u"), F.col("node_v").alias("v")).distinct()


def simhash_pairs(prints: DataFrame, radius: int, scratch: Scratch) -> DataFrame:
    """Candidates (u, v) from (node, simhash): texts of one fingerprint with its least text, and least texts of fingerprints within the radius."""
    least = scratch.keep(prints.groupBy("simhash").agg(F.min("node").alias("least")), "least")
    same = prints.join(least, "simhash").select(F.col("least").alias("u"), F.col("node").alias("v")).where("u <> v")
    ends = links(least.select("simhash"), radius, scratch)
    for side in "uv":
        ends = ends.join(least.select(F.col("simhash").alias(side), F.col("least").alias(f"node_{side}")), side)
    return same.union(ends.select(F.col("node_u").alias("u"), F.col("node_v").alias("v")))


def alike(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (u, v) whose sets (node, shingles) have that Jaccard similarity or more; two empty sets are alike."""
    pairs = pairs.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)))
    left = pairs.select("u", "salt").distinct().join(sets.select(F.col("node").alias("u"), F.col("shingles").alias("a")), "u")
    both = pairs.join(sets.select(F.col("node").alias("v"), F.col("shingles").alias("b")), "v").join(left, ["u", "salt"])

    def make():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            keep = []
            for a, b in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(a.as_buffer(), "<u4"), np.frombuffer(b.as_buffer(), "<u4")
                small, large = sorted((len(x), len(y)))
                if small < similarity * large:
                    keep.append(False)
                    continue
                shared = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(shared >= similarity * (small + large - shared))
            return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(keep, pa.bool_()))

        return each

    return arrow_pass(both.select("u", "v", "a", "b"), "u long, v long", make)


def representatives(docs: DataFrame, words: int = 5, radius: int = 2, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group of texts joined by pairs of that similarity: that with the least id, or any one of the rows that share it; groups without an id keep one row.

    Null and wordless texts are one group.  Shingle sets are joined to candidates only.  Texts are never joined by shuffle:
    rows are written with a number each, and a bit for each number, 64 in a broadcast row, tells which stay.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    texts = scratch.keep(docs.withColumn("__row", F.monotonically_increasing_id()), "texts")
    marked = sketches(texts.select(F.col(id_col), F.col(text_col), "__row", row_key(id_col, text_col).alias("__key")), words, text_col)
    kept = scratch.keep(marked, "sketches")
    first = F.min_by("__row", F.struct(F.col(id_col).isNull(), F.col(id_col), "__key", "__row")).alias("__row")
    nodes = scratch.keep(kept.groupBy("node").agg(F.first("bands").alias("bands"), F.min("simhash").alias("simhash"), first), "nodes")
    banded, crowded = band_pairs(nodes, scratch)
    pairs = scratch.keep(banded.union(simhash_pairs(nodes, radius, scratch)).distinct(), "pairs")
    needed = pairs.select(F.col("u").alias("node")).union(pairs.select("v")).distinct()
    holders = nodes.select("node", "__row").join(needed, "node", "left_semi")
    sets = scratch.keep(kept.select("__row", "shingles").join(holders, "__row").select("node", "shingles"), "sets")
    roots = scratch.keep(components(alike(pairs, sets, similarity), scratch), "roots")
    rest = scratch.keep(rest_pairs(crowded, roots, sets, similarity, scratch), "rest")
    more = scratch.keep(alike(rest, sets, similarity), "more")
    if not more.isEmpty():
        roots = scratch.keep(components(roots.select(F.col("node").alias("u"), F.col("root").alias("v")).union(more), scratch), "roots")
    named = kept.select(id_col, "__row", "__key", "node").join(roots, "node", "left").select(id_col, "__row", "__key", F.coalesce("root", "node").alias("g"))
    stay = named.groupBy("g").agg(first)
    bits = scratch.keep(stay.groupBy(F.shiftright("__row", 6).alias("__word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(__row & 63 as int))")).alias("__bits")), "bits")
    found = texts.join(bounded_broadcast(bits, BIT_WORDS), F.shiftright(F.col("__row"), 6) == F.col("__word"))
    return found.where(F.expr("shiftrightunsigned(__bits, cast(__row & 63 as int)) & 1 = 1")).drop("__row", "__word", "__bits")
