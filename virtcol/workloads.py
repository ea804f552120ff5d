"""The experiment workloads on the given tables: conditions with hidden truth, dialogs, pages, and the runs over them."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import baselines
from .engine import Engine, TableInfo
from .index import features as feats
from .index.sample import allocate, draw, estimate, md5_key, strata_sizes
from .index.search import active_search
from .metrics import Spans
from .model.base import NoisyModel, RuleModel
from .plans.planner import Costs
from .tables import shared_folder

#: Insults that the lexical model looks for.
INSULTS = "idiot|moron|clown|loser|pathetic|scum|worthless|trash|disgusting|stupid"
LICENCE = "case when text like '%Apache License%' then 'apache' when text like '%MIT License%' then 'mit' when text like '%General Public License%' or text like '%GPL%' then 'gpl' when text like '%Creative Commons%' or text like '%CC BY%' then 'cc' end"
TRUTH = {
    "text is French": "lang = 'fr'",
    "text is English": "lang = 'en'",
    "text is German": "lang = 'de'",
    "text is Spanish": "lang = 'es'",
    "text is clean readable prose": "quality = 1",
    "text insults someone": "toxic = 1",
    "insulting": f"lower(text) rlike '\\\\b({INSULTS})\\\\b'",
    "insulting junk": "toxic = 1 and quality = 0",
    "opens with a system instruction": "transcript like 'system: %'",
    "carries a licence line": f"({LICENCE}) is not null",
    "page is English": "html like '%<html lang=\"en\"%'",
    "digit is below 1": "label = 0",
    "digit is above 7": "label > 7",
    "three": "label = 3",
    "its square is itself": "label < 2",
    "smallest prime": "label = 2",
}
LABELS = {"language of the text": "lang", "which licence": LICENCE, "topic of the dialog": "split(transcript, ' ')[1]"}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def dialogs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per dialog: its turns in order and their text, each with its speaker."""
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    out = read(spark, sf_dir, "conversations").groupBy("conv_id").agg(turns.alias("turns"))
    return out.select("conv_id", F.size("turns").alias("n_turns"), "turns", F.array_join(F.transform("turns", lambda t: F.concat_ws(": ", t["role"], t["text"])), "\n").alias("transcript"))


def pages_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    body = F.regexp_replace(F.regexp_replace(F.col("html"), r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " "), r"(?s)<[^>]*>", " ")
    return read(spark, sf_dir, "pages").select("page_id", F.try_parse_url("url", F.lit("HOST")).alias("host"), F.trim(F.regexp_replace(body, r"\s+", " ")).alias("body"), "html")


def labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id")


def balanced(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All junk and as much clean prose, the first in md5 order."""
    df = labelled(spark, sf_dir)
    ranked = df.withColumn("_r", F.row_number().over(Window.partitionBy("quality").orderBy(md5_key("doc_id", 0))))
    n = df.groupBy().agg(F.count_if(F.col("quality") == 0).alias("_n0"))
    return ranked.crossJoin(F.broadcast(n)).where("quality = 0 or _r <= _n0").drop("_r", "_n0")


#: name -> (table, phrase)
CONDITIONS = {
    "w1": ("labelled", "text is clean readable prose"), "w1b": ("balanced", "text is clean readable prose"), "w2": ("documents", "text is Spanish"), "w3": ("labelled", "text insults someone"),
    "w4": ("documents", "text is English"), "w5": ("documents", "text is French"), "w6": ("documents", "text is German"), "w7": ("labelled", "insulting junk"), "w8": ("embeddings", "digit is below 1"),
    "w9": ("embeddings", "digit is above 7"), "w26a": ("embeddings", "three"), "w26b": ("embeddings", "its square is itself"), "w26c": ("embeddings", "smallest prime"), "w34": ("pages", "page is English"),
}


def table(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, TableInfo]:
    hidden = ("lang", "quality", "toxic", "label")
    match name:
        case "labelled":
            return labelled(spark, sf_dir), TableInfo("doc_id", "text", "documents", hidden, LABELS)
        case "balanced":
            return balanced(spark, sf_dir), TableInfo("doc_id", "text", "documents", hidden, LABELS)
        case "embeddings":
            return read(spark, sf_dir, name), TableInfo("vec_id", "embedding", "vectors", hidden, LABELS, vectors="embedding")
        case "pages":
            return pages_text(spark, sf_dir), TableInfo("page_id", "body", "web pages", (), LABELS)
        case "dialogs":
            return dialogs(spark, sf_dir), TableInfo("conv_id", "transcript", "dialogs", (), LABELS)
    return read(spark, sf_dir, name), TableInfo("doc_id" if name == "documents" else "id", "text", name, ("lang",), LABELS)


def engine(spark: SparkSession, sf_dir: str, budget: int | None = None, seed: int = 0, model: RuleModel | None = None, stratum: str | None = None) -> Engine:
    costs = Costs() if budget is None else Costs(budget, budget)
    e = Engine(spark, model or RuleModel(TRUTH, "truth"), costs, seed)
    for name in ("documents", "labelled", "embeddings", "pages", "dialogs"):
        df, info = table(spark, sf_dir, name)
        if stratum and name == "documents":
            info.stratum = stratum
        e.register(name, df, info)
    e.register("lineitem", read(spark, sf_dir, "lineitem"), TableInfo("l_orderkey", "l_returnflag"))
    return e


def truth(name: str, spark: SparkSession, sf_dir: str) -> int:
    at, phrase = CONDITIONS[name]
    return table(spark, sf_dir, at)[0].where(F.expr(TRUTH[phrase])).count()


#: What a user would type to find texts of a kind by inner product; no label is looked at. Vectors have no such words: see spoken().
QUERY_TEXT = {
    "text is French": "le la les de des et est une dans que pour", "text is English": "the of and to in is that for with on by", "text is German": "der die das und ist nicht ein eine zu den mit",
    "text is Spanish": "el la los de y en que una es por con", "text is clean readable prose": "the of and to in is that for with on by", "text insults someone": INSULTS.replace("|", " "),
    "insulting": INSULTS.replace("|", " "), "insulting junk": INSULTS.replace("|", " ") + " # | * $", "page is English": "the of and to in is that for with on by",
}


def features_of(df: DataFrame, info: TableInfo) -> DataFrame:
    return feats.build_features(df, info.id_col, info.vectors or info.source, "given" if info.vectors else "hashed_words")


def stored(df: DataFrame, info: TableInfo, k: int = 10, spans: Spans | None = None) -> tuple[DataFrame, DataFrame]:
    """(id, e) and (id, stratum), computed once and kept on the shared folder."""
    spark, spans = df.sparkSession, spans or Spans()
    root = shared_folder(spark, "features")
    with spans("embed"):
        features_of(df, info).write.parquet(f"{root}/e")
        e = spark.read.parquet(f"{root}/e")
    with spans("cluster"):
        feats.assign_strata(e, "kmeans", k, 0).write.parquet(f"{root}/strata")
    return e, spark.read.parquet(f"{root}/strata")


def spoken(df: DataFrame, info: TableInfo, f, seed: int, n: int = 3) -> list[float]:
    """A query for vectors that no text describes: the mean of a few exemplars that the user hands over, as a speech bridge would."""
    some = df.where(f).select(F.col(info.id_col).alias("id")).orderBy(md5_key("id", seed)).limit(n)
    v = features_of(df, info).join(F.broadcast(some), "id").toPandas()["e"]
    return np.mean([np.asarray(x, float) for x in v], axis=0).tolist() if len(v) else [0.0]


def query_vector(df: DataFrame, info: TableInfo, phrase: str, f, seed: int) -> list[float]:
    if info.vectors:
        return spoken(df, info, f, seed)
    one = df.sparkSession.createDataFrame([(0, QUERY_TEXT[phrase])], "id long, q string")
    return [float(x) for x in feats.build_features(one, "id", "q", "hashed_words").first()["e"]]


def run(name: str, spark: SparkSession, sf_dir: str, method: str = "stratified", budget: int = 128, seed: int = 0, model: RuleModel | None = None, pool: int | None = None) -> dict:
    """One row of the run log: a COUNT by stratified, uniform or packed sampling, or a retrieval by active, udf or mips search."""
    at, phrase = CONDITIONS[name]
    df, info = table(spark, sf_dir, at)
    f = (model or RuleModel(TRUTH)).column(phrase)
    start, spans = time.time(), Spans()
    out = {"workload": name, "method": method, "budget": budget, "seed": seed, "truth": df.where(F.expr(TRUTH[phrase])).count()}
    if method == "stratified":
        _, s = stored(df, info, 10, spans)
        with spans("sample"):
            w = draw(s, "id", "stratum", allocate(strata_sizes(s, "stratum"), budget), seed)
        with spans("judge"):
            w.df = w.df.join(df.select(F.col(info.id_col).alias("id"), f.alias("_f")), "id")
            out["estimate"] = estimate(w, "count", F.col("_f")).first()[0]
    elif method == "uniform":
        out["estimate"] = baselines.udf_count(df, info.id_col, f, budget, seed).first()[0]
    elif method == "packed":
        from .model.base import PackedModel

        packed = baselines.packs(df, info.id_col, F.length(F.col(info.source).cast("string")) / 4, 4000, budget, seed)
        out["estimate"] = baselines.packed_count(packed, PackedModel(RuleModel(TRUTH), info.id_col).column(phrase, F.col("place"), F.col("size")), df.count()).first()[0]
    else:
        if method == "active":
            root = shared_folder(spark, "features")
            with spans("embed"):
                features_of(df, info).write.parquet(root)

            def judge(ids: list) -> list[bool]:
                """One filter for a batch."""
                with spans("judge"):
                    yes = {r[0] for r in df.where(F.col(info.id_col).isin(ids)).where(f).select(info.id_col).collect()}
                return [i in yes for i in ids]

            with spans("search"):
                got = active_search(spark.read.parquet(root), judge, budget, 16, seed=seed, pool=pool)
            spans.seconds["fit and score"] = spans.seconds.pop("search") - spans.seconds.get("judge", 0.0)
            hits, returned = len(got.hits), len(got.hits)
        elif method == "udf":
            hits = returned = baselines.udf_rows(df, info.id_col, f, budget, seed).count()
        else:
            q = query_vector(df, info, phrase, f, seed)
            top = baselines.mips(features_of(df, info), "id", "e", q, budget)
            returned, hits = budget, top.join(df.where(f).select(F.col(info.id_col).alias("id")), "id", "left_semi").count()
        cap = min(budget, out["truth"])
        p, r = hits / returned if returned else 0.0, hits / cap if cap else 0.0
        out |= {"hits": hits, "precision": p, "recall_capped": r, "f1": 2 * p * r / (p + r) if p + r else 0.0}
    if "estimate" in out and out["truth"]:
        out["relative_error"] = abs((out["estimate"] or 0.0) - out["truth"]) / out["truth"]
    return out | {"seconds": time.time() - start, "spans": spans.seconds}


def sampler_study(spark: SparkSession, sf_dir: str, name: str, budget: int = 128, seeds: int = 200) -> DataFrame:
    """(sampler, seed, estimate) for uniform and stratified draws with the truth as model, in one job.

    A row's key under each seed is compared with its stratum's threshold before anything is multiplied, so what is
    shuffled is a little more than the draws themselves; of those the least keys stay.
    """
    at, phrase = CONDITIONS[name]
    df, info = table(spark, sf_dir, at)
    _, s = stored(df, info)
    base = df.select(F.col(info.id_col).alias("id"), F.coalesce(F.expr(TRUTH[phrase]), F.lit(False)).cast("int").alias("f")).join(s, "id")
    sizes = strata_sizes(s, "stratum")
    take, n = allocate(sizes, budget), sum(sizes.values())
    cells = [("stratified", k, sizes[k], v) for k, v in take.items() if v] + [("uniform", -1, n, min(budget, n))]
    share = lambda size, v: min(1.0, (v + 8 * v**0.5 + 20) / size)  # noqa: E731  # fewer than v keys below it: never in practice
    plan = spark.createDataFrame([(a, int(g), float(size), int(v), share(size, v)) for a, g, size, v in cells], "sampler string, g int, size double, take int, share double")
    arms = base.select("id", "f", F.explode(F.array(F.struct(F.lit("stratified").alias("sampler"), F.col("stratum").cast("int").alias("g")), F.struct(F.lit("uniform").alias("sampler"), F.lit(-1).alias("g")))).alias("a")).select("id", "f", "a.sampler", "a.g").join(F.broadcast(plan), ["sampler", "g"])
    key = lambda seed: F.xxhash64(seed, F.col("id"))
    low = F.lit(-(2.0**63)) + F.col("share") * 2.0**64
    spread = arms.withColumn("seed", F.explode(F.filter(F.sequence(F.lit(0), F.lit(seeds - 1)), lambda x: key(x).cast("double") <= low))).withColumn("key", key(F.col("seed")))
    mine = Window.partitionBy("sampler", "seed", "g")
    drawn = spread.withColumn("r", F.row_number().over(mine.orderBy("key", "id"))).where("r <= take").withColumn("w", F.col("size") / F.count("*").over(mine))
    return drawn.groupBy("sampler", "seed").agg((F.lit(float(n)) * F.sum(F.col("w") * F.col("f")) / F.sum("w")).alias("estimate"))


def learning_curves(spark: SparkSession, sf_dir: str, name: str, budget: int = 96, runs: int = 8, pool: int = 512) -> DataFrame:
    """(run, step, hit) of active searches from different seeds; features are computed once for all runs."""
    at, phrase = CONDITIONS[name]
    df, info = table(spark, sf_dir, at)
    root = shared_folder(spark, "features")
    features_of(df, info).write.parquet(root)
    e, rows = spark.read.parquet(root), []

    def judge(ids: list) -> list[bool]:
        yes = {r[0] for r in df.where(F.col(info.id_col).isin(ids)).where(F.expr(TRUTH[phrase])).select(info.id_col).collect()}
        return [i in yes for i in ids]

    for seed in range(runs):
        got = active_search(e, judge, budget, 16, seed=seed, pool=pool, refresh=3)
        rows += [(seed, k, bool(t[3])) for k, t in enumerate(got.trace)]
    return spark.createDataFrame(rows, "run int, step int, hit boolean")


def backend_swap(spark: SparkSession, sf_dir: str, name: str = "w1", budget: int = 128, seed: int = 0) -> list[dict]:
    """The same runs with two backends that err for different rows."""
    base = RuleModel(TRUTH)
    id_col = table(spark, sf_dir, CONDITIONS[name][0])[1].id_col
    return [run(name, spark, sf_dir, m, budget, seed, NoisyModel(base, id_col, 0.03, 0.03, salt)) | {"backend": salt} for salt in ("a", "b") for m in ("stratified", "active")]


def budget_sweep(spark: SparkSession, sf_dir: str, name: str, methods=("stratified", "uniform"), budgets=(32, 64, 128, 256, 512), seeds=range(8)) -> list[dict]:
    return [run(name, spark, sf_dir, m, b, s) for m in methods for b in budgets for s in seeds]
