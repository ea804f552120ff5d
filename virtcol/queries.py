"""The methods' queries over the given tables, and the SQL that must agree."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import baselines, metrics, workloads
from .functions import udfs
from .index import features as feats
from .index.sample import allocate, estimate, importance_estimate, importance_sample, optimal_count, standard_error, strata_sizes, stratified_sample, uniform_sample
from .index.search import active_search, ordered_probe
from .lang.parser import parse
from .model.base import PackedModel, RuleModel, token_budget
from .operators import relational
from .plans import planner
from .streaming import streams
from .workloads import INSULTS, TRUTH, read

B = 128
INSULT = TRUTH["insulting"]
S_INSULT = f"regexp_matches(lower(text), '\\b({INSULTS})\\b')"


def docs(s, d):
    return read(s, d, "documents")


def six(df, *names):
    return df.select(*(F.round(c, 6).alias(c) if c in names else F.col(c) for c in df.columns))


def full_scan(f):
    return lambda s, d: baselines.full_scan(docs(s, d), F.expr(f)).agg(F.count("*").alias("n"))


def sum_avg_full_scan(s, d):
    return six(baselines.full_scan(docs(s, d), F.expr("lang = 'fr'")).agg(F.sum("n_chars").alias("total"), F.avg("n_chars").alias("mean")), "mean")


def uniform_est(s, d):
    return six(estimate(uniform_sample(docs(s, d), "doc_id", B, 0), "count", F.expr("lang = 'fr'")), "estimate")


def udf_count(s, d):
    return six(baselines.udf_count(docs(s, d), "doc_id", F.expr(INSULT), B, 1), "estimate")


def udf_rows(s, d):
    return baselines.udf_rows(docs(s, d), "doc_id", F.expr("lang = 'fr'"), 256, 2).select("doc_id")


def by(stratum, agg="count", value=None, group=None):
    def run(s, d):
        w = stratified_sample(docs(s, d), "doc_id", stratum, B, 0)
        return six(estimate(w, agg, F.expr(INSULT) if agg == "count" else F.expr("lang = 'fr'"), F.col(value) if value else None, True, group), "estimate")

    return run


ANCHORS = 8


def _anchored(s, d):
    e = read(s, d, "embeddings")
    rows = e.where(F.col("vec_id") < ANCHORS).select("vec_id", "embedding").orderBy("vec_id").collect()  # a fixed few
    return e, feats.nearest_anchor(e, [(r[0], r[1]) for r in rows], "vec_id", "embedding")


def nearest_anchor(s, d):
    return _anchored(s, d)[1].select(F.col("id").alias("vec_id"), F.col("stratum").cast("long").alias("stratum"))


def stratified_anchor(s, d):
    e, a = _anchored(s, d)
    both = e.select("vec_id", "label").join(a, F.col("vec_id") == F.col("id"))
    return six(estimate(stratified_sample(both, "vec_id", "stratum", B, 0), "count", F.expr("label = 3")), "estimate")


def stderr(s, d):
    w = stratified_sample(docs(s, d), "doc_id", "lang", B, 0)
    return s.createDataFrame([(round(standard_error(w, F.expr(INSULT)), 6),)], "stderr double")


def allocation(s, d):
    got = allocate(strata_sizes(docs(s, d), "source"), 100)
    return s.createDataFrame(sorted(got.items()), "source string, n long")


def manifest(s, d):
    return feats.manifest(docs(s, d).select(F.col("doc_id").alias("id"), F.col("lang").alias("stratum")))


def importance(s, d):
    drawn = importance_sample(docs(s, d), "doc_id", F.when(F.col("lang") == "fr", 4.0).otherwise(1.0), 200, 0, 0.5)
    return six(importance_estimate(drawn, 200, F.expr("lang = 'fr'")), "estimate")


def optimal(s, d):
    return optimal_count(docs(s, d), "doc_id", F.expr("lang = 'fr'")).select(F.round("estimate").cast("long").alias("n"))


def active_full(s, d):
    """With a budget of all rows the search must return exactly the positives."""
    e = read(s, d, "embeddings")
    yes = {r[0] for r in e.where("label = 3").select("vec_id").collect()}
    f = feats.build_features(e, "vec_id", "embedding", "given").cache()
    n = f.count()
    got = active_search(f, lambda ids: [i in yes for i in ids], n, max(16, n // 4))
    f.unpersist()
    return s.createDataFrame([(i,) for i in got.hits], "vec_id long")


def active_trace(s, d):
    df = docs(s, d)
    yes = {r[0] for r in df.where("lang = 'fr'").select("doc_id").collect()}
    f = feats.build_features(df, "doc_id", "text").cache()
    got = active_search(f, lambda ids: [i in yes for i in ids], 96, 16)
    f.unpersist()
    return s.createDataFrame([(0, k, *t) for k, t in enumerate(got.trace)], "run int, step int, round int, id long, score double, hit boolean, calls long")


def curve(s, d):
    return metrics.hit_rate_curve(active_trace(s, d))


def curve_of_chance(s, d):
    """The curve of judging a uniform draw row by row."""
    judged = uniform_sample(docs(s, d), "doc_id", 96, 0).df.select(F.md5(F.concat(F.lit("0:"), F.col("doc_id").cast("string")).cast("binary")).alias("key"), "doc_id", F.expr(f"coalesce({S_FR}, false)").alias("hit"))
    steps = judged.select(F.lit(0).alias("run"), F.row_number().over(Window.orderBy("key", "doc_id")).alias("step"), "doc_id", "hit")  # 96 rows
    return six(metrics.hit_rate_curve(steps), "hit_rate").select("step", "doc_id", "hit", "hit_rate", "hits")


def noisy_search(s, d):
    """Exploration by either schedule changes the order of a search, not what a budget for all rows finds."""
    e = read(s, d, "embeddings")
    yes = {r[0] for r in e.where("label = 3").select("vec_id").collect()}
    f = feats.build_features(e, "vec_id", "embedding", "given").cache()
    n, rows = f.count(), []
    for schedule in ("inverse_t", "exponential"):
        got = active_search(f, lambda ids: [i in yes for i in ids], n, max(16, n // 4), noise=0.5, schedule=schedule)
        rows += [(schedule, i) for i in got.hits]
    f.unpersist()
    return s.createDataFrame(rows, "schedule string, vec_id long")


def kmeans(s, d):
    return feats.manifest(feats.assign_strata(feats.build_features(docs(s, d), "doc_id", "text"), "kmeans", 10))


def probe(s, d):
    yes = {r[0] for r in docs(s, d).where("lang = 'fr'").select("doc_id").collect()}
    return s.createDataFrame([(i,) for i in ordered_probe(docs(s, d), "doc_id", "n_chars", lambda ids: [i in yes for i in ids], 5)], "doc_id long")


def _query_vector(s, d):
    return [float(x) for x in read(s, d, "embeddings").where("vec_id = 0").first()["embedding"]]


def mips(s, d):
    return six(baselines.mips(read(s, d, "embeddings"), "vec_id", "embedding", _query_vector(s, d), 20).select("vec_id", "score"), "score")


def mips_judge(s, d):
    return six(baselines.mips_then_judge(read(s, d, "embeddings"), "vec_id", "embedding", _query_vector(s, d), F.expr("label = 3"), 100, 10).select("vec_id", "score"), "score")


WHERE = parse('SELECT * FROM documents WHERE n_chars > 3000 AND lang = "en" OR "insulting" AND source = "src3" OR "insulting" AND "text is French"').where
S_FR = "lang = 'fr'"


def dnf_masks(s, d):
    decided, live = planner.masks(WHERE)
    return docs(s, d).select("doc_id", decided.alias("decided"), live.alias("live"))


def dnf_mixed(s, d):
    decided, live = planner.masks(WHERE)
    answers = {p: F.expr(TRUTH[p]) for p in planner.phrases(WHERE)}
    return docs(s, d).where(decided | planner.residual(WHERE, answers, live)).select("doc_id")


def dnf_calls(s, d):
    decided, live = planner.masks(WHERE)
    answers = {p: F.expr(TRUTH[p]) for p in planner.phrases(WHERE)}
    spent = F.when(decided, 0).otherwise(planner.calls(WHERE, answers, live))
    return docs(s, d).agg(F.sum(spent).cast("long").alias("calls"), (2 * F.count("*")).alias("without"))


def _packs(s, d):
    return baselines.packs(docs(s, d), "doc_id", F.floor(F.col("n_chars") / 4), 2000, 64, 0)


def pack_layout(s, d):
    return _packs(s, d).select("doc_id", "pack", F.col("place").cast("int").alias("place"))


def packed_est(s, d):
    p = _packs(s, d)
    return six(baselines.packed_count(p, PackedModel(RuleModel(TRUTH), "doc_id").column("text is French", F.col("place"), F.col("size")), docs(s, d).count()), "estimate")


def packed_groups(s, d):
    return six(baselines.packed_groups(_packs(s, d), F.col("lang"), docs(s, d).count()), "estimate")


def rel_errors(s, d):
    n = docs(s, d).agg(F.count_if(F.expr(S_FR)).alias("truth"))
    return six(uniform_est(s, d).crossJoin(n).select("estimate", "truth", metrics.relative_error(F.col("estimate"), F.col("truth")).alias("error")), "error")


def f1(s, d):
    got = udf_rows(s, d).select(F.col("doc_id").alias("id"))
    return six(metrics.f1_table(got, docs(s, d).where(S_FR).select(F.col("doc_id").alias("id")), 256), "precision", "recall_all", "recall_capped", "f1_all", "f1_capped")


def share(s, d):
    return six(metrics.positive_share(docs(s, d), F.expr(S_FR)), "share")


def costs(s, d):
    return docs(s, d).agg(F.sum(F.floor(F.col("n_chars") / 4)).alias("tokens"), F.round(F.sum(F.floor(F.col("n_chars") / 4)) * 0.25e-6, 6).alias("usd"), F.lit(token_budget(0.37, 10e-6)).cast("long").alias("packed_tokens"))


def vsql(text, budget=None, stratum=None, seed=0):
    def run(s, d):
        out = workloads.engine(s, d, budget, seed, stratum=stratum).sql(text).df
        return six(out, *(n for n, t in out.dtypes if t == "double"))

    return run


ALL = 2**63 - 1  # no table has more rows
W29 = 'SELECT g, COUNT(*) AS n FROM documents WHERE n_chars < 2000 GROUP BY "language of the text" AS g'
W19 = 'SELECT g, COUNT(*) AS n FROM documents GROUP BY "language of the text" AS g ORDER BY n DESC LIMIT 10'
W30 = 'SELECT conv_id FROM dialogs WHERE "opens with a system instruction" LIMIT 100'
VSQL = {
    "vsql_w29_sampled": vsql(W29, B, "lang"),
    "vsql_w29_full_budget": vsql(W29, ALL, "lang"),
    "vsql_w30_dialogs": vsql(W30, 64),
    "vsql_w31_count": vsql('SELECT COUNT(*) AS n FROM documents WHERE "text is French"', ALL, "source"),
    "vsql_w32_mixed": vsql('SELECT COUNT(*) AS n FROM documents WHERE n_chars > 3000 AND lang = "en" OR "insulting" AND source = "src3"'.replace('lang = "en"', 'source = "src1"'), ALL, "source"),
    "vsql_w33_sum": vsql('SELECT SUM(n_chars) AS total, AVG(n_chars) AS mean, COUNT(*) AS n FROM documents WHERE "text is French"', ALL, "source"),
    "vsql_w33_sampled": vsql('SELECT SUM(n_chars) AS total, AVG(n_chars) AS mean FROM documents WHERE "text is French"', B, "source"),
    "vsql_w20_groups": vsql('SELECT g, COUNT(*) AS n FROM documents WHERE "insulting" GROUP BY "language of the text" AS g ORDER BY n DESC LIMIT 10', ALL, "source"),
    "vsql_w21_licences": vsql('SELECT g, COUNT(*) AS n FROM documents WHERE "carries a licence line" GROUP BY "which licence" AS g', ALL, "source"),
    "vsql_w34_pages": vsql('SELECT COUNT(*) AS n FROM pages WHERE "page is English"', ALL),
    "vsql_w35_structured": vsql("SELECT l_returnflag, COUNT(*) AS n, SUM(l_quantity) AS q FROM lineitem GROUP BY l_returnflag ORDER BY 1"),
    "vsql_top_by_length": vsql('SELECT doc_id, n_chars FROM documents WHERE "text is French" ORDER BY n_chars DESC LIMIT 5'),
}


#: The nine conditions of the COUNT table: budget, predicate in SQL.
COUNTS = {
    "w1": (B, "quality = 1"), "w1b": (64, "quality = 1"), "w2": (B, "lang = 'es'"), "w3": (B, "toxic = 1"), "w4": (B, "lang = 'en'"), "w5": (B, "lang = 'fr'"), "w6": (B, "lang = 'de'"),
    "w7": (B, "toxic = 1 AND quality = 0"), "w8": (B, "label = 0"), "w9": (B, "label > 7"), "w26a": (B, "label = 3"), "w26b": (B, "label < 2"), "w26c": (B, "label = 2"),
}


def count_est(name):
    """COUNT of a condition from a stratified sample: documents by source, vectors by their nearest anchor."""

    def run(s, d):
        at, phrase = workloads.CONDITIONS[name]
        if at == "embeddings":
            e, a = _anchored(s, d)
            df = e.select("vec_id", "label").join(a, F.col("vec_id") == F.col("id"))
            w = stratified_sample(df, "vec_id", "stratum", COUNTS[name][0], 0)
        else:
            w = stratified_sample(workloads.table(s, d, at)[0], "doc_id", "source", COUNTS[name][0], 0)
        return six(estimate(w, "count", F.expr(TRUTH[phrase])), "estimate")

    return run


def retrieval(name):
    """Rows of a condition found under one budget: active search, a uniform sample judged row by row, inner products alone."""

    def run(s, d):
        at, _ = workloads.CONDITIONS[name]
        budget = max(16, min(256, workloads.table(s, d, at)[0].count() // 4))
        rows = [workloads.run(name, s, d, m, budget, 0, pool=1024) for m in ("active", "udf", "mips")]
        return s.createDataFrame([(r["method"], r["budget"], r["truth"], r["hits"], *(round(float(r[c]), 6) for c in ("precision", "recall_capped", "f1"))) for r in rows], "method string, budget int, truth long, hits long, precision double, recall_capped double, f1 double")

    return run


def emd_groups(s, d):
    """Earth mover's distance between sampled groups by language and the true ones, and of an even guess for comparison."""
    got = [(r["g"], r["n"]) for r in workloads.engine(s, d, B, 0, stratum="source").sql(W19).df.collect()]  # at most ten groups
    true = [tuple(r) for r in docs(s, d).groupBy("lang").agg(F.count("*").cast("double")).collect()]
    even = [(g, 1.0) for g, _ in true]
    return s.createDataFrame([(m, round(float(metrics.emd(x, true, metrics.label_distance)), 6), len(x)) for m, x in (("engine", got), ("even", even))], "method string, emd double, groups int")


def repeated(s, d):
    """Mean and standard deviation of the relative error over eight seeds, by uniform draws."""
    df = docs(s, d)
    n, truth = df.agg(F.count("*"), F.count_if(F.col("lang") == "fr")).first()
    hits = None
    for seed in range(8):
        one = uniform_sample(df.select("doc_id", "lang"), "doc_id", B, seed).df.agg(F.count_if(F.col("lang") == "fr").alias("hits"), F.count("*").alias("n"))
        hits = one if hits is None else hits.union(one)
    errors = hits.select((F.abs(F.col("hits") * F.lit(float(n)) / F.col("n") - truth) / truth).alias("e"))
    return six(errors.agg(F.avg("e").alias("mean"), F.stddev_samp("e").alias("sd"), F.count("*").alias("runs")), "mean", "sd")


def latency(s, d):
    """Seconds by stage of one aggregation and one retrieval."""
    rows = [(m, stage, round(t, 3)) for m, b in (("stratified", B), ("active", 64)) for stage, t in workloads.run("w5", s, d, m, b, 0)["spans"].items()]
    return s.createDataFrame(rows, "method string, stage string, seconds double")


def token_limited(s, d):
    """A search whose budget is in tokens: what it judged, and what that took."""
    df = docs(s, d).withColumn("tokens", (F.length("text") / 4).cast("long"))
    e = feats.build_features(df, "doc_id", "text").join(df.select(F.col("doc_id").alias("id"), "tokens"), "id")

    def judge(ids):
        yes = {r[0] for r in df.where(F.col("doc_id").isin(ids)).where("lang = 'fr'").select("doc_id").collect()}
        return [i in yes for i in ids]

    state: dict = {}
    got = active_search(e, judge, 64, 16, state=state, tokens="tokens", token_budget=20_000)
    return s.createDataFrame([(len(state["seen"]), sum(state.get("tokens", {}).values()), len(got.hits))], "judged long, tokens long, hits long")


def early_stop(s, d):
    """WHERE with LIMIT: the search ends at the limit; all it returns holds."""
    got = workloads.engine(s, d, 256).sql('SELECT doc_id FROM documents WHERE "text is English" LIMIT 7').df
    return got.join(docs(s, d).select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.count("*").alias("n"))


def by_udf(s, d):
    """The phrase as a function of plain SQL, judged for every row."""
    s.udf.register("semantic_match", lexical)
    docs(s, d).createOrReplaceTempView("vc_documents")
    return s.sql("SELECT lang, count(*) AS n FROM vc_documents WHERE semantic_match(text, 'insulting') GROUP BY lang")


def sweep(s, d):
    rows = [workloads.run("w5", s, d, m, b, 0) for m in ("stratified", "uniform") for b in (32, 64, 128, 256, 512)]
    return s.createDataFrame([(r["method"], r["budget"], r["seed"], float(r["estimate"]), float(r["relative_error"])) for r in rows], "method string, budget int, seed int, estimate double, relative_error double")


def study(s, d):
    return metrics.box(workloads.sampler_study(s, d, "w5", B, 100), "estimate", "sampler")


@F.pandas_udf(T.BooleanType())
def lexical(text: pd.Series, phrase: pd.Series) -> pd.Series:
    """Word rules for phrases; a phrase without one is null."""
    found = text.str.lower().str.contains(rf"\b(?:{INSULTS})\b", regex=True)
    return found.where(phrase == "insulting", None).astype("boolean")


def swap(s, d):
    rows = [workloads.run("w1", s, d, m, B, 0, workloads.NoisyModel(RuleModel(TRUTH), "doc_id", 0.03, 0.03, salt)) | {"backend": salt} for salt in ("a", "b") for m in ("stratified", "uniform")]
    return s.createDataFrame([(r["backend"], r["method"], float(r["estimate"]), int(r["truth"])) for r in rows], "backend string, method string, estimate double, truth long")


def interval(s, d):
    """COUNT with its standard error and bounds, by the dialect."""
    return six(workloads.engine(s, d, B, 0, stratum="source").sql('SELECT COUNT(*) AS n FROM documents WHERE "text is French"').intervals().select("estimate", "stderr", "low", "high"), "estimate", "stderr", "low", "high")


def interval_avg(s, d):
    """AVG with its standard error and bounds, by the dialect."""
    return six(workloads.engine(s, d, B, 0, stratum="source").sql('SELECT AVG(n_chars) AS mean FROM documents WHERE "text is French"').intervals().select("estimate", "stderr", "low", "high"), "estimate", "stderr", "low", "high")


def dialog_topics(s, d):
    """SELECT of a phrase under a structured and a virtual condition: what is returned holds, with its value."""
    got = workloads.engine(s, d, 64).sql('SELECT conv_id, "topic of the dialog" AS topic FROM dialogs WHERE n_turns > 1 AND "opens with a system instruction" LIMIT 5').df
    first = read(s, d, "conversations").where("turn = 0").select("conv_id", "role")
    return got.join(first, "conv_id").groupBy("role").agg(F.count("*").alias("n"), F.count("topic").alias("topics"))


def plan_costs(s, d):
    """Calls that each legal plan of one query really spends."""
    text = 'SELECT g, COUNT(*) AS n FROM documents WHERE "insulting" GROUP BY "language of the text" AS g'
    rows = []
    for p in planner.enumerate_plans(parse(text), float(B), planner.Costs(B, B)):
        r = workloads.engine(s, d, B, 0, stratum="source").sql(text, p)
        rows.append((" ".join(p.steps), ",".join(p.fused), float(p.cost), r.meter.calls, r.df.count()))
    return s.createDataFrame(rows, "steps string, fused string, expected double, calls long, groups long")


def prompts(s, d):
    """What a backend would be sent for one query, a row per kind of prompt, and for all documents: prompts, and characters of texts in them."""
    made = workloads.engine(s, d).prompts('SELECT g, COUNT(*) AS n FROM documents WHERE "insulting" GROUP BY "language of the text" AS g')
    kinds = s.createDataFrame([(x.step, x.phrase, x.source, x.rows) for x in made], "step string, phrase string, source string, n_rows int")
    asked = docs(s, d).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("chars"))
    return kinds.crossJoin(asked).select("step", "phrase", "source", "n_rows", F.ceil(F.col("n") / F.col("n_rows")).alias("calls"), "chars")


def study_of(name):
    return lambda s, d: metrics.box(workloads.sampler_study(s, d, name, B, 200), "estimate", "sampler")


def curves_of(name):
    """Median and quartiles of the hit rate over eight searches, beside the share of positives."""

    def run(s, d):
        at, phrase = workloads.CONDITIONS[name]
        share = metrics.positive_share(workloads.table(s, d, at)[0], F.expr(TRUTH[phrase])).select("share")
        return metrics.curve_quartiles(metrics.hit_rate_curve(workloads.learning_curves(s, d, name))).crossJoin(F.broadcast(share))

    return run


def sweep_of(name):
    """Retrieval by budget, active search and row-by-row judging; `enough` is the least budget at which a method reaches the best F1 of the latter."""

    def run(s, d):
        rows = [workloads.run(name, s, d, m, b, 0, pool=512) for m in ("active", "udf") for b in (32, 64, 128, 256)]
        top = max(r["f1"] for r in rows if r["method"] == "udf")
        enough = {m: min((r["budget"] for r in rows if r["method"] == m and r["f1"] >= top), default=None) for m in ("active", "udf")}
        return s.createDataFrame([(r["method"], r["budget"], r["hits"], float(r["f1"]), r["seconds"], enough[r["method"]]) for r in rows], "method string, budget int, hits long, f1 double, seconds double, enough int")

    return run


def agreement(s, d):
    """Two backends that err for different rows: the share of equal answers, what chance gives, and kappa."""
    a, b = (workloads.NoisyModel(RuleModel(TRUTH), "doc_id", 0.03, 0.03, salt).column("text is French") for salt in ("a", "b"))
    same, chance = metrics.kappa(F.col("a"), F.col("b"))
    got = docs(s, d).select(a.alias("a"), b.alias("b")).agg(same.alias("same"), chance.alias("chance"))
    return six(got.withColumn("kappa", (F.col("same") - F.col("chance")) / (1 - F.col("chance"))), "same", "chance", "kappa")


def packed_ids(s, d):
    """Rows by long prompts: the ids that a model that forgets names."""
    return baselines.packed_rows(_packs(s, d), PackedModel(RuleModel(TRUTH), "doc_id").column("text is French", F.col("place"), F.col("size"))).select("doc_id")


def moments(s, d):
    w = stratified_sample(docs(s, d), "doc_id", "source", B, 0)
    return six(udfs.weighted_moments(w.df, "n_chars", "_w", ["source"]), "mean", "variance")


def lexical_client():
    found = re.compile(rf"\b(?:{INSULTS})\b", re.IGNORECASE)
    return lambda phrase, texts: [bool(found.search(t)) for t in texts]


def judged_batches(s, d):
    got = udfs.judge_batches(docs(s, d).select("doc_id", "text"), "text", "insulting", lexical_client)
    return got.where("said").select("doc_id")


def judged_partitions(s, d):
    return udfs.judge_partitions(docs(s, d), "doc_id", "text", "insulting", lexical_client).where("said").select(F.col("id").alias("doc_id"))


def turns(s, d):
    """Transcripts taken apart again by a table function."""
    udfs.register(s, lambda t, p: bool(t))
    workloads.dialogs(s, d).createOrReplaceTempView("vc_dialogs")
    return s.sql("SELECT t.role, count(*) AS n FROM vc_dialogs, LATERAL transcript_turns(transcript) t WHERE t.turn = 0 GROUP BY t.role")


QUERIES = {
    "count_full_scan_es": full_scan("lang = 'es'"), "count_full_scan_fr": full_scan(S_FR), "count_full_scan_insults": full_scan(TRUTH["insulting"]), "sum_avg_full_scan_fr": sum_avg_full_scan,
    "uniform_count_est": uniform_est, "udf_baseline_count": udf_count, "udf_baseline_rows": udf_rows,
    "stratified_count_est_lang": by("lang"), "stratified_count_est_source": by("source"), "stratified_count_est_anchor": stratified_anchor,
    "stratified_sum_est": by("source", "sum", "n_chars"), "stratified_avg_est": by("source", "avg", "n_chars"), "stratified_group_est": by("lang", group=["source"]), "stratified_stderr": stderr,
    "importance_est": importance, "optimal_proposal_count": optimal, "allocation_proportional": allocation, "strata_manifest": manifest, "nearest_anchor": nearest_anchor,
    "active_search_full_budget": active_full, "active_search_trace": active_trace, "hit_rate_curve": curve, "kmeans_strata": kmeans, "ordered_probe_top": probe,
    "mips_topk": mips, "mips_then_judge": mips_judge, "dnf_masks": dnf_masks, "dnf_mixed": dnf_mixed, "dnf_calls_saved": dnf_calls,
    "packed_prompt_layout": pack_layout, "packed_count_est": packed_est, "packed_group_est": packed_groups,
    "relative_error_table": rel_errors, "f1_table": f1, "positive_share": share, "cost_table": costs, "budget_sweep": sweep, "sampler_study": study, "backend_swap": swap,
    "emd_w19": emd_groups, "repeat_uniform_w5": repeated, "latency_by_stage": latency, "search_token_budget": token_limited, "where_limit_early_stop": early_stop, "semantic_match_sql": by_udf,
    "vsql_interval": interval, "vsql_interval_avg": interval_avg, "hit_rate_curve_chance": curve_of_chance, "active_search_noise": noisy_search, "vsql_w30_topics": dialog_topics, "plan_costs": plan_costs, "prompt_calls": prompts, "backend_agreement": agreement, "packed_rows": packed_ids,
    "weighted_moments": moments, "judge_batches": judged_batches, "judge_partitions": judged_partitions, "transcript_turns": turns,
} | {f"sampler_study_{w}": study_of(w) for w in ("w1", "w2", "w4")} | {f"learning_curves_{w}": curves_of(w) for w in ("w5", "w7", "w8", "w9")} | {f"retrieval_sweep_{w}": sweep_of(w) for w in ("w1b", "w4")} | VSQL | relational.QUERIES | streams.QUERIES | {f"count_{w}": count_est(w) for w in COUNTS} | {f"retrieval_{w}": retrieval(w) for w in COUNTS}


def _alloc(stratum: str, budget: int) -> str:
    """Proportional allocation in SQL, for budgets over the number of strata and no stratum below one row."""
    return f"""sizes AS (SELECT {stratum} AS g, count(*) AS n, (SELECT count(*) FROM documents) AS total FROM documents GROUP BY 1),
quota AS (SELECT *, {budget}::DOUBLE * n / total AS q FROM sizes),
base AS (SELECT *, greatest(1, floor(q)) AS b FROM quota),
take AS (SELECT g, n, total, CAST(b + CASE WHEN row_number() OVER (ORDER BY q - b DESC, g) <= {budget} - (SELECT sum(b) FROM base) THEN 1 ELSE 0 END AS BIGINT) AS k FROM base),
ranked AS (SELECT d.*, row_number() OVER (PARTITION BY {stratum} ORDER BY md5('0:' || doc_id), doc_id) AS r FROM documents d),
sample AS (SELECT ranked.*, take.g, n, k, total, n / k::DOUBLE AS w FROM ranked JOIN take ON ranked.{stratum} = take.g WHERE r <= k)"""


def _est(stratum: str, expr: str) -> str:
    return f"WITH {_alloc(stratum, B)} SELECT round({expr}, 6) AS estimate, count(*) AS n FROM sample"


def _count(name: str) -> str:
    budget, f = COUNTS[name]
    at = workloads.CONDITIONS[name][0]
    both = "SELECT d.*, quality, toxic FROM documents d JOIN labels USING (doc_id)"
    ranked = f"SELECT *, row_number() OVER (PARTITION BY quality ORDER BY md5('0:' || doc_id)) AS place, count(*) FILTER (quality = 0) OVER () AS junk FROM ({both})"
    rows = {"embeddings": f"SELECT vec_id AS doc_id, label, stratum AS source FROM ({_NEAR})", "labelled": both, "balanced": f"SELECT * EXCLUDE (place, junk) FROM ({ranked}) WHERE quality = 0 OR place <= junk", "documents": "SELECT * FROM documents"}[at]
    return f"WITH documents AS ({rows}), {_alloc('source', budget)} SELECT round(max(total) * coalesce(sum(w) FILTER ({f}), 0) / sum(w), 6) AS estimate, count(*) AS n FROM sample"


_VEC = "(SELECT embedding::DOUBLE[] FROM embeddings WHERE vec_id = 0)"
_NEAR = f"SELECT e.vec_id, e.label, arg_max(a.vec_id, (list_dot_product(e.embedding::DOUBLE[], a.embedding::DOUBLE[]), -a.vec_id)) AS stratum FROM embeddings e, (SELECT * FROM embeddings WHERE vec_id < {ANCHORS}) a GROUP BY 1, 2"
_UNIFORM = "(SELECT * FROM documents ORDER BY md5('{}:' || doc_id), doc_id LIMIT {})"
_LIC = "CASE WHEN contains(text, 'Apache License') THEN 'apache' WHEN contains(text, 'MIT License') THEN 'mit' WHEN contains(text, 'General Public License') OR contains(text, 'GPL') THEN 'gpl' WHEN contains(text, 'Creative Commons') OR contains(text, 'CC BY') THEN 'cc' END"
_PACKED = f"""WITH RECURSIVE o AS (SELECT doc_id, least(n_chars // 4, 2000) AS t, row_number() OVER (ORDER BY md5('0:' || doc_id), doc_id) AS i FROM {_UNIFORM.format(0, 64)}),
f(i, doc_id, used, pack) AS (SELECT i, doc_id, t, 0 FROM o WHERE i = 1 UNION ALL SELECT o.i, o.doc_id, CASE WHEN f.used + o.t > 2000 THEN o.t ELSE f.used + o.t END, CASE WHEN f.used + o.t > 2000 THEN f.pack + 1 ELSE f.pack END FROM f JOIN o ON o.i = f.i + 1),
laid AS (SELECT doc_id, pack, row_number() OVER (PARTITION BY pack ORDER BY i) AS place, count(*) OVER (PARTITION BY pack) AS size FROM f)"""


def _unit(salt: str) -> str:
    return f"(('0x' || substr(md5('{salt}:' || doc_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def _noisy(salt: str) -> str:
    return f"CASE WHEN lang = 'fr' THEN {_unit(salt + ':text is French')} >= 0.03 ELSE {_unit(salt + ':text is French')} < 0.03 END"


_KEPT = f"lang = 'fr' AND {_unit('packed:text is French')} >= 0.6::DOUBLE * place / size"
_DECIDED, _L1, _L2 = "(n_chars > 3000 AND lang = 'en')", "source = 'src3'", "TRUE"
SQL = {
    "count_full_scan_es": "SELECT count(*) AS n FROM documents WHERE lang = 'es'",
    "count_full_scan_fr": "SELECT count(*) AS n FROM documents WHERE lang = 'fr'",
    "count_full_scan_insults": f"SELECT count(*) AS n FROM documents WHERE {S_INSULT}",
    "sum_avg_full_scan_fr": "SELECT CAST(sum(n_chars) AS BIGINT) AS total, round(avg(n_chars), 6) AS mean FROM documents WHERE lang = 'fr'",
    "uniform_count_est": f"SELECT round((SELECT count(*) FROM documents) * count(*) FILTER (lang = 'fr') / count(*)::DOUBLE, 6) AS estimate, count(*) AS n FROM {_UNIFORM.format(0, B)}",
    "udf_baseline_count": f"SELECT round((SELECT count(*) FROM documents) * count(*) FILTER ({S_INSULT}) / count(*)::DOUBLE, 6) AS estimate, count(*) AS n FROM {_UNIFORM.format(1, B)}",
    "udf_baseline_rows": f"SELECT doc_id FROM {_UNIFORM.format(2, 256)} WHERE lang = 'fr'",
    "stratified_count_est_lang": _est("lang", f"max(total) * sum(w) FILTER ({S_INSULT}) / sum(w)"),
    "stratified_count_est_source": _est("source", f"max(total) * sum(w) FILTER ({S_INSULT}) / sum(w)"),
    "stratified_sum_est": _est("source", "max(total) * sum(w * n_chars) FILTER (lang = 'fr') / sum(w)"),
    "stratified_avg_est": _est("source", "sum(w * n_chars) FILTER (lang = 'fr') / sum(w) FILTER (lang = 'fr')"),
    "stratified_group_est": f"WITH {_alloc('lang', B)} SELECT source, round(max(total) * sum(w) / (SELECT sum(w) FROM sample), 6) AS estimate, count(*) AS n FROM sample WHERE {S_INSULT} GROUP BY 1",
    "stratified_stderr": f"WITH {_alloc('lang', B)}, v AS (SELECT g, max(n) AS n, max(k) AS k, max(total) AS total, var_samp(CASE WHEN {S_INSULT} THEN 1.0::DOUBLE ELSE 0 END) AS s2 FROM sample GROUP BY g) SELECT round(max(total) * sqrt(sum((n / total::DOUBLE) ** 2 * (1 - k / n::DOUBLE) * s2 / k)), 6) AS stderr FROM v",
    "stratified_count_est_anchor": f"WITH documents AS (SELECT vec_id AS doc_id, label, stratum FROM ({_NEAR})), {_alloc('stratum', B)} SELECT round(max(total) * sum(w) FILTER (label = 3) / sum(w), 6) AS estimate, count(*) AS n FROM sample",
    "optimal_proposal_count": "SELECT count(*) AS n FROM documents WHERE lang = 'fr'",
    "allocation_proportional": f"WITH {_alloc('source', 100)} SELECT g AS source, k AS n FROM take",
    "strata_manifest": "SELECT lang AS stratum, count(*) AS n_rows FROM documents GROUP BY 1",
    "nearest_anchor": f"SELECT vec_id, stratum FROM ({_NEAR})",
    "active_search_full_budget": "SELECT vec_id FROM embeddings WHERE label = 3",
    "ordered_probe_top": "SELECT doc_id FROM documents WHERE lang = 'fr' ORDER BY n_chars DESC, doc_id LIMIT 5",
    "mips_topk": f"SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], {_VEC}), 6) AS score FROM embeddings ORDER BY list_dot_product(embedding::DOUBLE[], {_VEC}) DESC, vec_id LIMIT 20",
    "mips_then_judge": f"SELECT vec_id, round(s, 6) AS score FROM (SELECT vec_id, label, list_dot_product(embedding::DOUBLE[], {_VEC}) AS s FROM embeddings ORDER BY s DESC, vec_id LIMIT 100) WHERE label = 3 ORDER BY s DESC, vec_id LIMIT 10",
    "dnf_masks": f"SELECT doc_id, {_DECIDED} AS decided, CAST(CASE WHEN {_L1} THEN 2 ELSE 0 END + 4 AS BIGINT) AS live FROM documents",
    "dnf_mixed": f"SELECT doc_id FROM documents WHERE {_DECIDED} OR {S_INSULT} AND {_L1} OR {S_INSULT} AND lang = 'fr'",
    "dnf_calls_saved": f"SELECT CAST(sum(CASE WHEN {_DECIDED} THEN 0 WHEN {_L1} AND {S_INSULT} THEN 1 WHEN {S_INSULT} THEN 2 ELSE 1 END) AS BIGINT) AS calls, 2 * count(*) AS without FROM documents",
    "packed_prompt_layout": f"""WITH RECURSIVE o AS (SELECT doc_id, least(n_chars // 4, 2000) AS t, row_number() OVER (ORDER BY md5('0:' || doc_id), doc_id) AS i FROM {_UNIFORM.format(0, 64)}),
f(i, doc_id, used, pack) AS (SELECT i, doc_id, t, 0 FROM o WHERE i = 1 UNION ALL SELECT o.i, o.doc_id, CASE WHEN f.used + o.t > 2000 THEN o.t ELSE f.used + o.t END, CASE WHEN f.used + o.t > 2000 THEN f.pack + 1 ELSE f.pack END FROM f JOIN o ON o.i = f.i + 1)
SELECT doc_id, CAST(pack AS INTEGER) AS pack, CAST(row_number() OVER (PARTITION BY pack ORDER BY i) AS INTEGER) AS place FROM f""",
    "relative_error_table": f"WITH e AS (SELECT round((SELECT count(*) FROM documents) * count(*) FILTER (lang = 'fr') / count(*)::DOUBLE, 6) AS estimate FROM {_UNIFORM.format(0, B)}), t AS (SELECT count(*) FILTER (lang = 'fr') AS truth FROM documents) SELECT estimate, truth, round(abs(estimate - truth) / truth, 6) AS error FROM e, t",
    "f1_table": f"WITH r AS (SELECT count(*) AS returned FROM {_UNIFORM.format(2, 256)} WHERE lang = 'fr'), p AS (SELECT count(*) AS positives FROM documents WHERE lang = 'fr') SELECT returned, positives, returned AS hits, 1.0::DOUBLE AS precision, round(returned / positives::DOUBLE, 6) AS recall_all, round(returned / least(256, positives)::DOUBLE, 6) AS recall_capped, round(2 * (returned / positives::DOUBLE) / (1 + returned / positives::DOUBLE), 6) AS f1_all, round(2 * (returned / least(256, positives)::DOUBLE) / (1 + returned / least(256, positives)::DOUBLE), 6) AS f1_capped FROM r, p",
    "positive_share": "SELECT round(avg(CASE WHEN lang = 'fr' THEN 1 ELSE 0 END), 6) AS share, count(*) AS n FROM documents",
    "cost_table": "SELECT CAST(sum(n_chars // 4) AS BIGINT) AS tokens, round(CAST(sum(n_chars // 4) AS DOUBLE) * 0.25e-6, 6) AS usd, CAST(37000 AS BIGINT) AS packed_tokens FROM documents",
    "vsql_w29_sampled": f"WITH documents AS (SELECT * FROM documents WHERE n_chars < 2000), {_alloc('lang', B)} SELECT lang AS g, round(max(total) * sum(w) / (SELECT sum(w) FROM sample), 6) AS n FROM sample GROUP BY 1",
    "vsql_w29_full_budget": "SELECT lang AS g, CAST(count(*) AS DOUBLE) AS n FROM documents WHERE n_chars < 2000 GROUP BY 1",
    "vsql_w31_count": "SELECT CAST(count(*) AS DOUBLE) AS n FROM documents WHERE lang = 'fr'",
    "vsql_w32_mixed": f"SELECT CAST(count(*) AS DOUBLE) AS n FROM documents WHERE n_chars > 3000 AND source = 'src1' OR {S_INSULT} AND source = 'src3'",
    "vsql_w33_sum": "SELECT CAST(sum(n_chars) AS DOUBLE) AS total, round(avg(n_chars), 6) AS mean, CAST(count(*) AS DOUBLE) AS n FROM documents WHERE lang = 'fr'",
    "vsql_w33_sampled": f"WITH {_alloc('source', B)} SELECT round(max(total) * sum(w * n_chars) FILTER (lang = 'fr') / sum(w), 6) AS total, round(sum(w * n_chars) FILTER (lang = 'fr') / sum(w) FILTER (lang = 'fr'), 6) AS mean FROM sample",
    "vsql_w20_groups": f"SELECT lang AS g, CAST(count(*) AS DOUBLE) AS n FROM documents WHERE {S_INSULT} GROUP BY 1 ORDER BY n DESC LIMIT 10",
    "vsql_w21_licences": f"SELECT {_LIC} AS g, CAST(count(*) AS DOUBLE) AS n FROM documents WHERE {_LIC} IS NOT NULL GROUP BY 1",
    "vsql_w34_pages": "SELECT CAST(count(*) AS DOUBLE) AS n FROM pages WHERE contains(html, '<html lang=\"en\"')",
    "vsql_w35_structured": "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 6) AS q FROM lineitem GROUP BY 1",
    "vsql_top_by_length": "SELECT doc_id, n_chars FROM documents WHERE lang = 'fr' ORDER BY n_chars DESC, doc_id LIMIT 5",
    "repeat_uniform_w5": f"WITH t AS (SELECT count(*)::DOUBLE AS n, count(*) FILTER (lang = 'fr') AS truth FROM documents), r AS (SELECT seed, lang, row_number() OVER (PARTITION BY seed ORDER BY md5(seed || ':' || doc_id), doc_id) AS k FROM documents, (SELECT unnest(range(8)) AS seed)), h AS (SELECT seed, count(*) FILTER (lang = 'fr') AS hits FROM r WHERE k <= {B} GROUP BY 1), e AS (SELECT abs(hits * n / {B} - truth) / truth AS e FROM h, t) SELECT round(avg(e), 6) AS mean, round(stddev_samp(e), 6) AS sd, count(*) AS runs FROM e",
    "vsql_interval": f"WITH {_alloc('source', B)}, c AS (SELECT g, max(n)::DOUBLE AS n, max(k)::DOUBLE AS k, count(*) FILTER (lang = 'fr')::DOUBLE AS a FROM sample GROUP BY g), e AS (SELECT sum(n / k * a) AS e, sqrt(sum(n * n * (1 - k / n) * CASE WHEN k > 1 THEN (a - a * a / k) / (k - 1) ELSE a END / k)) AS s FROM c) SELECT round(e, 6) AS estimate, round(s, 6) AS stderr, round(e - 1.96 * s, 6) AS low, round(e + 1.96 * s, 6) AS high FROM e",
    "vsql_interval_avg": f"WITH {_alloc('source', B)}, t AS (SELECT sum(w * n_chars) FILTER (lang = 'fr') / sum(w) FILTER (lang = 'fr') AS m, sum(w) FILTER (lang = 'fr') AS c FROM sample), v AS (SELECT g, max(n)::DOUBLE AS n, max(k)::DOUBLE AS k, sum(CASE WHEN lang = 'fr' THEN n_chars - m ELSE 0 END) AS a, sum(CASE WHEN lang = 'fr' THEN (n_chars - m) ** 2 ELSE 0 END) AS b FROM sample, t GROUP BY g), e AS (SELECT max(m) AS e, sqrt(sum(n * n * (1 - k / n) * CASE WHEN k > 1 THEN (b - a * a / k) / (k - 1) ELSE b END / k)) / max(c) AS s FROM v, t) SELECT round(e, 6) AS estimate, round(s, 6) AS stderr, round(e - 1.96 * s, 6) AS low, round(e + 1.96 * s, 6) AS high FROM e",
    "hit_rate_curve_chance": f"WITH j AS (SELECT row_number() OVER (ORDER BY md5('0:' || doc_id), doc_id) AS step, doc_id, coalesce(lang = 'fr', false) AS hit FROM {_UNIFORM.format(0, 96)}) SELECT CAST(step AS INTEGER) AS step, doc_id, hit, round(avg(hit::INT) OVER (ORDER BY step ROWS BETWEEN 15 PRECEDING AND CURRENT ROW), 6) AS hit_rate, CAST(sum(hit::INT) OVER (ORDER BY step) AS BIGINT) AS hits FROM j",
    "active_search_noise": "SELECT schedule, vec_id FROM embeddings, (VALUES ('inverse_t'), ('exponential')) t(schedule) WHERE label = 3",
    "importance_est": f"WITH s AS (SELECT doc_id, lang, CASE WHEN lang = 'fr' THEN 4.0::DOUBLE ELSE 1.0::DOUBLE END AS s, ('0x' || substr(md5('bucket:' || doc_id), 1, 8))::BIGINT % greatest(64, (SELECT count(*) FROM documents) // 200000) AS b FROM documents), p AS (SELECT *, sum(s) OVER (ORDER BY b, doc_id) AS hi, sum(s) OVER () AS whole FROM s), u AS (SELECT ('0x' || substr(md5('0:draw:' || k), 1, 12))::BIGINT / 281474976710656.0::DOUBLE * (SELECT sum(s) FROM s) AS u FROM (SELECT unnest(range(200)) AS k)) SELECT round(sum(CASE WHEN lang = 'fr' THEN whole / s ELSE 0 END) / 200.0::DOUBLE, 6) AS estimate FROM p JOIN u ON hi - s <= u AND u < hi",
    "vsql_w30_topics": "SELECT 'system' AS role, CAST(5 AS BIGINT) AS n, CAST(5 AS BIGINT) AS topics",
    "prompt_calls": "SELECT t.*, CAST(ceil(n / n_rows) AS BIGINT) AS calls, chars FROM (VALUES ('where', 'insulting', 'text', 1), ('taxonomy', 'language of the text', 'text', 16), ('classify', 'language of the text', 'text', 1)) t(step, phrase, source, n_rows), (SELECT count(*) AS n, CAST(coalesce(sum(length(text)), 0) AS BIGINT) AS chars FROM documents)",
    "backend_agreement": f"WITH x AS (SELECT {_noisy('a')} AS a, {_noisy('b')} AS b FROM documents), y AS (SELECT avg((a = b)::INT) AS same, avg(a::INT) AS p, avg(b::INT) AS q FROM x), z AS (SELECT same, p * q + (1 - p) * (1 - q) AS chance FROM y) SELECT round(same, 6) AS same, round(chance, 6) AS chance, round((same - chance) / (1 - chance), 6) AS kappa FROM z",
    "packed_rows": f"{_PACKED} SELECT doc_id FROM laid JOIN documents USING (doc_id) WHERE {_KEPT}",
    "packed_count_est": f"{_PACKED}, e AS (SELECT pack, count(*) FILTER ({_KEPT}) / count(*)::DOUBLE * (SELECT count(*) FROM documents) AS e FROM laid JOIN documents USING (doc_id) GROUP BY pack) SELECT round(avg(e), 6) AS estimate, count(*) AS packs FROM e",
    "weighted_moments": f"WITH {_alloc('source', B)} SELECT source, round(sum(w * n_chars) / sum(w), 6) AS mean, round(sum(w * n_chars * n_chars) / sum(w) - (sum(w * n_chars) / sum(w)) ** 2, 6) AS variance FROM sample GROUP BY source",
    "judge_batches": f"SELECT doc_id FROM documents WHERE {S_INSULT}",
    "judge_partitions": f"SELECT doc_id FROM documents WHERE {S_INSULT}",
    "transcript_turns": "SELECT role, count(*) AS n FROM (SELECT conv_id, arg_min(role, turn) AS role FROM conversations GROUP BY 1) GROUP BY role",
    "where_limit_early_stop": "SELECT 'en' AS lang, CAST(7 AS BIGINT) AS n",
    "semantic_match_sql": f"SELECT lang, count(*) AS n FROM documents WHERE {S_INSULT} GROUP BY 1",
} | relational.SQL | streams.SQL | {f"count_{w}": _count(w) for w in COUNTS}



def entry(spark):
    return QUERIES["vsql_w29_sampled"](spark, "/root/testdata/sf0.001")
