import itertools
import math
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from virtcol import baselines, metrics, workloads
from virtcol.engine import Engine, TableInfo
from virtcol.index import features as feats
from virtcol.index.sample import allocate, draw, estimate, importance_estimate, importance_sample, optimal_count, standard_error, strata_sizes, uniform_sample
from virtcol.index.search import active_search, logistic, ordered_probe
from virtcol.model.base import CachedModel, RuleModel, parse_bool, parse_group_table, parse_index_list, parse_int
from virtcol.plans.planner import Costs

SF = "/root/testdata/sf0.01"


def tiny(spark):
    return spark.createDataFrame([(i, "aaaaabbc"[i], f, float(i)) for i, f in enumerate([1, 0, 1, 1, 0, 1, 0, 0])], "id long, g string, f int, x double")


@pytest.mark.parametrize("budget", [0, 1, 2, 3, 4, 7, 8, 13])
@pytest.mark.parametrize("rule", ["proportional", "equal", "neyman"])
def test_allocation_bounds(budget, rule):
    sizes = {"a": 5, "b": 2, "c": 1, "empty": 0}
    got = allocate(sizes, budget, rule)
    assert sum(got.values()) == min(budget, 8) and all(0 <= got[k] <= n for k, n in sizes.items())
    assert budget < 3 or all(got[k] >= 1 for k in "abc")


def test_worked_example(spark):
    w = draw(tiny(spark), "id", "g", {"a": 2, "b": 1, "c": 1})
    rows = w.df.collect()
    assert sorted(r["_w"] for r in rows) == [1.0, 2.0, 2.5, 2.5]
    by_hand = sum(r["_w"] * r["f"] for r in rows)
    assert math.isclose(estimate(w, "count", F.col("f") == 1).first()[0], by_hand)
    assert math.isclose(estimate(w, "count", F.col("f") == 1, normalize=False).first()[0], by_hand)


def test_unbiased_over_all_samples():
    groups = {"a": [1, 0, 1, 1, 0], "b": [1, 0], "c": [0]}
    take = {"a": 2, "b": 1, "c": 1}
    all_ = [Fraction(sum(Fraction(len(groups[k]), take[k]) * sum(s) for k, s in zip(groups, pick))) for pick in itertools.product(*(list(itertools.combinations(groups[k], take[k])) for k in groups))]
    assert sum(all_) / len(all_) == 4


def test_missed_stratum(spark):
    df = spark.createDataFrame([(i, 0 if i < 6 else 1, 1) for i in range(7)], "id long, g int, f int")
    w = draw(df, "id", "g", {0: 2})
    assert estimate(w, "count", F.col("f") == 1).first()[0] == 7 and estimate(w, "count", F.col("f") == 1, normalize=False).first()[0] == 6


def test_errors_and_empty(spark):
    w = draw(tiny(spark), "id", "g", {"a": 1, "b": 1, "c": 1})
    assert standard_error(w, F.col("f") == 1) >= 0
    none = uniform_sample(tiny(spark).limit(0), "id", 5)
    assert none.df.count() == 0
    assert estimate(uniform_sample(tiny(spark), "id", 5), "avg", F.lit(False), F.col("x")).first()[0] is None


def test_optimal_proposal_has_no_variance(spark):
    assert {round(optimal_count(tiny(spark), "id", F.col("f") == 1, seed).first()[0], 9) for seed in range(4)} == {4.0}
    got = [importance_estimate(importance_sample(tiny(spark), "id", F.col("x"), 50, s, 1.0), 50, F.col("f") == 1).first()[0] for s in range(12)]
    assert abs(np.mean(got) - 4) < 1.2


def test_search_invariants(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 8))
    y = x[:, 0] > 0.8
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, e array<float>").cache()
    judge = lambda ids: [bool(y[i]) for i in ids]
    a, b = (active_search(df, judge, 64, 16, seed=3) for _ in range(2))
    ids = [t[1] for t in a.trace]
    assert a.trace == b.trace and len(ids) == len(set(ids)) == 64 and all(y[i] for i in a.hits) and len(a.hits) > 2 * 64 * y.mean()
    assert len(active_search(df, judge, 64, 16, limit=5, seed=3).hits) == 5
    assert active_search(df, lambda i: [False] * len(i), 32).hits == [] and len(active_search(df, lambda i: [True] * len(i), 400).hits) == 300
    assert active_search(df.limit(0), judge, 10).hits == []
    w = logistic(x, y.astype(float))
    assert np.corrcoef(x @ w[:-1], y)[0, 1] > 0.7
    assert ordered_probe(df.withColumn("k", F.col("e")[1]), "id", "k", judge, 3) == [int(i) for i in np.argsort(-x[:, 1].astype(np.float32)) if y[i]][:3]


def test_stratified_beats_uniform(spark):
    box = {r["sampler"]: r for r in metrics.box(workloads.sampler_study(spark, SF, "w5", 128, 200), "estimate", "sampler").collect()}
    truth = workloads.truth("w5", spark, SF)
    assert box["stratified"]["variance"] < 0.5 * box["uniform"]["variance"]
    for r in box.values():
        assert abs(r["mean"] - truth) < 4 * math.sqrt(r["variance"] / 200)


def test_engine(spark):
    e = Engine(spark, RuleModel({"odd": "id % 2 = 1", "f": "f = 1"}), Costs(100, 100))
    e.register("t", tiny(spark), TableInfo("id", "g", labels={"group": "g"}, stratum="g"))
    r = e.sql('SELECT COUNT(*) AS n FROM t WHERE "odd" OR x > 6')
    assert r.df.first()["n"] == 4 and r.meter.calls == 7
    assert {tuple(x) for x in e.sql('SELECT k, COUNT(*) AS n FROM t WHERE "odd" GROUP BY "group" AS k').df.collect()} == {("a", 2.0), ("b", 1.0), ("c", 1.0)}
    assert e.table("t").where_semantic("f").count().df.first()["n"] == 4
    assert "cost" not in e.explain('SELECT * FROM t WHERE "odd" LIMIT 1') and "limit" in e.explain('SELECT * FROM t WHERE "odd" LIMIT 1')
    m = CachedModel(RuleModel({"f": "f = 1"}), "id")
    assert m.answers(tiny(spark), "f") == m.answers(tiny(spark), "f") and m.asked == 8


def test_budget_for_all_rows_takes_no_sample(spark, monkeypatch):
    from virtcol import queries

    def none(*_):
        raise AssertionError("a sample was drawn")

    monkeypatch.setattr(Engine, "_sample", none)
    e = Engine(spark, RuleModel({"odd": "id % 2 = 1"}), Costs(8, 8))
    e.register("t", tiny(spark), TableInfo("id", "g", stratum="g"))
    assert e.sql('SELECT COUNT(*) AS n, SUM(x) AS s FROM t WHERE "odd"').df.first() == (4.0, 16.0) and queries.ALL > 10**15


def test_taxonomy_groups(spark):
    """Categories come from the few rows of the taxonomy; rows may fit several, or none."""
    rows = [(i, t, s) for i, (t, s) in enumerate([("red", "a"), ("red blue", "b"), ("blue", "c"), ("green", "a"), ("", "b"), ("red", "c")] * 4)]
    df = spark.createDataFrame(rows, "id long, text string, g string")
    sql = 'SELECT k, COUNT(*) AS n FROM t GROUP BY "colours" AS k'
    labels = {"colours": "filter(split(text, ' '), x -> x <> '')"}
    whole = Engine(spark, RuleModel({}), Costs(100, 100))
    whole.register("t", df, TableInfo("id", "text", labels=labels, stratum="g"))
    assert {tuple(r) for r in whole.sql(sql).df.collect()} == {("red", 12.0), ("blue", 8.0), ("green", 4.0), ("none", 4.0)}
    few = Engine(spark, RuleModel({}), Costs(23, 23, taxonomy_rows=1))
    few.register("t", df, TableInfo("id", "text", labels=labels, stratum="g"))
    got = few.sql(sql)
    found = {r["k"]: r["n"] for r in got.df.collect()}
    assert "none" in found and len(found) < 4 and 23 < sum(found.values()) < 29 and got.meter.calls == 24

    def fn(prompt, text):
        return "red | | 2\nblue | | 1" if "Group the records" in prompt else ", ".join(str(i) for i, c in enumerate(["red", "blue"]) if c in (text or ""))

    from virtcol.model.base import CallableModel

    asked = Engine(spark, CallableModel(fn, "text"), Costs(100, 100))
    asked.register("t", df, TableInfo("id", "text", stratum="g"))
    assert {tuple(r) for r in asked.sql(sql).df.collect()} == {("red", 12.0), ("blue", 8.0), ("none", 8.0)}


def test_measures():
    d = lambda a, b: float(a != b)
    assert metrics.emd([("a", 7), ("b", 3)], [("a", 14), ("b", 6)], d) == 0
    assert math.isclose(metrics.emd([("a", 1)], [("b", 5)], d), 1) and math.isclose(metrics.emd([("a", 7), ("b", 3)], [("a", 3), ("b", 7)], d), 0.4)
    rng = np.random.default_rng(1)
    for _ in range(20):
        c = rng.random((4, 4))
        best = min(sum(c[i][p[i]] for i in range(4)) / 4 for p in itertools.permutations(range(4)))
        assert math.isclose(metrics.emd([(str(i), 1) for i in range(4)], [(str(i), 1) for i in range(4)], lambda a, b: c[int(a)][int(b)]), best, abs_tol=1e-9)


def test_replies():
    assert [parse_bool(x) for x in ("True", " yes.", "FALSE!", "", None, "perhaps")] == [True, True, False, None, None, None]
    assert parse_int("about 12 rows") == 12 and parse_int("none") is None
    assert parse_index_list("1, 3,3, 9", 5) == [1, 3] and parse_index_list(None, 5) == []
    assert parse_group_table("Boots | shoes | 3\n| hats | head | 9 |\nnoise\nboots|x|1") == [("hats", "head", 9), ("boots", "shoes", 3)]


def test_packs(spark):
    df = spark.createDataFrame([(i, t) for i, t in enumerate([5, 5, 5, 50])], "id long, t long")
    rows = baselines.packs(df, "id", F.col("t"), 12, 10).collect()
    sums = {}
    for r in rows:
        sums[r["pack"]] = sums.get(r["pack"], 0) + min(r["t"], 12)
    assert len(rows) == 4 and max(sums.values()) <= 12


def test_strata_sizes_follow_filters(spark):
    assert strata_sizes(tiny(spark).where("x < 5"), "g") == {"a": 5}


def test_null_groups_stay(spark):
    """Rows whose group is null are a group of their own, whatever the number of aggregates and for any budget."""
    rows = [(i, "text", [None, "a", "b"][i % 3], i) for i in range(60)]
    for budget in (1000, 30):
        e = Engine(spark, RuleModel({"any": "true"}), Costs(budget, budget))
        e.register("t", spark.createDataFrame(rows, "id long, text string, g string, x long"), TableInfo("id", "text", stratum="g"))
        got = {r["g"]: (r["n"], r["total"]) for r in e.sql('SELECT g, COUNT(*) AS n, SUM(x) AS total FROM t WHERE "any" GROUP BY g').df.collect()}
        assert set(got) == {None, "a", "b"} and all(abs(n - 20) < 1e-6 for n, _ in got.values())


def test_search_with_pool_and_token_budget(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(400, 8)).astype(np.float32)
    yes = {i for i in range(400) if x[i, 0] > 0.8}
    df = spark.createDataFrame([(i, v.tolist(), 10 + i % 5) for i, v in enumerate(x)], "id long, e array<float>, t long").repartition(3)
    judge = lambda ids: [i in yes for i in ids]
    plain, pooled = active_search(df, judge, 96, 16, seed=3), active_search(df, judge, 96, 16, seed=3, pool=200, refresh=3)
    assert len(pooled.trace) == 96 and set(pooled.hits) <= yes and len(pooled.hits) >= 0.8 * len(plain.hits)
    whole = active_search(df, judge, 96, 16, seed=3, pool=400, refresh=100)  # a pool of all rows loses nothing
    assert [t[1] for t in whole.trace[:32]] == [t[1] for t in plain.trace[:32]]
    state: dict = {}
    active_search(df, judge, 400, 16, seed=3, state=state, tokens="t", token_budget=500)
    assert 480 <= sum(state["tokens"].values()) <= 500 and len(state["seen"]) == len(state["tokens"])


def test_repeat_and_label_distance():
    mean, sd, got = metrics.repeat(lambda s: None if s == 3 else float(s), range(5))
    assert got == [0, 1, 2, 4] and mean == 1.75 and abs(sd - 1.7078) < 1e-3
    assert metrics.label_distance("fr", "fr") < 1e-9 and metrics.label_distance("fr", "de") == 1.0
    assert abs(metrics.emd([("fr", 3), ("de", 1)], [("fr", 1), ("de", 1)], metrics.label_distance) - 0.25) < 1e-9


def test_queries_without_labels_find_more_than_chance(spark):
    """Inner products with a query of common words, which looks at no label."""
    r = workloads.run("w5", spark, "/root/testdata/sf0.01", "mips", 100)
    assert r["hits"] > 2 * 100 * r["truth"] / 1000


def small_engine(spark, model=None, n=60, budget=20, **options):
    from virtcol.engine import Engine, TableInfo
    from virtcol.model.base import RuleModel

    rows = [(i, f"row {i} " + ("red" if i % 3 == 0 else "blue"), "ab"[i % 2], f"k{i % 4}") for i in range(n)]
    df = spark.createDataFrame(rows, "id long, text string, s string, kind string")
    e = Engine(spark, model or RuleModel({"is red": "text like '%red'", "is even": "id % 2 = 0"}), Costs(budget, budget, 4), **options)
    e.register("t", df, TableInfo("id", "text", "rows", ("kind",), {"its kind": "kind", "its colour": "split(text, ' ')[2]"}, stratum="s"))
    return e


def test_plans_spend_what_they_say(spark):
    from virtcol.lang.parser import parse
    from virtcol.plans import planner

    text = 'SELECT "its kind", COUNT(*) AS n FROM t WHERE "is red" GROUP BY "its kind"'
    e = small_engine(spark)
    spent = {}
    for p in planner.enumerate_plans(parse(text), 20.0, e.costs):
        r = e.sql(text, p)
        spent[p.fused] = r.meter.calls
        assert abs(sum(x["n"] for x in r.df.select(F.col(r.df.columns[1]).alias("n")).collect()) - 20) < 12
    assert spent[("extract+classify", "proposal")] < spent[("proposal",)] and spent[("extract+classify", "proposal")] < spent[("extract+classify",)] < spent[()]


def test_limit_unfused_judges_the_whole_budget(spark):
    from virtcol.lang.parser import parse
    from virtcol.plans import planner

    text = 'SELECT id FROM t WHERE "is red" LIMIT 2'
    e = small_engine(spark, batch=4)
    plans = {p.fused: e.sql(text, p) for p in planner.enumerate_plans(parse(text), 60.0, e.costs)}
    assert plans[("limit",)].meter.calls < plans[()].meter.calls == 20
    assert all(r.df.count() == 2 and all(x["id"] % 3 == 0 for x in r.df.collect()) for r in plans.values())


def test_order_of_phrases_saves_calls(spark):
    text = 'SELECT COUNT(*) AS n FROM t WHERE "is even" AND "is red"'
    plain, told = small_engine(spark, budget=100).sql(text), small_engine(spark, budget=100, selectivity={"is even": 0.5, "is red": 0.33}).sql(text)
    assert plain.df.first()["n"] == told.df.first()["n"] == 10
    assert plain.meter.calls == 60 + 30 and told.meter.calls == 60 + 20


def test_a_called_model_is_asked_for_open_rows_alone(spark, tmp_path):
    from virtcol.model.base import CallableModel, StoredModel

    log = str(tmp_path / "asked")

    def says(phrase, text):
        with open(log, "a") as f:
            f.write(f"{phrase}|{text}\n")
        return text.endswith("red") if phrase == "is red" else int(text.split()[1]) % 2 == 0

    text = 'SELECT COUNT(*) AS n FROM t WHERE s = "a" AND "is red" AND "is even" OR s = "b" AND "is red"'
    model = CallableModel(says, "text", parallel=4)
    r = small_engine(spark, model, budget=100).sql(text)
    assert r.df.first()["n"] == 20 and r.meter.calls == 60 + 10
    assert len(open(log).read().splitlines()) == 70
    kept = StoredModel(model, "id", "text", "file://" + str(tmp_path / "answers"))
    for again in (70, 0):
        kept.asked = 0
        assert small_engine(spark, kept, budget=100).sql(text).df.first()["n"] == 20
        assert kept.asked == again
    assert len(open(log).read().splitlines()) == 140


def test_select_extracts_what_is_left(spark):
    e = small_engine(spark, allow_virtual_sort=True)
    r = e.sql('SELECT id, "its colour" AS c, "its kind" AS k FROM t WHERE s = "a" ORDER BY id LIMIT 4')
    assert [tuple(x) for x in r.df.collect()] == [(0, "red", "k0"), (2, "blue", "k2"), (4, "blue", "k0"), (6, "red", "k2")]
    assert r.meter.calls == 4
    by = e.sql('SELECT id FROM t WHERE s = "a" ORDER BY "its colour" DESC LIMIT 3').df.collect()
    assert all(x["id"] % 3 == 0 for x in by)


def test_intervals_cover(spark):
    inside = 0
    for seed in range(20):
        e = small_engine(spark, seed=seed)
        row = e.sql('SELECT COUNT(*) AS n FROM t WHERE "is red"').intervals().first()
        inside += row["low"] <= 20 <= row["high"]
    assert inside >= 16


def test_average_has_an_interval(spark):
    rows = spark.range(400).selectExpr("id", "if(id % 4 = 0, 'red', 'blue') AS label", "if(id < 200, 'a', 'b') AS s", "cast(id % 10 AS double) AS v")
    e = Engine(spark, RuleModel({"is red": "label = 'red'"}), Costs(60, 60))
    e.register("t", rows, TableInfo("id", "label", "rows", ("label",), stratum="s"))
    r = e.sql('SELECT AVG(v) AS m FROM t WHERE "is red"')
    row = r.intervals().first()
    assert math.isclose(row["estimate"], r.df.first()["m"])
    assert row["stderr"] > 0 and math.isclose(row["stderr"], standard_error(r.sample, F.col("_f"), "avg", F.col("v")))
    e = Engine(spark, RuleModel({"is red": "label = 'red'"}), Costs(400, 400))
    e.register("t", rows, TableInfo("id", "label", "rows", ("label",), stratum="s"))
    got = {x["s"]: (x["estimate"], x["stderr"]) for x in e.sql('SELECT s, AVG(v) AS m FROM t WHERE "is red" GROUP BY s').intervals().collect()}
    assert got == {"a": (4.0, 0.0), "b": (4.0, 0.0)}


def test_kmeans_finds_separate_groups():
    x = np.repeat(np.eye(3, 8, dtype=np.float32), 20, axis=0)
    assert sorted(map(tuple, feats.lloyd(x, 3))) == sorted(map(tuple, np.eye(3, 8, dtype=np.float32)))
    assert feats.lloyd(np.zeros((5, 2), np.float32), 4).shape == (1, 2) and feats.lloyd(np.zeros((0, 1), np.float32), 4).shape == (0, 1)


def test_explain_and_prompts(spark):
    e = small_engine(spark)
    text = 'SELECT id FROM t WHERE s = "a" AND "is red" LIMIT 3'
    assert "tokens" in e.explain(text) and "dollars" in e.explain(text) and "Physical Plan" in e.explain(text)
    assert [x.step for x in e.prompts(text)] == ["where"] and "{row}" in e.prompts(text)[0].template


def test_two_levels_number_cells(spark):
    rows = [(i, [float(10 * (i % 2)), float(i % 4 // 2)]) for i in range(40)]
    from virtcol.index.features import assign_strata

    got = assign_strata(spark.createDataFrame(rows, "id long, e array<float>"), "two_level", 2, 0, k2=2).toPandas().set_index("id")["stratum"]
    assert got.nunique() == 4 and all(got[i] // 2 == got[i + 2] // 2 for i in range(38))


def test_semantic_join_within_words_and_over_breaks(spark, tmp_path):
    from virtcol.operators.relational import semantic_join

    texts = [(1, "say one two\nthree four five six seven end"), (2, "xone two\nthree four five six sevenx"), (3, "a bc d"), (4, "one two three four five six seven"), (None, "z q r s z"), (5, None), (6, "")]
    passages = [(1, "one two\nthree four five six seven"), (2, "bc"), (3, "q r s"), (4, " "), (None, "c d"), (5, None), (6, "absent word here")]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(passages, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = semantic_join(spark, str(tmp_path)).collect()
    assert {tuple(r) for r in got} == {(i, j) for i, t in texts for j, p in passages if t is not None and p is not None and p in t} and len(got) == len(set(got))


def test_dedup_goes_through_files_and_is_whole(spark, tmp_path):
    """No event reaches the driver; late repeats, late events and null ids and times count as in SQL."""
    import datetime

    from virtcol.streaming import streams

    day = lambda n: datetime.datetime(2024, 1, 1) + datetime.timedelta(days=n)
    for part in ([(1, day(200)), (2, day(200)), (None, day(200)), (7, None)], [(3, day(0)), (1, day(400)), (7, day(3))], [(1, day(600)), (4, day(600)), (3, day(1))]):
        spark.createDataFrame(part, "event_id long, ts timestamp_ntz").coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    before, store = {t.name for t in spark.catalog.listTables()}, spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    assert [tuple(r) for r in streams.stream_dedup(spark, str(tmp_path)).collect()] == [(5,)]
    assert {t.name for t in spark.catalog.listTables()} == before and spark.conf.get("spark.sql.streaming.stateStore.providerClass") == store


def test_paged_and_prompts_read_given_tables(spark, tmp_path):
    from virtcol import queries

    keys = [None, -3, 7, 9_999, 10_000, 10_000_000_000, 8]
    spark.createDataFrame([(k,) for k in keys], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    want = sorted(keys, key=lambda k: (k is not None, k or 0))
    assert sorted(tuple(r) for r in queries.QUERIES["rel_paged"](spark, str(tmp_path)).collect()) == [(i, i // 2, k) for i, k in enumerate(want)]
    spark.createDataFrame([(i, "ab" if i else None, "en", "s", 2) for i in range(17)], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    for name in ("benchmark", "labels", "pages", "conversations", "embeddings", "orders", "events", "lineitem", "part", "supplier", "nation", "region"):
        spark.read.parquet(f"/root/testdata/sf0.001/{name}.parquet").limit(5).write.parquet(f"{tmp_path}/{name}.parquet")
    got = {r["step"]: (r["calls"], r["chars"]) for r in queries.QUERIES["prompt_calls"](spark, str(tmp_path)).collect()}
    assert got == {"where": (17, 32), "taxonomy": (2, 32), "classify": (17, 32)}
