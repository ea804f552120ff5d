"""Runs VSQL: parse, bind, plan, sample or search, judge the few rows, estimate."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .index import features as feats
from .index.sample import WeightedFrame, draw, allocate, estimate, intervals, md5_key, strata_sizes
from .index.search import active_search, ordered_probe
from .lang.parser import Agg, Col, IntLit, Phrase, Query, Star, parse
from .model.base import Meter, RuleModel
from .plans import planner
from .plans.prompts import Backend, PromptCall, instantiate
from .tables import shared_folder


@dataclass
class TableInfo:
    """How a table is read: its id, the text its phrases are about, and what only a model may see."""

    id_col: str
    source: str
    about: str = "records"
    hidden: tuple[str, ...] = ()
    labels: dict = field(default_factory=dict)  # phrase -> SQL expression of a category or an extracted value
    vectors: str | None = None
    stratum: str | None = None  # a stored column to stratify by, in place of clusters


@dataclass
class Result:
    df: DataFrame
    meter: Meter
    plan: planner.Plan
    trace: list = field(default_factory=list)
    sample: WeightedFrame | None = None  # what an aggregate over phrases was estimated from
    exact: DataFrame | None = None  # rows that stored columns alone decide
    shape: tuple = ()  # (group names, group columns of exact, aggregates)

    def intervals(self, z: float = 1.96) -> DataFrame:
        """For each aggregate a row per group: estimate, standard error and normal bounds; rows that were counted exactly add no error.

        AVG is a ratio of two sums; its error is that of the hits' distances from it. A group without a value has no average.
        """
        if self.sample is None:
            raise ValueError("nothing was estimated")
        names, keys, aggs = self.shape

        def summed(op: str, value: Column | None) -> DataFrame:
            sure = self.exact.groupBy(*(k.alias(n) for k, n in zip(keys, names))).agg((F.count("*").cast("double") if value is None else F.count(value).cast("double") if op == "count" else F.coalesce(F.sum(value.cast("double")), F.lit(0.0))).alias("estimate"), F.lit(0.0).alias("stderr"))
            f = F.col("_f") if value is None else F.col("_f") & value.isNotNull()
            both = intervals(self.sample, op, f, value, names).select(*names, "estimate", "stderr").unionByName(sure)
            return both.groupBy(*names).agg(F.sum("estimate").alias("estimate"), F.sum("stderr").alias("stderr"))

        def mean(value: Column) -> DataFrame:
            total, number = (summed(op, value).select(*names, F.col("estimate").alias(c)) for op, c in (("sum", "_total"), ("count", "_number")))
            ratio = paired(total, number, names).where("_number > 0").select(*names, (F.col("_total") / F.col("_number")).alias("_mean"), "_number")
            off = replace(self.sample, df=paired(self.sample.df, ratio.select(*names, "_mean"), names))
            far = intervals(off, "sum", F.col("_f") & value.isNotNull(), value - F.col("_mean"), names).select(*names, F.lit(None).cast("double").alias("_mean"), F.lit(None).cast("double").alias("_number"), "stderr")
            both = ratio.withColumn("stderr", F.lit(0.0)).unionByName(far).groupBy(*names).agg(F.max("_mean").alias("estimate"), F.max("_number").alias("_number"), F.sum("stderr").alias("stderr"))
            return both.where("_number > 0").withColumn("stderr", F.col("stderr") / F.col("_number"))

        out = None
        for agg, name in aggs:
            value = None if agg.arg == "*" else F.col(agg.arg)
            one = mean(value) if agg.op == "avg" else summed(agg.op, value)
            one = one.select(F.lit(name).alias("aggregate"), *names, "estimate", "stderr", (F.col("estimate") - z * F.col("stderr")).alias("low"), (F.col("estimate") + z * F.col("stderr")).alias("high"))
            out = one if out is None else out.unionByName(one)
        if out is None:
            raise ValueError("the query has no aggregate")
        return out


def paired(a: DataFrame, b: DataFrame, names: list[str]) -> DataFrame:
    """Two tables with a row per group, side by side; a null key is a group like any other."""
    if not names:
        return a.crossJoin(b)  # a row each
    other = b.withColumnsRenamed({n: f"__{n}" for n in names})
    return a.join(other, reduce(lambda x, y: x & y, [F.col(n).eqNullSafe(F.col(f"__{n}")) for n in names])).drop(*(f"__{n}" for n in names))


class Engine:
    def __init__(self, spark: SparkSession, model: RuleModel, costs: planner.Costs = planner.Costs(), seed: int = 0, strata: int = 10, batch: int = 16, selectivity: dict[str, float] | None = None, allow_virtual_sort: bool = False, pool: int | None = None):
        self.spark, self.model, self.costs, self.seed, self.strata, self.batch = spark, model, costs, seed, strata, batch
        self.selectivity, self.allow_virtual_sort = selectivity or {}, allow_virtual_sort  # shares that phrases are thought to hold for; 0.5 unless given
        self.pool = pool  # so many candidates are ranked on the driver between two scans of a search
        self.tables: dict[str, tuple[DataFrame, TableInfo]] = {}

    def register(self, name: str, df: DataFrame, info: TableInfo) -> None:
        self.tables[name] = (df, info)

    def table(self, name: str) -> Fluent:
        return Fluent(self, name)

    def suggest_context(self, df: DataFrame) -> str | None:
        """The string column with the longest texts, from a few rows."""
        names = [n for n, t in df.dtypes if t == "string"]
        if not names:
            return None
        sizes = df.limit(100).agg(*(F.avg(F.length(n)).alias(n) for n in names)).first()
        return max(names, key=lambda n: (sizes[n] or 0, n))

    def explain(self, sql: str) -> str:
        q = parse(sql)
        df, info = self.tables[q.table]
        rows, length = df.agg(F.count("*"), F.coalesce(F.avg(F.length(F.col(info.source).cast("string"))), F.lit(0.0))).first()
        plan = planner.best(q, rows, self.costs)
        tokens, meter = plan.cost * length / 4, Meter()
        meter.add(0, int(tokens), int(plan.cost))
        order = " then ".join(planner.phrase_order(q.where, self.selectivity)) or "nothing"
        decided, live = planner.masks(q.where)
        kept = self._reached(df, q).where(decided | (live != 0))
        spark_plan = kept._jdf.queryExecution().explainString(kept.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("simple"))
        return f"{plan.kind}: {plan}\nasked in this order: {order}\nabout {tokens:.0f} tokens, {meter.usd:.6f} dollars\nrows that reach the model or need none:\n{spark_plan}"

    def prompts(self, sql: str, backend: Backend = Backend()) -> list[PromptCall]:
        """What a backend would be sent for the query."""
        q = parse(sql)
        return instantiate(planner.best(q, float(self.costs.row_budget), self.costs), q, self.tables[q.table][1], backend, self.costs)

    def _reached(self, df: DataFrame, q: Query) -> DataFrame:
        some = planner.reachable(q.where)
        return df if some is None else df.where(some)

    def sql(self, text: str, plan: planner.Plan | None = None) -> Result:
        return self.run(parse(text), plan)

    def run(self, q: Query, plan: planner.Plan | None = None) -> Result:
        """Runs the given plan, one of planner.enumerate_plans, or the cheapest."""
        df, info = (self.spark.read.parquet(q.table), TableInfo("id", "text")) if q.path else self.tables[q.table]
        visible = [c for c in df.columns if c not in info.hidden]
        if q.path and df.columns and "id" not in df.columns:
            info = TableInfo(df.columns[0], self.suggest_context(df) or df.columns[0])
        kind = planner.bind(q, visible, self.allow_virtual_sort)
        meter = Meter()
        semantic = planner.phrases(q.where)
        virtual = bool(semantic) or any(isinstance(x, Phrase) for x in (*q.select, *q.group))
        decided, live = planner.masks(q.where)
        kept = self._reached(df, q).withColumns({"_decided": decided, "_live": live}).where(F.col("_decided") | (F.col("_live") != 0))
        plan = plan or planner.best(q, float(self.costs.row_budget), self.costs)
        result = Result(kept, meter, plan)
        if kind == planner.AGGREGATE:
            out = self._aggregate(q, kept, info, semantic, virtual, meter, plan, result)
            trace = []
        else:
            out, trace = self._rows(q, kept, info, semantic, meter, plan, visible)
        if q.into:
            out.createOrReplaceTempView(q.into)
        result.df, result.trace = out, trace
        return result

    # Aggregates: decided rows are counted exactly; a budget of the open ones is drawn, judged once and weighed.

    def _strata(self, df: DataFrame, info: TableInfo) -> DataFrame:
        if info.stratum:
            return df.withColumn("_s", F.col(info.stratum))
        root = shared_folder(self.spark, "features")  # computed once, read by the fit, the sizes and the draw
        feats.build_features(df, info.id_col, info.vectors or info.source, "given" if info.vectors else "hashed_words").write.parquet(f"{root}/e")
        feats.assign_strata(self.spark.read.parquet(f"{root}/e"), "kmeans", self.strata, self.seed).write.parquet(f"{root}/strata")
        strata = self.spark.read.parquet(f"{root}/strata")
        return df.join(strata.select(F.col("id").alias("_sid"), F.col("stratum").alias("_s")), F.col(info.id_col) == F.col("_sid")).drop("_sid")

    def _sample(self, df: DataFrame, info: TableInfo, budget: int) -> WeightedFrame:
        """Drawn on ids and strata alone; the wide columns are fetched for the drawn ids."""
        ids = self._strata(df, info).select(info.id_col, "_s")
        w = draw(ids, info.id_col, "_s", allocate(strata_sizes(ids, "_s"), budget), self.seed)
        rows = w.df.select(info.id_col, "_w", "_stratum").toPandas()  # at most `budget` rows
        small = self.spark.createDataFrame(rows, w.df.select(info.id_col, "_w", "_stratum").schema) if len(rows) else w.df.select(info.id_col, "_w", "_stratum").limit(0)
        w.df = df.join(F.broadcast(small), info.id_col)
        return w

    def _judged_in_place(self, df: DataFrame, where: tuple, semantic: list[str], meter: Meter, info: TableInfo) -> DataFrame:
        """All rows with `_f`, for a budget that covers them: nothing but the meter's sums comes to the driver."""
        if not semantic:
            return df.withColumn("_f", F.lit(True))
        asked = planner.judge_residual(df, where, self.model, planner.phrase_order(where, self.selectivity))
        if not isinstance(self.model, RuleModel):  # a row is asked once
            root = shared_folder(self.spark, "judged")
            asked.write.parquet(root)
            asked = self.spark.read.parquet(root)
        tokens = F.coalesce((F.length(F.col(info.source).cast("string")) / 4).cast("long"), F.lit(0))
        n, t = asked.agg(F.coalesce(F.sum("_calls"), F.lit(0)), F.coalesce(F.sum(F.col("_calls") * tokens), F.lit(0))).first()
        meter.add(int(n), int(t), int(n))
        return asked

    def _judged(self, df: DataFrame, where: tuple, semantic: list[str], meter: Meter, info: TableInfo) -> DataFrame:
        """The (few) rows with `_f`, their truth, judged once: the answers come to the driver and go back as a local table."""
        if not semantic:
            return df.withColumn("_f", F.lit(True))
        made = planner.judge_residual(df, where, self.model, planner.phrase_order(where, self.selectivity))
        rows = made.select(info.id_col, "_f", "_calls", (F.length(F.col(info.source).cast("string")) / 4).cast("long").alias("_t")).toPandas()
        meter.add(int(rows["_calls"].sum()), int((rows["_calls"] * rows["_t"].fillna(0)).sum()), int(rows["_calls"].sum()))
        if not len(rows):
            return df.withColumn("_f", F.lit(False))
        local = self.spark.createDataFrame(rows[[info.id_col, "_f"]], made.select(info.id_col, "_f").schema)
        return df.join(F.broadcast(local), info.id_col)

    def _grouped(self, sample: WeightedFrame, phrase: str, info: TableInfo, meter: Meter, whole: bool, proposal: DataFrame | None, extracted: bool) -> Column:
        """An array with each row's categories of a phrase: the model names them from a few hits, dealt over the strata, and then classifies the rows against them.

        Where the budget covers all rows, a rule model's categories are those of all hits.  proposal: hits of a draw of
        the taxonomy's own, where the plan does not share the sample.  extracted: the plan reads the phrase's value with a
        call of its own before it classifies, rather than in one.
        """
        hits = sample.df.where("_f")
        turn = F.row_number().over(Window.partitionBy("_stratum").orderBy(md5_key(info.id_col, self.seed), info.id_col))
        few = hits.withColumn("_turn", turn).orderBy("_turn", "_stratum").limit(self.costs.taxonomy_rows) if proposal is None else proposal.limit(self.costs.taxonomy_rows)
        taxonomy = None if whole and isinstance(self.model, RuleModel) else self.model.propose(few, phrase, info)
        n = hits.count()
        meter.add(bool(n) + n * (1 + extracted), 0, n * (max(1, len(taxonomy or ())) + extracted))
        return self.model.classify(hits, phrase, info, taxonomy)

    def _aggregate(self, q: Query, kept: DataFrame, info: TableInfo, semantic: list[str], virtual: bool, meter: Meter, plan: planner.Plan, result: Result) -> DataFrame:
        keys, names = [], []
        for i, g in enumerate(q.group):
            keys.append(F.col(f"_g{i}") if isinstance(g, Phrase) else F.col(g.name))
            names.append(g.alias or (g.name if isinstance(g, Col) else f"group_{i}"))
        aggs = [(x, x.alias or (x.op if x.arg == "*" else f"{x.op}_{x.arg}")) for x in q.select if isinstance(x, Agg)]
        if not virtual:
            grouped = kept.groupBy(*(k.alias(n) for k, n in zip(keys, names)))
            made = {"count": lambda x: F.count("*" if x.arg == "*" else x.arg), "sum": lambda x: F.sum(x.arg), "avg": lambda x: F.avg(x.arg)}
            out = grouped.agg(*(made[x.op](x).alias(n) for x, n in aggs)) if aggs else grouped.agg(F.count("*")).select(*names)
            return self._finish(out, q, names, aggs)
        budget = self.costs.aggregate_budget
        exact = kept.where("_decided") if not any(isinstance(g, Phrase) for g in q.group) else kept.limit(0)
        open_ = kept.where("NOT _decided") if not any(isinstance(g, Phrase) for g in q.group) else kept
        n_open = open_.count()
        if n_open <= budget:
            sample = WeightedFrame(self._judged_in_place(open_, q.where, semantic, meter, info).withColumns({"_w": F.lit(1.0), "_stratum": F.lit(0)}), n_open, {0: n_open}, {0: n_open})
        else:
            sample = self._sample(open_, info, budget)
            sample.df = self._judged(sample.df, q.where, semantic, meter, info)
        grouped_phrases = [(i, g.text) for i, g in enumerate(q.group) if isinstance(g, Phrase)]
        if grouped_phrases:  # a row counts in each of its categories, so weights are scaled before rows are multiplied
            whole = sample.population <= budget
            own = None
            if not whole and semantic and "proposal" not in plan.fused:
                rows = open_.orderBy(md5_key(info.id_col, self.seed + 1), info.id_col).limit(int(self.costs.taxonomy_rows / self.costs.selectivity))
                own = self._judged(rows, q.where, semantic, meter, info).where("_f")
            shown = {x.text for x in q.select if isinstance(x, Phrase)}
            apart = "select" in plan.steps and "extract+classify" not in plan.fused
            found = {f"_g{i}": self._grouped(sample, text, info, meter, whole, own, apart and text in shown) for i, text in grouped_phrases}
            sums = sample.df.agg(F.sum("_w")).first()[0] or 1.0
            rows = sample.df.where("_f").withColumn("_w", F.col("_w") * F.lit(sample.population / sums)).withColumns(found)
            for c in found:
                rows = rows.withColumn(c, F.explode(c))
            sample.df = rows
            exact = exact.withColumns({c: F.lit(None).cast("string") for c in found})
        named = [k.alias(n) for k, n in zip(keys, names)]
        base = WeightedFrame(sample.df.withColumns({n: k for k, n in zip(keys, names)}), sample.population, sample.sizes, sample.drawn)
        result.sample, result.exact, result.shape = base, exact, (names, keys, aggs)
        parts = None
        for x, n in aggs or [(Agg("count", "*"), "count")]:
            value = None if x.arg == "*" else F.col(x.arg)
            weights = WeightedFrame(base.df, base.population, base.sizes, base.drawn)
            number = estimate(weights, "count", F.col("_f") & (value.isNotNull() if value is not None else F.lit(True)), None, not grouped_phrases, names or None).withColumnRenamed("estimate", "_n").drop("n")
            total = estimate(weights, "sum", F.col("_f"), value, not grouped_phrases, names or None).withColumnRenamed("estimate", "_s").drop("n")
            sampled = paired(number, total, names).select(*names, "_n", "_s")
            sure = exact.groupBy(*named).agg((F.count("*") if value is None else F.count(value)).cast("double").alias("_n"), F.coalesce(F.sum(F.lit(1.0) if value is None else value.cast("double")), F.lit(0.0)).alias("_s"))
            both = sampled.unionByName(sure).groupBy(*names).agg(F.coalesce(F.sum("_n"), F.lit(0.0)).alias("_n"), F.coalesce(F.sum("_s"), F.lit(0.0)).alias("_s"))
            shown = {"count": F.col("_n"), "sum": F.col("_s"), "avg": F.col("_s") / F.nullif(F.col("_n"), F.lit(0.0))}[x.op].alias(n)
            one = both.where("_n > 0").select(*names, shown) if names else both.select(shown)
            parts = one if parts is None else paired(parts, one, names)
        return self._finish(parts, q, names, aggs)

    def _finish(self, out: DataFrame, q: Query, names: list[str], aggs: list) -> DataFrame:
        shown, at = [], iter([n for _, n in aggs])
        for x in q.select:
            if isinstance(x, Agg):
                shown.append(F.col(next(at)))
            elif isinstance(x, IntLit):
                shown.append(F.lit(x.value).alias(f"lit_{x.value}"))
            else:
                i = next(i for i, g in enumerate(q.group) if (g.text if isinstance(g, Phrase) else g.name) == (x.text if isinstance(x, Phrase) else x.name) or g.alias == getattr(x, "name", None))
                shown.append(F.col(names[i]).alias(x.alias or names[i]))
        out = out.select(*shown)
        return self._sorted(out, q)

    def _sorted(self, out: DataFrame, q: Query) -> DataFrame:
        if q.order:
            by = [F.col(out.columns[x.value - 1]) if isinstance(x, IntLit) else F.col(x.name) for x in q.order]
            out = out.orderBy(*(c.desc() if q.desc else c for c in by))
        return out.limit(q.limit) if q.limit is not None else out

    # Rows: decided rows come free; open ones are searched under the budget, or walked in order when ORDER BY and LIMIT ask.

    def _rows(self, q: Query, kept: DataFrame, info: TableInfo, semantic: list[str], meter: Meter, plan: planner.Plan, visible: list[str]) -> tuple[DataFrame, list]:
        trace: list = []
        if semantic:
            limit, hits = q.limit, []
            free = [r[0] for r in kept.where("_decided").select(info.id_col).limit(limit).collect()] if limit is not None and not q.order else None
            open_ = kept.where("NOT _decided")

            def judge(ids: list) -> list[bool]:
                rows = self._judged(open_.where(F.col(info.id_col).isin(ids)), q.where, semantic, meter, info).where("_f").select(info.id_col).collect()
                yes = {r[0] for r in rows}
                return [i in yes for i in ids]

            if q.order and limit is not None and len(q.order) == 1 and isinstance(q.order[0], Col):
                whole = kept

                def judge_any(ids: list) -> list[bool]:
                    rows = self._judged(whole.where(F.col(info.id_col).isin(ids)), q.where, semantic, meter, info).where("_f").select(info.id_col).collect()
                    yes = {r[0] for r in rows}
                    return [i in yes for i in ids]

                ids = ordered_probe(kept, info.id_col, q.order[0].name, judge_any, limit, self.batch * 4, q.desc)
                found = kept.where(F.col(info.id_col).isin(ids))
            else:
                left = None if limit is None else limit - len(free or [])
                if left is None or left > 0:
                    e = feats.build_features(open_, info.id_col, info.vectors or info.source, "given" if info.vectors else "hashed_words").cache()
                    got = active_search(e, judge, self.costs.row_budget, self.batch, limit=left if "limit" in plan.fused else None, seed=self.seed, pool=self.pool)
                    e.unpersist()
                    hits, trace = got.hits, got.trace
                chosen = kept.where(F.col(info.id_col).isin([*hits, *free])) if free is not None else kept.where(F.col("_decided") | F.col(info.id_col).isin(hits))
                found = chosen
        else:
            found = kept
        # SELECT's phrases are read off the rows that are left at the end, all of a row's in one call.
        wanted = list(dict.fromkeys(x.text for x in (*q.select, *q.order) if isinstance(x, Phrase)))
        sorts_by_phrase = any(isinstance(x, Phrase) for x in q.order)

        def item(x) -> Column:
            return F.col(f"_x{wanted.index(x.text)}") if isinstance(x, Phrase) else F.lit(x.value) if isinstance(x, IntLit) else F.col(x.name)

        names = {x.alias: x for x in q.select if getattr(x, "alias", None)}

        def sort_item(x) -> Column:
            if isinstance(x, IntLit):
                return item(q.select[x.value - 1]) if not isinstance(q.select[x.value - 1], Star) else F.col(visible[0])
            return item(names[x.name]) if isinstance(x, Col) and x.name in names else item(x)

        sorts_by_phrase = sorts_by_phrase or any(isinstance(x, Col) and isinstance(names.get(x.name), Phrase) or isinstance(x, IntLit) and isinstance(q.select[x.value - 1], Phrase) for x in q.order)
        order = lambda d: d.orderBy(*(c.desc() if q.desc else c for c in map(sort_item, q.order))) if q.order else d
        cut = lambda d: d.limit(q.limit) if q.limit is not None else d
        out = found if sorts_by_phrase else cut(order(found))
        if wanted:
            out = self._extracted(out, wanted, info, meter)
        if sorts_by_phrase or wanted and q.order:
            out = cut(order(out))
        shown = []
        for i, x in enumerate(q.select):
            if isinstance(x, Star):
                shown += [F.col(c) for c in visible]
            elif isinstance(x, IntLit):
                shown.append(F.lit(x.value).alias(f"lit_{x.value}"))
            else:
                shown.append(item(x).alias(x.alias or (f"phrase_{i}" if isinstance(x, Phrase) else x.name)))
        return out.select(*shown), trace

    def _extracted(self, df: DataFrame, wanted: list[str], info: TableInfo, meter: Meter) -> DataFrame:
        """df with `_x0`, `_x1`, ...: one call a row for all phrases; a model that is no rule is asked once, and its answers are kept on the shared folder."""
        out = self.model.extract(df, wanted, info)
        if not isinstance(self.model, RuleModel):
            root = shared_folder(self.spark, "extracted")
            out.write.parquet(root)
            out = self.spark.read.parquet(root)
        n, t = out.agg(F.count("*"), F.coalesce(F.sum((F.length(F.col(info.source).cast("string")) / 4).cast("long")), F.lit(0))).first()
        meter.add(int(n), int(t), int(n) * len(wanted))
        return out


class Fluent:
    """The same queries from method calls."""

    def __init__(self, engine: Engine, table: str, **parts):
        self.engine, self.name, self.parts = engine, table, {"where": (), "group": (), "limit": None} | parts

    def _with(self, **more) -> Fluent:
        return Fluent(self.engine, self.name, **(self.parts | more))

    def where_semantic(self, phrase: str) -> Fluent:
        where = self.parts["where"] or ((),)
        return self._with(where=tuple((*c, Phrase(phrase)) for c in where))

    def group_by_semantic(self, phrase: str, alias: str) -> Fluent:
        return self._with(group=(*self.parts["group"], Phrase(phrase, alias)))

    def limit(self, n: int) -> Fluent:
        return self._with(limit=n)

    def query(self, *select) -> Query:
        return Query(tuple(select), self.name, self.parts["where"], self.parts["group"], limit=self.parts["limit"])

    def count(self, alias: str = "n") -> Result:
        keys = [Phrase(g.text, g.alias) for g in self.parts["group"]]
        return self.engine.run(self.query(*keys, Agg("count", "*", alias)))

    def rows(self) -> Result:
        return self.engine.run(self.query(Star()))
