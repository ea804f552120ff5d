"""Models answer phrases about rows. Offline ones are SQL expressions, so exact answers exist to compare with."""

from __future__ import annotations

import re
import time
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


@dataclass
class Meter:
    """Calls, tokens and money of a run."""

    prices: dict = field(default_factory=lambda: {"input": 0.25e-6, "output": 1.25e-6})
    calls: int = 0
    tokens_in: int = 0
    tokens_out: int = 0

    def add(self, calls: int, tokens_in: int, tokens_out: int) -> None:
        self.calls, self.tokens_in, self.tokens_out = self.calls + calls, self.tokens_in + tokens_in, self.tokens_out + tokens_out

    @property
    def usd(self) -> float:
        return self.tokens_in * self.prices["input"] + self.tokens_out * self.prices["output"]


def token_budget(usd: float, price: float) -> int:
    return int(usd / price)


#: The category of rows that fit none of a taxonomy.
NONE = "none"


def named(indexes: Column, taxonomy: list[str]) -> Column:
    """The categories' names, or NONE alone."""
    names = F.array(*map(F.lit, taxonomy)) if taxonomy else F.array(F.lit(NONE))
    return F.when(F.coalesce(F.size(indexes), F.lit(0)) > 0, F.transform(indexes, lambda i: F.get(names, i))).otherwise(F.array(F.lit(NONE)))


class RuleModel:
    """Phrases as SQL expressions: over hidden truth columns (a truth model) or over the text (a lexical one)."""

    def __init__(self, rules: dict[str, str], name: str = "rules"):
        self.rules, self.name = rules, name

    def column(self, phrase: str) -> Column:
        if phrase not in self.rules:
            raise KeyError(f"the model has no rule for {phrase!r}")
        return F.expr(self.rules[phrase])

    def judge(self, df: DataFrame, phrases: list[str]) -> DataFrame:
        """df with a column for each phrase, `_p0`, `_p1`, ..."""
        return df.withColumns({f"_p{i}": self.column(p) for i, p in enumerate(phrases)})

    def answer(self, df: DataFrame, phrase: str, need: str, out: str) -> DataFrame:
        """df with `out`: the phrase's answer for rows where `need` holds, null elsewhere."""
        return df.withColumn(out, F.when(F.col(need), self.column(phrase)))

    def extract(self, df: DataFrame, phrases: list[str], info) -> DataFrame:
        """df with a value for each phrase, `_x0`, `_x1`, ...; null where a row holds none."""
        return df.withColumns({f"_x{i}": F.expr(info.labels[p]) for i, p in enumerate(phrases)})

    def summarize(self, rows: DataFrame, phrase: str, info) -> list[tuple[str, int]]:
        """(category, rows) of the (few) rows, largest first: what one prompt over all of them returns."""
        got = rows.select(F.explode(self._labels(rows, phrase, info)).alias("g")).groupBy("g").count().collect()
        return sorted(((r[0], r[1]) for r in got), key=lambda g: (-g[1], g[0]))

    def _labels(self, df: DataFrame, phrase: str, info) -> Column:
        """What the model sees of a phrase in a row: distinct labels, perhaps none."""
        label = F.expr(info.labels[phrase])
        several = df.select(label).schema[0].dataType.typeName() == "array"
        return F.array_distinct(F.array_compact((label if several else F.array(label)).cast("array<string>")))

    def propose(self, rows: DataFrame, phrase: str, info) -> list[str]:
        """A taxonomy: the categories of the (few) rows."""
        return sorted(r[0] for r in rows.select(F.explode(self._labels(rows, phrase, info))).distinct().collect())

    def classify(self, rows: DataFrame, phrase: str, info, taxonomy: list[str] | None) -> Column:
        """An array with the names of the categories that a row fits, NONE alone if there is none; without a taxonomy every label is a category."""
        labels = self._labels(rows, phrase, info)
        if taxonomy is None:
            return F.when(F.size(labels) > 0, labels).otherwise(F.array(F.lit(NONE)))
        known = F.array(*map(F.lit, taxonomy)) if taxonomy else F.array().cast("array<string>")
        return named(F.transform(F.filter(labels, lambda x: F.array_contains(known, x)), lambda x: (F.array_position(known, x) - 1).cast("int")), taxonomy)


TruthModel = LexicalModel = RuleModel


class NoisyModel(RuleModel):
    """Another backend: a base model whose answers flip for rows that a salted hash picks."""

    def __init__(self, base: RuleModel, id_col: str, false_positive: float, false_negative: float, salt: str):
        super().__init__(base.rules, f"{base.name}+{salt}")
        self.base, self.id_col, self.fp, self.fn, self.salt = base, id_col, false_positive, false_negative, salt

    def column(self, phrase: str) -> Column:
        from ..index.search import uniform

        yes, u = self.base.column(phrase), uniform(self.id_col, self.salt, phrase)
        return F.when(yes, u >= self.fn).otherwise(u < self.fp)


class PackedModel:
    """Answers about many rows at once get worse with their place: a row at place i is missed with a chance that rises to `miss` at the end."""

    def __init__(self, base: RuleModel, id_col: str, miss: float = 0.6, salt: str = "packed"):
        self.base, self.id_col, self.miss, self.salt = base, id_col, miss, salt

    def column(self, phrase: str, place: Column, size: Column) -> Column:
        from ..index.search import uniform

        return self.base.column(phrase) & (uniform(self.id_col, self.salt, phrase) >= F.lit(self.miss) * place / size)


class CallableModel:
    """A caller's own function from a phrase and a text to an answer; tries again, and counts calls. Used on samples only."""

    def __init__(self, fn, source: str, tries: int = 3, parallel: int = 1, rate: float | None = None):
        self.fn, self.source, self.tries, self.parallel, self.rate, self.name = fn, source, tries, parallel, rate, "callable"

    def column(self, phrase: str) -> Column:
        fn, tries = self.fn, self.tries

        @F.pandas_udf("boolean")
        def ask(texts: pd.Series) -> pd.Series:
            def one(t):
                for k in range(tries):
                    try:
                        return fn(phrase, t)
                    except (OSError, TimeoutError):
                        if k + 1 == tries:
                            raise
                return None

            return texts.map(one)

        return ask(F.col(self.source))

    judge = RuleModel.judge

    def answer(self, df: DataFrame, phrase: str, need: str, out: str) -> DataFrame:
        """Calls are made for rows where `need` holds alone; a task's calls run `parallel` at a time, at most `rate` a second."""
        fn, tries, parallel, pause = self.fn, self.tries, self.parallel, 1.0 / self.rate if self.rate else 0.0

        @F.pandas_udf("boolean")
        def ask(texts: pd.Series, needed: pd.Series) -> pd.Series:
            def one(t):
                for k in range(tries):
                    try:
                        return fn(phrase, t)
                    except (OSError, TimeoutError):
                        if k + 1 == tries:
                            raise

            todo = [i for i, n in enumerate(needed) if n is not None and bool(n)]
            said: list = [None] * len(texts)
            with ThreadPoolExecutor(max(1, parallel)) as pool:
                waiting = []
                for i in todo:
                    waiting.append(pool.submit(one, texts.iloc[i]))
                    if pause:
                        time.sleep(pause)
                for i, w in zip(todo, waiting):
                    said[i] = w.result()
            return pd.Series(said, dtype="object")

        return df.withColumn(out, ask(F.col(self.source).cast("string"), F.col(need)))

    def extract(self, df: DataFrame, phrases: list[str], info) -> DataFrame:
        """All phrases share one prompt a row; the reply has a line for each."""
        fn, about, n = self.fn, info.about, len(phrases)

        @F.pandas_udf("array<string>")
        def ask(texts: pd.Series) -> pd.Series:
            return texts.map(lambda t: parse_lines(fn(extract_prompt(about, phrases, t or ""), t), n))

        return df.withColumn("_reply", ask(F.col(self.source).cast("string"))).withColumns({f"_x{i}": F.get("_reply", F.lit(i)) for i in range(n)}).drop("_reply")

    def summarize(self, rows: DataFrame, phrase: str, info) -> list[tuple[str, int]]:
        texts = [r[0] or "" for r in rows.select(F.col(self.source).cast("string")).collect()]
        reply = self.fn(packed_prompt("groups", info.about, phrase, texts), "\n".join(texts)) if texts else ""
        return [(name, n) for name, _, n in parse_group_table(reply)]

    def propose(self, rows: DataFrame, phrase: str, info) -> list[str]:
        """A taxonomy from one prompt about the (few) rows."""
        texts = [r[0] or "" for r in rows.select(F.col(self.source).cast("string")).collect()]
        reply = self.fn(packed_prompt("groups", info.about, phrase, texts), "\n".join(texts)) if texts else ""
        return [name for name, _, _ in parse_group_table(reply)]

    def classify(self, rows: DataFrame, phrase: str, info, taxonomy: list[str]) -> Column:
        fn, about = self.fn, info.about

        @F.pandas_udf("array<int>")
        def ask(texts: pd.Series) -> pd.Series:
            return texts.map(lambda t: parse_categories(fn(classify_prompt(about, phrase, t or "", taxonomy), t), len(taxonomy)))

        return named(ask(F.col(self.source)), taxonomy)


class CachedModel:
    """Remembers answers by phrase and id, so that no row is paid for twice; the store is a plain dict or anything like one."""

    def __init__(self, base, id_col: str, store: dict | None = None):
        self.base, self.id_col, self.store, self.asked = base, id_col, {} if store is None else store, 0

    def answers(self, df: DataFrame, phrase: str) -> dict:
        """Answers for the (few) rows of df."""
        ids = [r[0] for r in df.select(self.id_col).collect()]
        new = [i for i in ids if (phrase, i) not in self.store]
        if new:
            self.asked += len(new)
            rows = df.where(F.col(self.id_col).isin(new)).select(self.id_col, self.base.column(phrase)).collect()
            self.store.update({(phrase, r[0]): r[1] for r in rows})
        return {i: self.store[phrase, i] for i in ids}


class StoredModel(RuleModel):
    """A model whose answers are kept as Parquet by (model, phrase, id, text's hash): a row that was paid for is not asked again, in this run or a later one.

    Each call of `answer` writes what was new before it is read, so a task that is lost and run again asks nobody twice.
    It writes to a folder of its own: Spark takes two scans of one folder for equal, even if files came between them.
    """

    SCHEMA = "model string, phrase string, id string, text_hash long, said boolean"

    def __init__(self, base, id_col: str, source: str, path: str):
        self.base, self.id_col, self.source, self.path, self.name, self.asked = base, id_col, source, path, f"stored {base.name}", 0

    def column(self, phrase: str) -> Column:
        return self.base.column(phrase)

    def _kept(self, spark: SparkSession, phrase: str) -> DataFrame:
        root = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
        parts = sorted(x.getPath().toString() for x in fs.listStatus(root)) if fs.exists(root) else []  # one per call of answer
        kept = spark.read.schema(self.SCHEMA).parquet(*parts) if parts else spark.createDataFrame([], self.SCHEMA)
        mine = kept.where((F.col("model") == self.base.name) & (F.col("phrase") == phrase))
        return mine.groupBy(F.col("id").alias("_kid"), F.col("text_hash").alias("_khash")).agg(F.first("said").alias("_said"))

    def answer(self, df: DataFrame, phrase: str, need: str, out: str) -> DataFrame:
        spark = df.sparkSession
        on = F.col("_rid").eqNullSafe(F.col("_kid")) & (F.col("_rhash") == F.col("_khash"))
        rows = df.withColumns({"_rid": F.col(self.id_col).cast("string"), "_rhash": F.xxhash64(F.col(self.source).cast("string"))})
        new = rows.where(F.col(need)).join(self._kept(spark, phrase), on, "left_anti").dropDuplicates(["_rid", "_rhash"])
        fresh = self.base.answer(new, phrase, need, "_said").select(F.lit(self.base.name).alias("model"), F.lit(phrase).alias("phrase"), F.col("_rid").alias("id"), F.col("_rhash").alias("text_hash"), F.col("_said").alias("said"))
        seen = Observation()
        fresh.observe(seen, F.count("*").alias("n")).write.parquet(f"{self.path}/{uuid.uuid4().hex}")
        self.asked += seen.get["n"]
        return rows.join(self._kept(spark, phrase), on, "left").withColumn(out, F.when(F.col(need), F.col("_said"))).drop("_rid", "_rhash", "_kid", "_khash", "_said")


# Prompts and replies.


def judge_prompt(about: str, phrase: str, row: str) -> str:
    return f"You read one record of a table: {about}.\nRecord:\n{row}\n\nDoes this hold of the record: {phrase}?\nReply with the single word true or false."


def packed_prompt(task: str, about: str, phrase: str, rows: list[str]) -> str:
    body = "\n".join(f"[{i}] {r}" for i, r in enumerate(rows))
    want = {"count": "Reply with the number of records of which it holds.", "rows": "Reply with the numbers of those records, separated by commas.", "groups": "Group the records by it. Reply with one line per group: name | description | number of records."}[task]
    return f"You read {len(rows)} numbered records of a table: {about}.\n{body}\n\nConsider: {phrase}.\n{want}"


def extract_prompt(about: str, phrases: list[str], row: str) -> str:
    body = "\n".join(f"{i}: {p}" for i, p in enumerate(phrases))
    return f"You read one record of a table: {about}.\nRecord:\n{row}\n\nFind these in it:\n{body}\nReply with one line for each, in this order: its value alone, or a dash where the record holds none."


def parse_lines(reply: str | None, n: int) -> list[str | None]:
    """n values, a line each; numbering is dropped, dashes and missing lines are null."""
    lines = [re.sub(r"^\s*\d+\s*[:.)]\s*", "", x).strip() for x in (reply or "").strip().splitlines()][:n]
    return [None if x in ("", "-") else x for x in lines] + [None] * (n - len(lines))


def classify_prompt(about: str, phrase: str, row: str, taxonomy: list[str]) -> str:
    body = "\n".join(f"{i}: {t}" for i, t in enumerate(taxonomy))
    return f"You read one record of a table: {about}.\nRecord:\n{row}\n\nWhich of these fit its {phrase}?\n{body}\nReply with their numbers, separated by commas, or with none."


def parse_bool(reply: str | None) -> bool | None:
    m = re.search(r"\b(true|false|yes|no)\b", reply or "", re.IGNORECASE)
    return m[1].lower() in ("true", "yes") if m else None


def parse_int(reply: str | None) -> int | None:
    m = re.search(r"-?\d+", reply or "")
    return int(m[0]) if m else None


def parse_index_list(reply: str | None, size: int) -> list[int]:
    """Distinct numbers below size, in order; anything else in the reply is passed over."""
    return list(dict.fromkeys(i for i in map(int, re.findall(r"\d+", reply or "")) if i < size))


parse_categories = parse_index_list


def parse_group_table(reply: str | None, most: int = 10) -> list[tuple[str, str, int]]:
    """(name, description, count) lines; names are trimmed and case-folded, repeats dropped, the largest kept."""
    got: dict = {}
    for line in (reply or "").splitlines():
        cells = [c.strip() for c in line.strip(" |").split("|")]
        n = parse_int(cells[-1]) if len(cells) >= 2 else None
        if n is not None and cells[0] and cells[0].casefold() not in got:
            got[cells[0].casefold()] = (cells[0].casefold(), cells[1] if len(cells) > 2 else "", n)
    return sorted(got.values(), key=lambda g: (-g[2], g[0]))[:most]
