"""Structured Streaming forms of the relational parts and of the methods; each runs in AvailableNow mode to a table."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..tables import shared_folder


def replay(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a stream of files; timestamps get a zone (UTC) so that watermarks apply."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    out = spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(f"{sf_dir}/[{name[0]}]{name[1:]}.parquet")
    return out.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in out.columns else out


def to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything available, run through and read back."""
    spark, name = stream.sparkSession, "stream_" + uuid.uuid4().hex[:10]
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", shared_folder(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def to_files(stream: DataFrame) -> DataFrame:
    """to_table for streams whose rows grow with the input: each batch goes to Parquet in the shared folder, and state lies on the workers' disks.

    The driver holds no row.
    """
    spark, sink = stream.sparkSession, shared_folder(stream.sparkSession, "rows")
    store = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(store, None)
    spark.conf.set(store, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream.writeStream.format("parquet").option("path", sink).option("checkpointLocation", shared_folder(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set(store, before) if before else spark.conf.unset(store)
    return spark.read.schema(stream.schema).parquet(sink)


def stream_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return to_table(replay(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n")), "complete")


def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = replay(spark, sf_dir, "events").withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return to_table(w, "complete").select(F.to_date("w.start").alias("day"), "event_type", "n")


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = replay(spark, sf_dir, "events").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return to_table(w, "complete").select(F.to_date("w.start").alias("day"), "n")


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = replay(spark, sf_dir, "events").groupBy("user_id", F.session_window("ts", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return to_table(w, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each id once, however late it comes again; rows without an id are none."""
    d = replay(spark, sf_dir, "events").where("event_id IS NOT NULL").select("event_id").dropDuplicates(["event_id"])
    return to_files(d).agg(F.count("*").alias("n"))


def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment")
    j = replay(spark, sf_dir, "events").join(customers, F.col("user_id") == F.col("c_custkey"))
    return to_table(j.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def stream_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = replay(spark, sf_dir, "events").where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    b = replay(spark, sf_dir, "events").where("event_type = 'purchase'").select("user_id", F.col("ts").alias("t2")).withWatermark("t2", "1 hour")
    return to_table(a.join(b, (F.col("u") == F.col("user_id")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr("interval 1 hour"))).select("u", "t1", "t2")).agg(F.count("*").alias("n"))


def windowed_estimate(stream: DataFrame, id_col: str, window: str, f: str, budget: int = 64) -> DataFrame:
    """COUNT under a condition per window: state is the window's size and its `budget` rows with the least keys, whatever arrives."""
    ready = stream.select(F.expr(window).alias("w"), F.md5(F.col(id_col).cast("string").cast("binary")).alias("k"), F.coalesce(F.expr(f), F.lit(False)).cast("int").alias("f"))

    def update(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, keys, fs = state.get if state.exists else (0, [], [])
        rows = list(zip(keys, fs))
        for b in batches:
            n += len(b)
            rows = sorted([*rows, *zip(b["k"], (int(x) for x in b["f"]))])[:budget]
        state.update((n, [k for k, _ in rows], [x for _, x in rows]))
        yield pd.DataFrame({"w": [key[0]], "n": [n], "estimate": [n * sum(x for _, x in rows) / len(rows)]})

    return ready.groupBy("w").applyInPandasWithState(update, "w string, n long, estimate double", "n long, keys array<string>, fs array<int>", "update", "NoTimeout")


def stream_windowed_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = to_table(windowed_estimate(replay(spark, sf_dir, "events"), "event_id", "date_format(ts, 'yyyy-MM-dd')", "event_type = 'click'", 1_000_000), "update")
    return got.groupBy("w").agg(F.max_by("n", "n").alias("n"), F.max_by(F.round("estimate", 6), "n").alias("estimate"))


def standing_filter(stream: DataFrame, id_col: str, source: str, judge_sql: str, budget: int, sink: str) -> None:
    """Each trigger judges at most `budget` new rows, those that the last surrogate ranks highest, appends the positives to `sink` and refits."""
    from ..index.features import build_features
    from ..index.search import active_search

    state: dict = {}

    def batch(df: DataFrame, epoch: int) -> None:
        spark, ids = df.sparkSession, df.persist()
        e = build_features(ids, id_col, source).persist()
        held = {"seen": dict(state.get("seen", {})), "vectors": dict(state.get("vectors", {})), "trace": []}

        def judge(keys: list) -> list[bool]:
            yes = {r[0] for r in ids.where(F.col(id_col).isin(keys)).where(judge_sql).select(id_col).collect()}
            return [k in yes for k in keys]

        got = active_search(e, judge, len(held["seen"]) + budget, state=held)
        state.update(held)
        new = [t[1] for t in got.trace if t[3]]
        if new:
            spark.createDataFrame([(i, epoch) for i in new], "id long, epoch long").write.mode("append").parquet(sink)
        e.unpersist()
        ids.unpersist()

    stream.writeStream.foreachBatch(batch).option("checkpointLocation", shared_folder(stream.sparkSession, "standing")).trigger(availableNow=True).start().awaitTermination()


def stream_standing_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    sink = shared_folder(spark, "hits")
    standing_filter(replay(spark, sf_dir, "documents"), "doc_id", "text", "lang = 'fr'", 64, sink)
    return spark.read.schema("id long, epoch long").parquet(sink)


def drift(features: DataFrame, centroids: np.ndarray, before: float, rise: float = 0.2) -> DataFrame:
    """Mean squared distance of new rows to fixed centroids, and whether it has risen enough to fit anew."""

    @F.pandas_udf("double")
    def distance(e: pd.Series) -> pd.Series:
        x = np.array(e.tolist(), np.float64).reshape(len(e), -1)
        return pd.Series(((x * x).sum(1)[:, None] + (centroids * centroids).sum(1) - 2 * x @ centroids.T).min(axis=1) if len(e) else [], dtype="float64")

    return features.agg(F.avg(distance("e")).alias("distance"), F.count("*").alias("n")).withColumn("refit", F.col("distance") > before * (1 + rise))


def incremental_strata(stream: DataFrame, id_col: str, source: str, centroids: np.ndarray, before: float, sink: str) -> None:
    """New rows take the nearest of fixed centroids as they come; each batch's strata and its drift are appended to `sink`, once an epoch."""
    from ..index import features as feats

    def batch(df: DataFrame, epoch: int) -> None:
        e = feats.build_features(df, id_col, source).persist()
        feats.assign(e, centroids).write.mode("overwrite").parquet(f"{sink}/strata/epoch={epoch}")
        drift(e, centroids, before).write.mode("overwrite").parquet(f"{sink}/drift/epoch={epoch}")
        e.unpersist()

    stream.writeStream.foreachBatch(batch).option("checkpointLocation", shared_folder(stream.sparkSession, "strata")).trigger(availableNow=True).start().awaitTermination()


def stream_incremental_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that came, rows whose stratum is the one a batch job gives, and batches that ask for a new fit."""
    from ..index import features as feats

    e = feats.build_features(spark.read.parquet(f"{sf_dir}/documents.parquet"), "doc_id", "text")
    c = feats.fit_kmeans(e, 10)
    before, sink = drift(e, c, 0.0).first()["distance"], shared_folder(spark, "assigned")
    incremental_strata(replay(spark, sf_dir, "documents"), "doc_id", "text", c, before, sink)
    got = spark.read.parquet(f"{sink}/strata")
    same = got.join(feats.assign(e, c).withColumnRenamed("stratum", "again"), "id").agg(F.count("*").alias("n"), F.count_if(F.col("stratum") == F.col("again")).alias("same"))
    return same.crossJoin(spark.read.parquet(f"{sink}/drift").agg(F.count_if("refit").alias("refits")))


QUERIES = {f.__name__: f for f in (stream_replay, stream_tumbling, stream_sliding, stream_sessions, stream_dedup, stream_static_join, stream_interval_join, stream_windowed_count, stream_standing_filter, stream_incremental_strata)}
SQL = {
    "stream_replay": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
    "stream_tumbling": "SELECT CAST(date_trunc('day', ts) AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT CAST(d AS DATE) AS day, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1",
    "stream_sessions": "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS s FROM events) SELECT user_id, CAST(sum(s) AS BIGINT) AS sessions, count(*) AS n FROM g GROUP BY user_id",
    "stream_dedup": "SELECT count(DISTINCT event_id) AS n FROM events",
    "stream_static_join": "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
    "stream_interval_join": "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR",
    "stream_incremental_strata": "SELECT count(*) AS n, count(*) AS same, CAST(0 AS BIGINT) AS refits FROM documents",
    "stream_windowed_count": "SELECT strftime(ts, '%Y-%m-%d') AS w, count(*) AS n, CAST(count(*) FILTER (event_type = 'click') AS DOUBLE) AS estimate FROM events GROUP BY 1",
}
