"""Ordinary operators, one query each, with the SQL that must agree."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..tables import shared_folder
from ..workloads import dialogs, pages_text, read


def _six(c, name: str):
    return F.round(c, 6).alias(name)


def scan(s, d):
    return read(s, d, "lineitem").where("l_quantity > 45 AND l_shipdate < timestamp_ntz'1995-07-01'").select("l_orderkey", "l_linenumber", "l_quantity")


def formats(s, d):
    n = read(s, d, "nation")
    out = None
    for fmt in ("csv", "json", "orc"):
        path = shared_folder(s, fmt)
        n.write.format(fmt).option("header", True).save(path)
        one = s.read.schema(n.schema).format(fmt).option("header", True).load(path).groupBy().agg(F.lit(fmt).alias("fmt"), F.count("*").alias("n"), F.sum("n_nationkey").alias("keys"))
        out = one if out is None else out.union(one)
    return out


def json(s, d):
    """A field of JSON texts, and of the same texts parsed once as variants; what is no JSON gives null."""
    e = read(s, d, "events").select("event_type", "props", F.get_json_object("props", "$.k").cast("long").alias("k"), F.try_parse_json("props").alias("v"))
    return e.groupBy("event_type").agg(F.sum("k").alias("total"), F.max(F.try_variant_get("v", "$.k", "bigint")).alias("most"), F.count_if(F.col("v").isNull()).alias("broken"))


def views(s, d):
    read(s, d, "region").createOrReplaceTempView("vc_region")
    return s.table("vc_region").select("r_regionkey", "r_name")


def sinks(s, d):
    path = shared_folder(s, "sink")
    read(s, d, "orders").select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").mode("overwrite").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count("*").alias("n"))


def paged(s, d):
    """Customers in the order of their keys, their places fetched from an interface of five pages, each page in its task.

    Places are counted within ranges of keys, so no task sorts all customers.
    """
    from ..sources.paged import PagedRows

    s.dataSource.register(PagedRows)
    c = read(s, d, "customer").select("c_custkey", F.floor(F.col("c_custkey") / 10_000).alias("range"))
    sizes = c.groupBy("range").agg(F.count("*").alias("n"))
    before = sizes.select(F.col("range").alias("of"), (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("before"))
    placed = c.join(before, F.col("range").eqNullSafe(F.col("of"))).select("c_custkey", (F.col("before") + F.row_number().over(Window.partitionBy("range").orderBy("c_custkey")) - 1).alias("row"))
    pages = s.read.format("paged_rows").option("rows", c.count()).option("pages", 5).load()
    return pages.join(placed, "row").select("row", "page", "c_custkey")


def dialog_rows(s, d):
    return dialogs(s, d).select("conv_id", "n_turns", F.length("transcript").cast("long").alias("chars"), F.md5(F.col("transcript").cast("binary")).alias("digest"))


def page_rows(s, d):
    return pages_text(s, d).groupBy("host").agg(F.count("*").alias("n"))


def projection(s, d):
    return read(s, d, "part").select("p_partkey", _six(F.col("p_retailprice") * 2, "double_price"), F.lit(1).alias("one"))


def comparisons(s, d):
    return read(s, d, "part").where("p_size <> 1 AND p_size >= 2 AND p_size <= 40 AND p_retailprice > 900 AND p_partkey < 1500").agg(F.count("*").alias("n"))


def predicates(s, d):
    o = read(s, d, "orders")
    return o.where(o.o_orderstatus.isin("F", "O") & o.o_totalprice.between(1000, 200000) & o.o_orderpriority.rlike("^[12]-") & o.o_custkey.isNotNull()).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def broadcast_join(s, d):
    """The nation table has 25 rows by definition."""
    return read(s, d, "supplier").join(F.broadcast(read(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), _six(F.sum("s_acctbal"), "balance"))


def merge_join(s, d):
    return read(s, d, "orders").hint("merge").join(read(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), _six(F.sum("l_quantity"), "quantity"))


def outer_joins(s, d):
    j = read(s, d, "documents").select("doc_id").join(read(s, d, "labels"), "doc_id", "full")
    return j.agg(F.count("*").alias("n"), F.count_if(F.col("quality").isNull()).alias("unlabelled"))


def semi_anti(s, d):
    a, b = read(s, d, "documents").select("doc_id"), read(s, d, "labels").select("doc_id")
    return a.join(b, "doc_id", "left_semi").select("doc_id", F.lit("semi").alias("kind")).union(a.join(b, "doc_id", "left_anti").select("doc_id", F.lit("anti").alias("kind")))


def theta_join(s, d):
    """Regions and nations: both fixed and tiny."""
    return read(s, d, "nation").join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") < F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


def range_join(s, d):
    """Shipped within three days of the order: days are an equality key, so no pairs are enumerated."""
    o = read(s, d, "orders").select("o_orderkey", F.explode(F.sequence(F.to_date("o_orderdate"), F.date_add(F.to_date("o_orderdate"), 2))).alias("day"))
    ship = read(s, d, "lineitem").select("l_orderkey", F.to_date("l_shipdate").alias("day"))
    return o.join(ship, (F.col("o_orderkey") == F.col("l_orderkey")) & (o.day == ship.day)).agg(F.count("*").alias("n"))


def asof_join(s, d):
    """Each purchase with the user's last click at or before it: one union, one window."""
    e = read(s, d, "events").where("event_type IN ('click', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    last = F.last(F.when(F.col("event_type") == "click", F.col("ts")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return e.withColumn("click", last).where("event_type = 'purchase'").select("event_id", F.date_format("click", "yyyy-MM-dd HH:mm:ss").alias("click"))


def semantic_join(s, d):
    """Documents that quote a benchmark passage: candidates share words from inside the passage, then the pair is judged.

    A passage may begin and end within a word and hold line breaks, so its key is up to five words after its first blank
    or break and before its last; passages without such a word are judged against every text.  Ids and keys alone are
    multiplied; texts are read again for candidates.  Null ids count as one.
    """
    words = F.split("text", r"[ \n]")
    inner = F.when(F.size(words) > 2, F.slice(words, 2, F.least(F.size(words) - 2, F.lit(5))))
    b = read(s, d, "benchmark").where("text IS NOT NULL").select(F.col("item_id").alias("item"), F.col("text").alias("passage"), F.size(inner).alias("size"), F.array_join(inner, " ").alias("k"))
    docs = read(s, d, "documents").where("text IS NOT NULL").select("doc_id", "text")
    sizes = [r[0] for r in b.where("k IS NOT NULL").select("size").distinct().collect()]  # 1 to 5
    run = lambda w, n: F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.concat_ws(" ", *(w[i + j] for j in range(n))))
    keys = lambda w: F.flatten(F.array(*(F.when(F.size(w) >= n, run(w, n)).otherwise(F.array().cast("array<string>")) for n in sizes)))
    found = docs.crossJoin(b.where("k IS NULL").select("item", "passage")).where(F.contains("text", "passage")).select("doc_id", F.col("item").alias("item_id"))
    if sizes:
        once = F.transform(F.array(words), keys)[0]  # bound as a variable, so a text is split once and not for each key
        pairs = docs.select(F.col("doc_id").alias("doc"), F.explode(F.array_distinct(once)).alias("k")).join(b.select("item", "k"), "k").select("doc", "item").distinct()
        near = docs.join(pairs, F.col("doc_id").eqNullSafe(F.col("doc"))).select("doc_id", "text", F.col("item").alias("item_id"))
        found = found.union(near.join(b.select("item", "passage"), F.col("item").eqNullSafe(F.col("item_id"))).where(F.contains("text", "passage")).select("doc_id", "item_id"))
    return found.distinct()


def pricing(s, d):
    price = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(_six(F.sum("l_quantity"), "quantity"), F.round(F.sum(price), 2).alias("revenue"), _six(F.avg("l_discount"), "discount"), F.min("l_tax").alias("least_tax"), F.max("l_tax").alias("most_tax"), F.count("*").alias("n"))


def distinct_agg(s, d):
    return read(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


def cube(s, d):
    return read(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))


def having(s, d):
    return read(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), F.count_if(F.col("o_orderstatus") == "F").alias("done")).where("n >= 15")


def quantiles(s, d):
    return read(s, d, "events").groupBy("event_type").agg(_six(F.percentile("value", F.lit(0.5)), "median"), _six(F.var_samp("value"), "variance"), F.round(F.corr("value", "user_id"), 4).alias("corr"))


def lists(s, d):
    return read(s, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles"), F.max_by("role", "turn").alias("last_role"))


def pivot(s, d):
    return read(s, d, "events").groupBy(F.dayofmonth("ts").alias("day")).pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).select("day", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("purchase", F.lit(0)).cast("long").alias("purchase"))


def ranking(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return read(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.ntile(4).over(w).alias("quartile"), _six(F.percent_rank().over(w), "pr"))


def analytic(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return read(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first_value("role").over(w).alias("opens"))


def frames(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(s, d, "events").select("event_id", _six(F.avg("value").over(w.rowsBetween(-15, 0)), "moving"), _six(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), "running"))


def topk(s, d):
    return read(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20).select("o_orderkey", "o_totalprice")


def topk_per_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return read(s, d, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_brand", "p_partkey", "rn")


def set_ops(s, d):
    a, b = read(s, d, "customer").select(F.col("c_nationkey").alias("k")), read(s, d, "supplier").select(F.col("s_nationkey").alias("k"))
    tag = lambda x, n: x.agg(F.lit(n).alias("op"), F.count("*").alias("n"))
    return tag(a.unionByName(b), "union_all").union(tag(a.intersect(b), "intersect")).union(tag(a.exceptAll(b), "except_all"))


def strings(s, d):
    return read(s, d, "documents").select("doc_id", F.length("text").cast("long").alias("chars"), F.regexp_count("text", F.lit("[0-9]")).cast("long").alias("digits"), F.md5(F.lower("text").cast("binary")).alias("digest"), F.levenshtein("lang", F.lit("en")).cast("long").alias("far"))


def dates(s, d):
    return read(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n"), F.sum(F.datediff(F.last_day("o_orderdate"), "o_orderdate")).cast("long").alias("left_days"))


def maths(s, d):
    return read(s, d, "lineitem").agg(_six(F.sum(F.sqrt("l_quantity")), "roots"), _six(F.sum(F.exp(-F.col("l_quantity") / 10)), "exps"), F.sum(F.when(F.col("l_discount") > 0.05, 1).otherwise(0)).cast("long").alias("n"))


def arrays(s, d):
    from ..index.features import dot

    e = F.col("embedding")
    return read(s, d, "embeddings").select("vec_id", _six(dot(e, F.reverse(e)), "palindrome"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


def maps(s, d):
    return read(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("event_type", "n")))).alias("m")).select(F.explode(F.transform_values("m", lambda k, v: v * 2)).alias("event_type", "twice"))


def duplicates(s, d):
    return read(s, d, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).where("n > 1")


def samples(s, d):
    from ..index.sample import uniform_sample

    return uniform_sample(read(s, d, "documents"), "doc_id", 50, 3).df.select("doc_id")


QUERIES = {f"rel_{f.__name__}": f for f in (
    scan, json, formats, views, sinks, paged, dialog_rows, page_rows, projection, comparisons, predicates, broadcast_join, merge_join, outer_joins, semi_anti, theta_join, range_join, asof_join, semantic_join, pricing, distinct_agg,
    cube, having, quantiles, lists, pivot, ranking, analytic, frames, topk, topk_per_group, set_ops, strings, dates, maths, arrays, maps, duplicates, samples,
)}
SQL = {
    "rel_scan": "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_shipdate < TIMESTAMP '1995-07-01'",
    "rel_formats": "SELECT unnest(['csv', 'json', 'orc']) AS fmt, count(*) AS n, CAST(sum(n_nationkey) AS BIGINT) AS keys FROM nation",
    "rel_views": "SELECT r_regionkey, r_name FROM region",
    "rel_sinks": "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1",
    "rel_paged": "SELECT row, CAST(row // CAST(ceil(n / 5) AS BIGINT) AS INTEGER) AS page, c_custkey FROM (SELECT c_custkey, row_number() OVER (ORDER BY c_custkey NULLS FIRST) - 1 AS row, count(*) OVER () AS n FROM customer)",
    "rel_dialog_rows": "WITH t AS (SELECT conv_id, count(*) AS n, string_agg(role || ': ' || text, chr(10) ORDER BY turn) AS x FROM conversations GROUP BY 1) SELECT conv_id, CAST(n AS INTEGER) AS n_turns, length(x) AS chars, md5(x) AS digest FROM t",
    "rel_page_rows": "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages GROUP BY 1",
    "rel_projection": "SELECT p_partkey, round(p_retailprice * 2, 6) AS double_price, 1 AS one FROM part",
    "rel_comparisons": "SELECT count(*) AS n FROM part WHERE p_size <> 1 AND p_size >= 2 AND p_size <= 40 AND p_retailprice > 900 AND p_partkey < 1500",
    "rel_predicates": "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 AND regexp_matches(o_orderpriority, '^[12]-') AND o_custkey IS NOT NULL GROUP BY 1",
    "rel_broadcast_join": "SELECT n_name, count(*) AS n, round(sum(s_acctbal), 6) AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1",
    "rel_merge_join": "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 6) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1",
    "rel_outer_joins": "SELECT count(*) AS n, count(*) FILTER (quality IS NULL) AS unlabelled FROM documents FULL JOIN labels USING (doc_id)",
    "rel_semi_anti": "SELECT doc_id, CASE WHEN doc_id IN (SELECT doc_id FROM labels) THEN 'semi' ELSE 'anti' END AS kind FROM documents",
    "rel_theta_join": "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey < r_regionkey GROUP BY 1",
    "rel_range_join": "SELECT count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND CAST(l_shipdate AS DATE) BETWEEN CAST(o_orderdate AS DATE) AND CAST(o_orderdate AS DATE) + 2",
    "rel_asof_join": "SELECT p.event_id, strftime(c.ts, '%Y-%m-%d %H:%M:%S') AS click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts",
    "rel_semantic_join": "SELECT DISTINCT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "rel_pricing": "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 6) AS quantity, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS discount, min(l_tax) AS least_tax, max(l_tax) AS most_tax, count(*) AS n FROM lineitem GROUP BY 1, 2",
    "rel_distinct_agg": "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
    "rel_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping(o_orderstatus) * 2 + grouping(o_orderpriority) AS INTEGER) AS level FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "rel_having": "SELECT o_custkey, count(*) AS n, count(*) FILTER (o_orderstatus = 'F') AS done FROM orders GROUP BY 1 HAVING count(*) >= 15",
    "rel_quantiles": "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(var_samp(value), 6) AS variance, round(corr(value, user_id), 4) AS corr FROM events GROUP BY 1",
    "rel_lists": "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles, arg_max(role, turn) AS last_role FROM conversations GROUP BY 1",
    "rel_pivot": "SELECT CAST(day(ts) AS INTEGER) AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1",
    "rel_ranking": "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(ntile(4) OVER w AS INTEGER) AS quartile, round(percent_rank() OVER w, 6) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)",
    "rel_analytic": "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after, first_value(role) OVER w AS opens FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)",
    "rel_frames": "SELECT event_id, round(avg(value) OVER (w ROWS BETWEEN 15 PRECEDING AND CURRENT ROW), 6) AS moving, round(sum(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 6) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "rel_topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5",
    "rel_topk_per_group": "SELECT p_brand, p_partkey, CAST(rn AS INTEGER) AS rn FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) WHERE rn <= 3",
    "rel_set_ops": "SELECT 'union_all' AS op, count(*) AS n FROM (SELECT c_nationkey FROM customer UNION ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', count(*) FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except_all', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)",
    "rel_strings": "SELECT doc_id, length(text) AS chars, CAST(len(regexp_extract_all(text, '[0-9]')) AS BIGINT) AS digits, md5(lower(text)) AS digest, levenshtein(lang, 'en') AS far FROM documents",
    "rel_dates": "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, count(*) AS n, CAST(sum(date_diff('day', CAST(o_orderdate AS DATE), last_day(o_orderdate))) AS BIGINT) AS left_days FROM orders GROUP BY 1, 2",
    "rel_maths": "SELECT round(sum(sqrt(l_quantity)), 6) AS roots, round(sum(exp(-l_quantity / 10)), 6) AS exps, CAST(sum(CASE WHEN l_discount > 0.05::DOUBLE THEN 1 ELSE 0 END) AS BIGINT) AS n FROM lineitem",
    "rel_arrays": "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], list_reverse(embedding)::DOUBLE[]), 6) AS palindrome, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive FROM embeddings",
    "rel_maps": "SELECT event_type, CAST(2 * count(*) AS BIGINT) AS twice FROM events GROUP BY 1",
    "rel_duplicates": "SELECT md5(text) AS digest, count(*) AS n, min(doc_id) AS first FROM documents GROUP BY 1 HAVING count(*) > 1",
    "rel_json": "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total, max(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS most, count(*) FILTER (NOT json_valid(coalesce(props, 'x'))) AS broken FROM events GROUP BY 1",
    "rel_samples": "SELECT doc_id FROM documents ORDER BY md5('3:' || doc_id), doc_id LIMIT 50",
}
