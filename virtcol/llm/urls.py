"""URL rules, and block decisions carried to aliases.

Pages that redirect to each other or name each other as canonical are one
resource.  Their links are the edges of a graph whose connected components a
distributed contraction finds; a component that holds a blocked address is
blocked.  A page's own rule always comes first, so an explicit allow stands.
DataFrame functions only.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, bounded_broadcast
from .components import components

#: (verdict, host and path)
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
#: A list of up to so many rules becomes one expression; a longer one is joined on host suffixes.
INLINE = 200
MOST_RULES = 1_000_000


def _rest(url: Column) -> Column:
    at = F.locate("://", F.coalesce(url, F.lit("")))
    return F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))


def _lower(x: Column) -> Column:
    return F.translate(x, string.ascii_uppercase, string.ascii_lowercase)


def host_of(url: Column) -> Column:
    return _lower(F.regexp_extract(_rest(url), r"^[^/?#]*", 0))


def path_of(url: Column) -> Column:
    return F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1)


def with_address(df: DataFrame, url: str, out: str) -> DataFrame:
    """df with what names the resource of column url: host, path and query; scheme and fragment are left out, an empty path is the root. Null without a host.

    Each step is a column of its own, so no expression is computed twice.
    """
    return (
        df.withColumn("__rest", _rest(F.col(url)))
        .withColumns({"__head": _lower(F.regexp_extract("__rest", r"^[^/?#]*", 0)), "__mid": F.regexp_extract("__rest", r"^[^/?#]*([^?#]*)", 1), "__query": F.regexp_extract("__rest", r"^[^?#]*(\?[^#]*)?", 1)})
        .withColumn(out, F.when(F.col("__head") != "", F.concat("__head", F.when(F.col("__mid") == "", F.lit("/")).otherwise(F.col("__mid")), "__query")))
        .drop("__rest", "__head", "__mid", "__query")
    )


def apply_rules(df: DataFrame, rules: list[tuple[str, str]] | tuple, host: str, path: str) -> DataFrame:
    """df with rule (null if none fits) and rule_verdict. The longest rule wins; of equal rules given twice, the first."""
    ordered = sorted(dict(reversed([(r, v) for v, r in rules])).items(), key=lambda x: (-len(x[0]), x[0]))
    if len(ordered) <= INLINE:
        rule = verdict = None
        for text, kind in ordered:
            name, _, rest = text.partition("/")
            fits = ((F.col(host) == name) | F.col(host).endswith("." + name)) & F.col(path).startswith("/" + rest)
            rule = F.when(fits, F.lit(text)) if rule is None else rule.when(fits, F.lit(text))
            verdict = F.when(fits, F.lit(kind)) if verdict is None else verdict.when(fits, F.lit(kind))
        null = F.lit(None).cast("string")
        return df.withColumns({"rule": null if rule is None else rule.otherwise(null), "rule_verdict": null if verdict is None else verdict.otherwise(null)})
    table = df.sparkSession.createDataFrame([(r.partition("/")[0], "/" + r.partition("/")[2], r, v) for r, v in ordered], "h string, p string, r string, v string")
    pairs = df.select(host, path).distinct()
    labels = F.split(F.col(host), r"\.")
    ends = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels) - i + 1), "."))
    best = (
        pairs.withColumn("h", F.explode(ends))
        .join(bounded_broadcast(table, MOST_RULES), "h")
        .where(F.startswith(F.col(path), F.col("p")))
        .groupBy(host, path)
        .agg(F.max_by(F.struct("r", "v"), F.struct(F.length("r"), F.col("r"))).alias("b"))
        .select(F.col(host).alias("__h"), F.col(path).alias("__p"), F.col("b.r").alias("rule"), F.col("b.v").alias("rule_verdict"))
    )
    return df.join(best, (F.col(host) == F.col("__h")) & (F.col(path) == F.col("__p")), "left").drop("__h", "__p")


CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?canonical\b)[^>]*?\bhref\s*=\s*["']?([^"'\s>]+)"""
REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?refresh\b)[^>]*?\bcontent\s*=\s*["'][^"'>]*?url\s*=\s*([^"'\s>]+)"""


def absolute(target: Column, host: Column, path: Column) -> Column:
    """A link's target as an absolute URL, seen from its page's host and path."""
    folder = F.regexp_replace(path, r"[^/]*$", "")
    return (
        F.when(target.contains("://"), target)
        .when(target.startswith("//"), F.concat(F.lit("x:"), target))
        .when(target.startswith("/"), F.concat(F.lit("x://"), host, target))
        .when(target.startswith("#"), F.lit(None).cast("string"))
        .otherwise(F.concat(F.lit("x://"), host, F.when(folder == "", F.lit("/")).otherwise(folder), target))
    )


def _both(df: DataFrame, a: str, b: str) -> DataFrame:
    return with_address(with_address(df, a, "u"), b, "v").select("u", "v")


def alias_edges(pages: DataFrame, scratch: Scratch, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(u, v): addresses that a page's canonical link or refresh redirect makes one; rows with a null or with u = v are no edges.

    The few links found are written first: a later filter would else be pushed into these expressions again and again.
    """
    html = F.col(html_col)
    some = pages.select(F.col(url_col).alias("__url"), html.alias("__html")).where(html.rlike("(?i)canonical|refresh"))
    targets = F.array(*(F.nullif(F.regexp_extract("__html", p, 1), F.lit("")) for p in (CANONICAL, REFRESH)))
    found = some.select("__url", F.explode(targets).alias("__t")).where("__t IS NOT NULL")
    placed = scratch.keep(found.withColumns({"__h": host_of(F.col("__url")), "__p": path_of(F.col("__url"))}), "links")
    return _both(placed.select("__url", absolute(F.col("__t"), F.col("__h"), F.col("__p")).alias("__t")), "__url", "__t")


def judge(pages: DataFrame, rules=RULES, redirects: DataFrame | None = None, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """pages with host, path, rule, verdict.

    redirects (from_url, to_url) adds edges that a crawl has seen.  Null urls
    and urls without "://" have an empty host and path, fit no rule, have no
    alias and are allowed.  Columns with the result's names are replaced.
    """
    scratch = Scratch(pages.sparkSession, "urls")
    edges = alias_edges(pages, scratch, url_col, html_col)
    if redirects is not None:
        edges = edges.union(_both(redirects, "from_url", "to_url"))
    edges = scratch.keep(edges, "aliases").where("u <> v")
    made = [c for c in ("host", "path", "rule", "verdict", "rule_verdict") if c != url_col]
    named = pages.drop(*made).withColumns({"host": host_of(F.col(url_col)), "path": path_of(F.col(url_col))})
    ruled = apply_rules(named, rules, "host", "path")
    if edges.isEmpty():
        return ruled.withColumn("verdict", F.coalesce("rule_verdict", F.lit("allow"))).drop("rule_verdict")
    members = components(edges, scratch)
    as_url = F.concat(F.lit("x://"), F.col("node"))
    judged = apply_rules(members.withColumns({"host": host_of(as_url), "path": path_of(as_url)}), rules, "host", "path")
    roots = judged.groupBy("root").agg(F.max(F.col("rule_verdict") == "block").alias("bad")).where("bad").select("root")
    aliases = scratch.keep(members.join(roots, "root", "left_semi").select(F.col("node").alias("__node")), "blocked")
    return (
        with_address(ruled, url_col, "__address")
        .join(aliases.distinct(), F.col("__address") == F.col("__node"), "left")
        .withColumn("verdict", F.coalesce("rule_verdict", F.when(F.col("__node").isNotNull(), F.lit("block")).otherwise(F.lit("allow"))))
        .drop("rule_verdict", "__address", "__node")
    )


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")).select("page_id", "host", "path", "rule", "verdict")


def _sql_address(u: str) -> str:
    rest = f"substr({u}, instr({u}, '://') + 3)"
    low = f"translate(regexp_extract({rest}, '^[^/?#]*'), '{string.ascii_uppercase}', '{string.ascii_lowercase}')"
    path = f"regexp_extract({rest}, '^[^/?#]*([^?#]*)', 1)"
    return f"CASE WHEN instr({u}, '://') > 0 AND {low} <> '' THEN {low} || CASE WHEN {path} = '' THEN '/' ELSE {path} END || regexp_extract({rest}, '^[^?#]*(\\?[^#]*)?', 1) END"


def _sql_rule(host: str, path: str, pick: int) -> str:
    whens = ""
    for verdict, text in sorted(RULES, key=lambda x: -len(x[1])):
        name, _, rest = text.partition("/")
        whens += f" WHEN ({host} = '{name}' OR ends_with({host}, '.{name}')) AND starts_with({path}, '/{rest}') THEN '{(verdict, text)[pick]}'"
    return f"CASE{whens} END"


OP6_SQL = f"""
WITH RECURSIVE p AS (
  SELECT page_id, url, html,
    CASE WHEN instr(coalesce(url, ''), '://') > 0 THEN translate(regexp_extract(substr(url, instr(url, '://') + 3), '^[^/?#]*'), '{string.ascii_uppercase}', '{string.ascii_lowercase}') ELSE '' END AS host,
    CASE WHEN instr(coalesce(url, ''), '://') > 0 THEN regexp_extract(substr(url, instr(url, '://') + 3), '^[^/?#]*([^?#]*)', 1) ELSE '' END AS path FROM pages),
links AS (
  SELECT url, host, path, unnest([
    nullif(regexp_extract(coalesce(regexp_extract(html, '(?is)<link\\b[^>]*\\brel\\s*=\\s*["'']?canonical\\b[^>]*>'), ''), '(?is)\\bhref\\s*=\\s*["'']?([^"''\\s>]+)', 1), ''),
    nullif(regexp_extract(coalesce(regexp_extract(html, '(?is)<meta\\b[^>]*\\bhttp-equiv\\s*=\\s*["'']?refresh\\b[^>]*>'), ''), '(?is)\\bcontent\\s*=\\s*["''][^"''>]*?url\\s*=\\s*([^"''\\s>]+)', 1), '')]) AS t FROM p),
whole AS (
  SELECT url, CASE WHEN contains(t, '://') THEN t WHEN starts_with(t, '//') THEN 'x:' || t WHEN starts_with(t, '/') THEN 'x://' || host || t
    WHEN starts_with(t, '#') THEN NULL ELSE 'x://' || host || CASE WHEN regexp_replace(path, '[^/]*$', '') = '' THEN '/' ELSE regexp_replace(path, '[^/]*$', '') END || t END AS t FROM links WHERE t IS NOT NULL),
edges AS (SELECT DISTINCT {_sql_address('url')} AS u, {_sql_address('t')} AS v FROM whole),
both_ways AS (SELECT u, v FROM edges WHERE u <> v UNION SELECT v, u FROM edges WHERE u <> v),
reach(a, b) AS (SELECT u, v FROM both_ways UNION SELECT r.a, e.v FROM reach r JOIN both_ways e ON r.b = e.u),
parts AS (SELECT a, b, regexp_extract(b, '^[^/]*') AS host, regexp_extract(b, '^[^/]*([^?#]*)', 1) AS path FROM (SELECT a, b FROM reach UNION SELECT u, u FROM both_ways)),
bad AS (SELECT DISTINCT a FROM parts WHERE {_sql_rule('host', 'path', 0)} = 'block'),
named AS (SELECT p.*, {_sql_rule('host', 'path', 1)} AS rule, {_sql_rule('host', 'path', 0)} AS own, {_sql_address('url')} AS address FROM p)
SELECT page_id, host, path, rule, coalesce(own, CASE WHEN bad.a IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict FROM named LEFT JOIN bad ON named.address = bad.a
"""
