"""URL filter: host-suffix and path-prefix expressions, joined on short hash prefixes, then confirmed.

A rule is ``host/path``; it fits its host and all subdomains if the URL's path starts with the rule's.
Each URL is expanded into one expression for each suffix of its host (at label boundaries, of as many labels
as a rule has at most) and each path length that occurs among the rules. Expressions meet rules on the first 32 bits of a SHA-256 digest, the
whole digests confirm, and the longest rule wins; of equal rules, block wins. Nothing fits: allow.

Host: after the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased. Path: from there up to
``?``, ``#`` or the end. A null URL, or one without ``://``, has empty host and path and is allowed. Page ids
may be null or repeat, each row is judged by itself; extra columns are ignored. Native SQL throughout.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm.store import ascii_lower, bounded_broadcast, table

#: (verdict, rule), as the contract of the registered query fixes them.
RULES = [
    ("allow", "org/"),
    ("block", "example.org/es/"),
    ("block", "example.org/en/1"),
    ("allow", "com/fr/"),
    ("block", "com/de/"),
]


def rule_table(spark: SparkSession, rules: list[tuple[str, str]] | DataFrame) -> DataFrame:
    """(rule, verdict, path_length, digest, short): one row for each different rule."""
    frame = rules if isinstance(rules, DataFrame) else spark.createDataFrame(rules, "verdict string, rule string")
    known = frame.where("rule is not null").groupBy("rule").agg(F.max("verdict").alias("verdict"))
    digest = F.sha2("rule", 256)
    return known.select("rule", "verdict", (F.length("rule") - F.instr("rule", "/") + 1).alias("path_length"), digest.alias("digest"), F.substring(digest, 1, 8).alias("short"))


def host_and_path(url: str = "url") -> tuple:
    """Columns host and path of a URL column."""
    rest = F.expr(f"case when instr({url}, '://') > 0 then substr({url}, instr({url}, '://') + 3) else '' end")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    after = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return ascii_lower(host), after


def filter_urls(spark: SparkSession, pages: DataFrame, rules: list[tuple[str, str]] | DataFrame) -> DataFrame:
    """One row per page: page_id, host, path, rule (null if none fits), verdict."""
    known = rule_table(spark, rules)
    count = known.count()
    lengths = sorted(r[0] for r in known.select("path_length").distinct().collect())  # at most as many as a URL is long
    host, path = host_and_path()
    urls = pages.select("page_id", "url").select("page_id", host.alias("host"), path.alias("path"), F.monotonically_increasing_id().alias("row"))
    most = known.agg(F.max(F.length("rule") - F.length(F.regexp_replace("rule", r"\.", "")))).first()[0] or 0  # more dots than a rule's host has
    dots = F.length("host") - F.length(F.translate("host", ".", ""))
    suffixes = F.transform(F.sequence(F.lit(1), F.least(dots + 1, F.lit(most + 1))), lambda k: F.element_at(F.transform(F.array(F.col("host")), lambda h: F.call_function("substring_index", h, F.lit("."), -k)), 1))
    fitting = F.filter(F.array(*(F.lit(x) for x in lengths)).cast("array<int>"), lambda x: x <= F.length("path"))
    expressions = F.flatten(F.transform(suffixes, lambda s: F.transform(fitting, lambda x: F.concat(s, F.substr(F.col("path"), F.lit(1), x)))))
    spread = urls.select("row", "page_id", "host", "path", F.explode_outer(expressions).alias("expression"))
    hashed = spread.withColumn("digest", F.sha2("expression", 256)).withColumn("short", F.substring("digest", 1, 8))
    met = hashed.join(bounded_broadcast(known, count), ["short"], "left").select("row", "page_id", "host", "path", F.when(hashed["digest"] == known["digest"], F.struct(F.length("rule").alias("long"), known["rule"], "verdict")).alias("fit"))
    best = met.groupBy("row", "page_id", "host", "path").agg(F.max("fit").alias("fit"))
    return best.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), F.coalesce("fit.verdict", F.lit("allow")).alias("verdict"))


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(spark, table(spark, sf_dir, "pages"), RULES)


ORACLE = r"""
WITH r AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), u AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r
), rules(h, p, v) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
f AS (
  SELECT page_id, arg_max(h || p, length(h || p)) AS rule, arg_max(v, length(h || p)) AS v
  FROM u JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY page_id
)
SELECT u.page_id, host, path, f.rule, coalesce(f.v, 'allow') AS verdict FROM u LEFT JOIN f USING (page_id)
"""
