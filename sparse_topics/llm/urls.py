"""URL filter: host-suffix and path-prefix expressions, short-hash equi-join, full-digest check, rule precedence.

A URL's host is what follows the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; its path goes on
to ``?``, ``#`` or the end. Each URL is expanded into the expressions that a rule could be written as: host suffixes of
as many labels as some rule has, times path prefixes as long as some rule's. So the expansion is bounded by the rule
list, not by the URL. Expressions meet the rules by the first 32 bits of their SHA-256 and are confirmed by the whole
digest. The longest fitting rule wins (ties: longer host, then code-point order); a URL that no rule fits is allowed.

Defined results: a null URL or one without ``://`` has empty host and path and no rule; repeated rows each get their
verdict; empty tables and rule lists work; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower

RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]
BROADCAST_RULES = 200_000


def split_url(url: Column) -> tuple[Column, Column]:
    start = F.instr(url, "://")
    rest = F.when(start > 0, F.substring(url, start + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    parts = r"^([^/?#]*)([^?#]*)"
    return ascii_lower(F.regexp_extract(rest, parts, 1)), F.regexp_extract(rest, parts, 2)


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    return spark.createDataFrame(rules, "rule_host string, rule_path string, rule_verdict string")


def filter_urls(pages: DataFrame, rules: DataFrame, *, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """(page_id, host, path, rule, verdict) for each row of ``pages``; rules: (rule_host, rule_path, rule_verdict)."""
    sizes = rules.agg(
        F.collect_set(F.size(F.split("rule_host", r"\."))).alias("labels"), F.collect_set(F.length("rule_path")).alias("lengths"), F.count(F.lit(1)).alias("n")
    ).first()
    host, path = split_url(F.col(url_col))
    rows = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"), F.monotonically_increasing_id().alias("row"))
    labels = F.split("host", r"\.")
    counts, lengths = sorted(sizes["labels"]) or [0], sorted(sizes["lengths"]) or [0]
    suffixes = F.filter(F.array(*[F.when(F.size(labels) >= n, F.concat_ws(".", F.slice(labels, F.greatest(F.size(labels) - n + 1, F.lit(1)), n))) for n in counts]), lambda x: x.isNotNull())
    prefixes = F.filter(F.array(*[F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in lengths]), lambda x: x.isNotNull())
    spread = rows.withColumn("h", F.explode_outer(suffixes)).withColumn("p", F.explode_outer(prefixes))
    # a space stands in no host, so that host and path can't be confused
    digest = lambda h, p: F.sha2(F.concat(h, F.lit(" "), p), 256)
    asked = spread.withColumn("digest", digest(F.col("h"), F.col("p"))).withColumn("short", F.substring("digest", 1, 8))
    known = rules.select(
        digest(F.col("rule_host"), F.col("rule_path")).alias("rule_digest"), F.concat("rule_host", "rule_path").alias("rule"), F.length("rule_host").alias("host_length"), "rule_verdict"
    ).withColumn("rule_short", F.substring("rule_digest", 1, 8))
    if sizes["n"] <= BROADCAST_RULES:
        known = F.broadcast(known)
    met = asked.join(known, (F.col("short") == F.col("rule_short")) & (F.col("digest") == F.col("rule_digest")), "left")
    best = F.max(F.when(F.col("rule").isNotNull(), F.struct(F.length("rule").alias("n"), F.col("host_length"), F.col("rule"), F.col("rule_verdict")))).alias("best")
    # the rows of one URL stand together in one partition, so partial aggregation leaves one of them to move
    judged = met.groupBy("row", "page_id", "host", "path").agg(best)
    return judged.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.rule_verdict", F.lit(default)).alias("verdict"))


SQL = r"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(rest, '^([^/?#]*)([^?#]*)', 2) AS path FROM u),
r(h, q, v) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
m AS (SELECT page_id, host, path, (SELECT h || q || ' ' || v FROM r WHERE (p.host = h OR ends_with(p.host, '.' || h)) AND starts_with(p.path, q)
    ORDER BY length(h || q) DESC, length(h) DESC LIMIT 1) AS won FROM p)
SELECT page_id, host, path, split_part(won, ' ', 1) AS rule, coalesce(split_part(won, ' ', 2), 'allow') AS verdict FROM m
"""
