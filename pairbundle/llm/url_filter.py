"""URL filtering by host suffixes and path prefixes.

Each URL expands into expressions, a host suffix followed by a path prefix, of just the label counts and path lengths that rules have.
Expressions meet rules in an equi-join on a short prefix of their digest; full digests confirm, and the longest rule wins (of equally
long ones the one with the longer host). Of the matches, only
confirmed ones are shuffled, reduced to one for each URL; the rows then meet them by URL.

A null URL, or one without ``://``, has an empty host and path; no rule fits it unless one is empty itself. Repeated rows and URLs get
one row each. Empty tables give empty tables; an empty rule table leaves the default verdict. Extra columns are not read. Hosts and
paths of any length cost no more than the rules' label counts times their path lengths.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Rules of the registered query: host, path, verdict.
RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def host_and_path(url: Column) -> tuple[Column, Column]:
    """The part after the first ``://`` up to a slash, question mark, number sign or end, A-Z lowered; then what stands before ? or #."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    return F.translate(host, UPPER, LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def filter_urls(pages: DataFrame, rules: DataFrame, default: str = "allow", prefix: int = 8) -> DataFrame:
    """page_id, host, path, rule, verdict for each row of ``pages`` (page_id, url)."""
    rules = rules.select("host", "path", "verdict", F.concat("host", "path").alias("rule"))
    shape = rules.agg(F.sort_array(F.collect_set(F.size(F.split("host", r"\.")))).alias("labels"), F.sort_array(F.collect_set(F.length("path"))).alias("lengths")).first()
    host, path = host_and_path(F.col("url"))
    rows = pages.select("page_id", F.col("url").cast("string").alias("url")).select("page_id", "url", host.alias("host"), path.alias("path"))
    if not shape["labels"]:
        return rows.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    of = lambda values: F.array(*[F.lit(v) for v in values])
    suffixes = F.transform(F.filter(of(shape["labels"]), lambda k: k <= F.size("parts")), lambda k: F.array_join(F.slice("parts", F.size("parts") - k + 1, k), "."))
    prefixes = F.transform(F.filter(of(shape["lengths"]), lambda k: k <= F.length("path")), lambda k: F.substring("path", F.lit(1), k))
    made = rows.select("url", F.split("host", r"\.").alias("parts"), "path").select("url", F.explode(suffixes).alias("suffix"), prefixes.alias("prefixes"))
    made = made.select("url", "suffix", F.explode("prefixes").alias("start")).select("url", F.sha2(F.concat("suffix", "start"), 256).alias("digest")).withColumn("short", F.substring("digest", 1, prefix))
    known = rules.withColumn("full", F.sha2("rule", 256)).withColumn("short", F.substring("full", 1, prefix))
    fits = made.join(known, "short").where("digest = full")
    rank = F.struct(F.length("rule").alias("n"), F.length("host").alias("h"), "rule", "verdict")
    best = fits.groupBy("url").agg(F.max(rank).alias("best")).select("url", F.col("best.rule").alias("rule"), F.col("best.verdict").alias("verdict"))
    return rows.join(best, "url", "left").select("page_id", "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    rules = F.array(*[F.struct(F.lit(h).alias("host"), F.lit(p).alias("path"), F.lit(v).alias("verdict")) for h, p, v in RULES])
    return filter_urls(pages, spark.range(1).select(F.inline(rules)))


ORACLE_OP7 = """
WITH rules(host, path, verdict) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
p AS (SELECT page_id, row_number() OVER () AS k, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
q AS (SELECT page_id, k, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM p),
m AS (SELECT q.k, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY q.k ORDER BY length(r.host || r.path) DESC, length(r.host) DESC) AS n
      FROM q JOIN rules r ON (q.host = r.host OR ends_with(q.host, '.' || r.host)) AND starts_with(q.path, r.path))
SELECT q.page_id, q.host, q.path, m.rule, coalesce(m.verdict, 'allow') AS verdict FROM q LEFT JOIN m ON q.k = m.k AND m.n = 1
"""
