"""URL filter by expanded host-suffix and path-prefix expressions.

Every URL is expanded into pairs (host suffix, path prefix). An equi-join on a short prefix of the expression's digest finds the rules
that may fit, the full digest confirms them, and the longest rule decides. Verdicts belong to (host, path) and are joined back by these
values, so no row needs a number of its own. Rules whose bytes were counted and found few are sent to every executor, so that only hits
are shuffled; of more rules the join is an ordinary equi-join, whose popular expressions Spark splits, as a rule has one row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules of so many bytes at most are sent to every executor.
BROADCAST_BYTES = 16 << 20
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL; both are empty for a null URL or one without ``://``."""
    at = F.locate("://", url)
    rest = F.coalesce(F.when(at > 0, F.substr(url, at + 3)), F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), _UPPER, _LOWER)
    return host, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def url_verdicts(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow", prefix_hex: int = 8) -> DataFrame:
    """Judge every row of ``pages``; returns its columns and ``host, path, rule, verdict`` (these replace columns of the same name).

    ``rules`` has ``host, path, verdict``; a rule fits its host and all subdomains where the URL's path starts with the rule's path. The
    longest rule (host and path together, then host) wins; of equal rules with different verdicts ``block`` wins. Null or odd URLs fit no
    rule and get ``default``. Repeated rows stay repeated; null rules and rules without host are ignored; an empty table gives no rows.
    Columns of any other name pass through. The driver gets the distinct path lengths and label counts of the rules: at most the length of
    the longest path and of the longest host.
    """
    rules = rules.where(F.col("host").isNotNull() & (F.col("host") != "")).select(
        F.translate("host", _UPPER, _LOWER).alias("r_host"), F.coalesce("path", F.lit("")).alias("r_path"), F.col("verdict").alias("r_verdict")
    )
    keyed = rules.groupBy("r_host", "r_path").agg(F.max("r_verdict").alias("r_verdict")).withColumn("r_digest", _digest(F.col("r_host"), F.col("r_path")))
    keyed = keyed.withColumn("r_key", F.substring("r_digest", 1, prefix_hex))
    known = keyed.agg(
        F.collect_set(F.length("r_path")).alias("lengths"), F.collect_set(F.size(F.split("r_host", r"\."))).alias("depths"),
        F.sum(F.octet_length("r_host") + F.octet_length("r_path") + F.lit(64 + prefix_hex + 60)).alias("bytes"),
    ).first()
    if (known["bytes"] or 0) <= BROADCAST_BYTES:
        keyed = F.broadcast(keyed)
    host, path = url_parts(F.col("u"))
    rows = pages.select(F.struct(*[F.col(f"`{c}`") for c in pages.columns]).alias("row"), F.col(f"`{url}`").cast("string").alias("u"))
    rows = rows.select("row", host.alias("x_host"), path.alias("x_path"))
    labels = F.split("x_host", r"\.")
    depths = F.filter(F.array(*[F.lit(n) for n in sorted(known["depths"])]).cast("array<int>"), lambda n: n <= F.size(labels))
    hosts = F.transform(depths, lambda n: F.array_join(F.slice(labels, F.size(labels) - n + 1, n), "."))
    fits = F.filter(F.array(*[F.lit(n) for n in sorted(known["lengths"])]).cast("array<int>"), lambda n: n <= F.length("x_path"))
    paths = F.transform(fits, lambda n: F.substr(F.col("x_path"), F.lit(1), n))
    found = rows.where("x_host <> ''").select("x_host", "x_path", F.explode(hosts).alias("e_host"), paths.alias("ps"))
    found = found.where("e_host <> ''").select("x_host", "x_path", "e_host", F.explode("ps").alias("e_path")).withColumn("e_digest", _digest(F.col("e_host"), F.col("e_path")))
    found = found.select("x_host", "x_path", "e_digest", F.substring("e_digest", 1, prefix_hex).alias("e_key"))
    hits = found.join(keyed, F.col("e_key") == F.col("r_key")).where(F.col("e_digest") == F.col("r_digest"))
    rule = F.concat("r_host", "r_path")
    place = F.struct(F.length(rule).alias("n"), F.length("r_host").alias("m"), (F.col("r_verdict") == "block").alias("b"), rule.alias("rule"), "r_verdict")
    best = hits.groupBy(F.col("x_host").alias("b_host"), F.col("x_path").alias("b_path")).agg(F.max(place).alias("best"))
    out = rows.join(best, (F.col("x_host") == F.col("b_host")) & (F.col("x_path") == F.col("b_path")), "left")
    taken = {"host", "path", "rule", "verdict"}
    kept = [F.col("row")[c].alias(c) for c in pages.columns if c not in taken]
    verdict = F.coalesce(F.col("best.r_verdict"), F.lit(default))
    return out.select(*kept, F.col("x_host").alias("host"), F.col("x_path").alias("path"), F.col("best.rule").alias("rule"), verdict.alias("verdict"))


#: The rule set of the registered query (fixed values): host, path, verdict.
QUERY_RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def op10_url_filter(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    rules = spark.createDataFrame(QUERY_RULES, "host string, path string, verdict string")
    return url_verdicts(pages, rules).select("page_id", "host", "path", "rule", "verdict")


OP10_SQL = """
WITH r(host, path, verdict) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'),
  ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
a AS (SELECT page_id, CASE WHEN url IS NOT NULL AND position('://' IN url) > 0 THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM a),
m AS (SELECT p.page_id, max_by(r.host || r.path, length(r.host || r.path)) AS rule, max_by(r.verdict, length(r.host || r.path)) AS verdict
  FROM p JOIN r ON (p.host = r.host OR p.host LIKE '%.' || r.host) AND starts_with(p.path, r.path) GROUP BY p.page_id)
SELECT p.page_id, p.host, p.path, m.rule, coalesce(m.verdict, 'allow') AS verdict FROM p LEFT JOIN m USING (page_id)
"""
