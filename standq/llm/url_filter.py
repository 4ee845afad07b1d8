"""URL rules by host suffix and path prefix, in DataFrame functions alone.

Every URL is expanded into the host-suffix and path-prefix expressions that some rule could equal; they meet the rules
in an equi-join on a short hash prefix; the full digest is compared; the longest rule decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rules are sent to every executor up to so many rows (some 200 bytes each); a larger table is joined by shuffle, with
#: the hash prefix salted so that one rule that most URLs meet is spread.
BROADCAST_RULES = 100_000
SALTS = 32
PREFIX_HEX = 8

#: The rules of the query's contract.
RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]  # fixed values


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (ASCII lower case) and path; both empty where there is no ``://`` or no URL."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def filter_urls(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """Judge every URL: ``id_col``, host, path, rule (null if none fits) and verdict (``default`` if none fits).

    ``rules`` has host, path, verdict. The longest host + path wins; of equal length the longer host, then block before
    allow. Repeated pages give repeated rows; null URLs have no host and get ``default``; other columns are not read.
    """
    rules = rules.select(
        F.col("host").alias("r_host"), F.col("path").alias("r_path"), F.col("verdict").alias("r_verdict"), F.concat("host", "path").alias("r_rule")
    ).distinct()
    shape = rules.agg(F.collect_set(F.size(F.split("r_host", r"\."))).alias("labels"), F.collect_set(F.length("r_path")).alias("lengths"), F.count("*").alias("n")).first()
    host, path = split_url(F.col(f"`{url_col}`"))
    urls = pages.select(F.monotonically_increasing_id().alias("rid"), F.col(f"`{id_col}`").alias("id"), host.alias("host"), path.alias("path"))
    labels = F.split("host", r"\.")
    expressions = [
        F.when((F.size(labels) >= n) & (F.length("path") >= m), F.concat(F.array_join(F.slice(labels, -n, n), "."), F.substring("path", 1, m)))
        for n in sorted(shape["labels"])
        for m in sorted(shape["lengths"])
    ] or [F.lit(None).cast("string")]
    asked = urls.withColumn("expression", F.explode_outer(F.array_distinct(F.array_compact(F.array(*expressions)))))
    asked = asked.withColumn("digest", F.sha2("expression", 256))
    held = rules.withColumn("r_digest", F.sha2("r_rule", 256)).withColumn("short", F.substring("r_digest", 1, PREFIX_HEX))
    asked = asked.withColumn("short", F.substring("digest", 1, PREFIX_HEX))
    if shape["n"] <= BROADCAST_RULES:
        held, on = F.broadcast(held), ["short"]
    else:
        held = held.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        asked, on = asked.withColumn("salt", F.pmod(F.xxhash64("rid"), F.lit(SALTS)).cast("int")), ["short", "salt"]
    met = asked.join(held, on, "left")
    fits = F.col("digest") == F.col("r_digest")
    rank = F.struct(F.length("r_rule").alias("a"), F.length("r_host").alias("b"), (F.col("r_verdict") == "block").alias("c"), "r_rule", "r_verdict")
    best = met.groupBy("rid", "id", "host", "path").agg(F.max(F.when(fits, rank)).alias("best"))
    return best.select(
        F.col("id").alias(id_col), "host", "path", F.col("best.r_rule").alias("rule"), F.coalesce(F.col("best.r_verdict"), F.lit(default)).alias("verdict")
    )


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    return filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"), rules)


ORACLE = r"""
WITH u AS (
  SELECT page_id, CASE WHEN url IS NOT NULL AND instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), h AS (
  SELECT page_id, regexp_extract(rest, '^([^/?#]*)', 1) AS raw, rest FROM u
), p AS (
  SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(substr(rest, length(raw) + 1), '^([^?#]*)', 1) AS path FROM h
), r(rh, rp, v) AS (
  VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')
), m AS (
  SELECT page_id, host, path, max_by(rh || rp, length(rh || rp)) AS rule, max_by(v, length(rh || rp)) AS v
  FROM p LEFT JOIN r ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp)
  GROUP BY page_id, host, path
)
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM m
"""
