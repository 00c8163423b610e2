"""URL verdicts by a sort-merge sweep over nested host rules; DataFrame functions only.

A host is keyed by its reversed labels, each followed by a comma, so a rule's host and all
its subdomains are one interval of keys.  Interval starts and ends carry the stack of rules
that are active from there on; a sweep in key order hands every URL the stack that holds at
its key, and the longest rule whose path starts the URL's path decides.

The sweep is dealt by top-level domain and a salt; a domain's few breakpoints are copied to
each of its salts, so a host with a third of all rows spreads over all tasks.

Null URLs and URLs without ``://`` have an empty host and path and match no rule.  No rule:
``default``.  Of rules of one length the greater text wins, of one text with two verdicts
``block``.  Repeated rows stay.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

RULES = [
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
]
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    return F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), _UPPER, _LOWER), F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def host_key(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), ","), F.lit(","))


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Rules (host, path, verdict) as a DataFrame; a rule needs a host."""
    if any(not host for host, _, _ in rules):
        raise ValueError("a rule without a host is the default verdict")
    return spark.createDataFrame(rules, "rule_host string, rule_path string, rule_verdict string")


def breakpoints(rules: DataFrame) -> DataFrame:
    """(key, tld, stack): from ``key`` on, until the next key, the rules in ``stack`` are active.

    A point's stack holds the rules of its label prefixes, found by an equality join: no pair of rules is compared.
    """
    rules = rules.select(host_key(F.col("rule_host")).alias("rule_key"), F.concat("rule_host", "rule_path").alias("rule"), "rule_path", "rule_verdict")
    held = rules.groupBy("rule_key").agg(F.collect_set(F.struct(F.length("rule").alias("size"), "rule", F.col("rule_verdict").alias("verdict"), F.col("rule_path").alias("path"))).alias("own"))
    labels = lambda key: F.split(F.rtrim(key, F.lit(",")), ",")
    # Behind "com,example," comes "com,example-", where only the rules of "com," are left.
    points = held.select(F.explode(F.array(F.struct(F.col("rule_key").alias("key"), labels("rule_key").alias("labels")), F.struct(F.concat(F.expr("substring(rule_key, 1, length(rule_key) - 1)"), F.lit("-")).alias("key"), F.expr("slice(split(rtrim(',', rule_key), ','), 1, size(split(rtrim(',', rule_key), ',')) - 1)").alias("labels")))).alias("p")).select("p.*", F.element_at(F.split(F.col("p.key"), "[,-]"), 1).alias("tld"))
    prefixes = points.select("key", "tld", F.explode_outer(F.expr("transform(labels, (x, i) -> concat(array_join(slice(labels, 1, i + 1), ','), ','))")).alias("prefix"))
    stacks = prefixes.join(held, prefixes["prefix"] == held["rule_key"], "left").groupBy("key", "tld")
    return stacks.agg(F.flatten(F.collect_list("own")).alias("stack"))


def judge(urls: DataFrame, rules: DataFrame, default: str = "allow", salts: int | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of ``urls`` (page_id, url)."""
    spark = urls.sparkSession
    salts = salts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    host, path = host_and_path(F.col("url"))
    pages = urls.select("page_id", F.col("url").cast("string").alias("url")).select("page_id", host.alias("host"), path.alias("path"), F.pmod(F.xxhash64("page_id", "url"), F.lit(salts)).cast("int").alias("salt"))
    pages = pages.withColumn("key", host_key(F.col("host")))
    pages = pages.select("page_id", "host", "path", "salt", "key", F.element_at(F.split("key", ","), 1).alias("tld"), F.lit(None).cast("array<struct<size:int,rule:string,verdict:string,path:string>>").alias("stack"), F.lit(1).alias("kind"))
    points = breakpoints(rules).select(F.lit(None).cast(pages.schema["page_id"].dataType).alias("page_id"), F.lit(None).cast("string").alias("host"), F.lit(None).cast("string").alias("path"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), "key", "tld", "stack", F.lit(0).alias("kind"))
    sweep = Window.partitionBy("tld", "salt").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    swept = points.unionByName(pages).withColumn("active", F.last("stack", ignorenulls=True).over(sweep)).filter("kind = 1")
    best = swept.withColumn("best", F.expr("array_max(filter(active, r -> startswith(path, r.path)))"))
    return best.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


def op5_url_rules(spark, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet"), rule_table(spark, RULES))


ORACLE = """
WITH u AS (
  SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), p AS (
  SELECT page_id,
         translate(regexp_extract(coalesce(rest, ''), '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path
  FROM u
), r(h, q, v) AS (
  VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')
), m AS (
  SELECT page_id, host, path, h || q AS rule, v, row_number() OVER (PARTITION BY page_id, host, path ORDER BY length(h || q) DESC) AS k
  FROM p JOIN r ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, q)
)
SELECT p.page_id, p.host, p.path, m.rule, coalesce(m.v, 'allow') AS verdict
FROM p LEFT JOIN m ON m.page_id = p.page_id AND m.host = p.host AND m.path = p.path AND m.k = 1
"""
