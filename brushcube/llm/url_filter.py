"""URL filters: host-suffix / path-prefix expressions met with a rule list on short hash prefixes.

Every URL is expanded into the expressions a rule could be written as (each host suffix on label
boundaries x each path prefix), the expressions equi-join the rules on the first 32 bits of their
SHA-256, the full digests confirm, and the longest fitting rule decides. DataFrame functions only.

Defined results: a null URL or one without ``://`` has an empty host and path, no rule and the default
verdict; repeated rows are judged alike; other columns of the input are not read. Rules of equal length:
the one with the longer host wins, then ``block``. Only as many labels and as long prefixes are expanded
as some rule has, so the work per URL is bounded by the rules and not by the URL's length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: (verdict, host, path) of the contract.
RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))
#: Rules are broadcast up to this many rows; beyond, Spark joins by shuffling both sides.
BROADCAST_RULES = 200_000
_URL = r"(?s)\A.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, _URL, 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _URL, 2), F.lit(""))


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    """(verdict, host, path) triples as a table."""
    rows = F.array(*[F.struct(F.lit(v).alias("verdict"), F.lit(h).alias("rule_host"), F.lit(p).alias("rule_path")) for v, h, p in rules])
    return spark.range(1).select(F.inline(rows))


def _expressions(host: Column, path: Column, labels: list[int], lengths: list[int]) -> Column:
    parts = F.split(host, r"\.", -1)
    n = F.size(parts)
    suffixes = F.filter(F.array(*[F.when(n >= k, F.array_join(F.slice(parts, -k, k), ".")) for k in labels]), lambda s: s.isNotNull())
    prefixes = F.filter(F.array(*[F.when(F.char_length(path) >= k, F.substring(path, 1, k)) for k in lengths]), lambda s: s.isNotNull())
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, F.lit("\n"), p))))


def judge_urls(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """``pages`` with host, path, rule and verdict. ``rules``: verdict, rule_host, rule_path."""
    shapes = rules.select(F.size(F.split("rule_host", r"\.", -1)).alias("labels"), F.char_length("rule_path").alias("length"))
    shapes = shapes.agg(F.sort_array(F.collect_set("labels")).alias("labels"), F.sort_array(F.collect_set("length")).alias("lengths"), F.count("*").alias("n")).first()
    judged = pages.withColumns({"host": host_of(F.col(url)), "path": path_of(F.col(url))})
    if not shapes["n"]:
        return judged.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})

    keyed = rules.withColumn("rule_digest", F.sha2(F.concat("rule_host", F.lit("\n"), "rule_path"), 256))
    keyed = keyed.withColumn("rule_prefix", F.substring("rule_digest", 1, 8))
    if shapes["n"] <= BROADCAST_RULES:
        keyed = F.broadcast(keyed)
    # The verdict hangs on the URL alone, so each distinct URL is expanded once.
    urls = pages.where(F.col(url).isNotNull()).select(F.col(url).alias("judged_url")).distinct()
    spread = urls.select("judged_url", F.explode(_expressions(host_of(F.col("judged_url")), path_of(F.col("judged_url")), shapes["labels"], shapes["lengths"])).alias("expression"))
    spread = spread.withColumn("digest", F.sha2("expression", 256)).withColumn("prefix", F.substring("digest", 1, 8))
    hits = spread.join(keyed, (F.col("prefix") == F.col("rule_prefix")) & (F.col("digest") == F.col("rule_digest")))
    size = F.char_length("rule_host") + F.char_length("rule_path")
    best = hits.groupBy("judged_url").agg(F.max(F.struct(size.alias("size"), F.char_length("rule_host").alias("host_size"), (F.col("verdict") == "block").alias("blocks"), F.concat("rule_host", "rule_path").alias("rule"), F.col("verdict").alias("verdict"))).alias("best"))
    out = judged.join(best, F.col(url) == F.col("judged_url"), "left")
    return out.select(*[F.col(c) for c in judged.columns], F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return judge_urls(pages, rule_table(spark)).select("page_id", "host", "path", "rule", "verdict")


_HOST = "coalesce(translate(regexp_extract(url, '^(?s:.*?)://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '')"
_PATH = "coalesce(regexp_extract(url, '^(?s:.*?)://([^/?#]*)([^?#]*)', 2), '')"
ORACLE_SQL = f"""
WITH rules(verdict, rh, rp) AS (VALUES {', '.join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES)}),
p AS (SELECT page_id, {_HOST} AS host, {_PATH} AS path, row_number() OVER () AS rn FROM pages),
m AS (SELECT p.rn, rules.verdict, rh || rp AS rule,
             row_number() OVER (PARTITION BY p.rn ORDER BY length(rh || rp) DESC, length(rh) DESC, rules.verdict DESC) AS k
      FROM p JOIN rules ON (p.host = rh OR ends_with(p.host, '.' || rh)) AND starts_with(p.path, rp))
SELECT page_id, host, path, m.rule AS rule, coalesce(m.verdict, 'allow') AS verdict
FROM p LEFT JOIN m ON p.rn = m.rn AND m.k = 1
"""
