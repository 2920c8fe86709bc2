"""URL filters on DataFrame functions alone: host rules, and a blocked Bloom filter before an exact hash join.

The filter has blocks of eight 64-bit words; a key sets one bit in every word of one block. Possible
hits go on to a join on the canonical URL itself, which removes false positives, so the outcome does not
depend on the filter's size.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower

WORDS = 8
BITS_PER_KEY = 16
MAX_BROADCAST_BLOCKS = 1 << 17  # 8 MB of filter words


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased; empty where there is none."""
    return F.coalesce(ascii_lower(F.regexp_extract(url, r"^(?s:.*?)://([^/?#]*)", 1)), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^(?s:.*?)://[^/?#]*([^?#]*)", 1), F.lit(""))


def canonical(host: Column, path: Column) -> Column:
    """Host without a www. or m. label, path without .html and closing slashes; queries and fragments are left out."""
    return F.concat(F.regexp_replace(host, r"^(www|m)\.", ""), F.regexp_replace(path, r"(\.html)?/*\z", ""))


def rule_for(host: Column, path: Column, rules: Sequence[tuple[str, str, str]]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest fitting (verdict, host, path) rule; null where none fits."""
    rule = verdict = F.lit(None).cast("string")
    for said, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r[1], r[2])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(said)).otherwise(verdict)
    return rule, verdict


def _bit(key: Column, word: int) -> Column:
    h = F.xxhash64(key, F.lit(word // 4))
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, 6 * (word % 4)).bitwiseAND(F.lit(63)).cast("int"))


def bloom_blocks(keys: DataFrame, key: str, n_keys: int) -> tuple[DataFrame, int]:
    """(block, w0..w7) rows of the filter, and its number of blocks, a power of two for BITS_PER_KEY bits a key."""
    n_blocks = 1
    while n_blocks * WORDS * 64 < n_keys * BITS_PER_KEY:
        n_blocks *= 2
    block = F.pmod(F.xxhash64(F.col(key), F.lit("block")), F.lit(n_blocks)).alias("block")
    return keys.groupBy(block).agg(*[F.bit_or(_bit(F.col(key), w)).alias(f"w{w}") for w in range(WORDS)]), n_blocks


def listed(rows: DataFrame, key: str, urls: DataFrame) -> DataFrame:
    """rows plus `_listed`, whether key is among urls(key); repeated rows stay, null keys are never listed.

    The filter is broadcast while its blocks are few enough (checked), else both steps are shuffled
    joins. Only distinct possible hits meet the list, so a key that holds many rows is no hot spot there.
    """
    urls = urls.select(key).where(F.col(key).isNotNull()).distinct()
    blocks, n_blocks = bloom_blocks(urls, key, urls.count())
    if n_blocks <= MAX_BROADCAST_BLOCKS:
        blocks = F.broadcast(blocks)
    probed = rows.select(F.col(key).alias("_key")).distinct().withColumn("block", F.pmod(F.xxhash64("_key", F.lit("block")), F.lit(n_blocks)))
    hit = F.lit(True)
    for w in range(WORDS):
        hit = hit & (F.col(f"w{w}").bitwiseAND(_bit(F.col("_key"), w)) != 0)
    possible = probed.join(blocks, "block").where(hit).select("_key")
    exact = possible.join(urls.select(F.col(key).alias("_key")), "_key").withColumn("_listed", F.lit(True))
    return rows.join(exact, rows[key] == exact["_key"], "left").drop("_key").withColumn("_listed", F.coalesce("_listed", F.lit(False)))


def judge(pages: DataFrame, urls: DataFrame, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """page_id, host, path, rule, verdict: the longest fitting rule's, else block where the canonical URL is listed.

    pages has page_id and url; other columns are ignored; urls has url. Null urls and those without
    :// have empty host and path, fit no rule and are allowed. Repeated rows are all judged.
    """
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    named = lambda df: df.withColumn("canon", F.when(F.col("host") != "", canonical(F.col("host"), F.col("path"))))
    rows = named(pages.select("page_id", host.alias("host"), path.alias("path")))
    rule, said = rule_for(F.col("host"), F.col("path"), rules)
    checked = listed(rows, "canon", named(urls.select(host.alias("host"), path.alias("path"))))
    return checked.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(said, F.when(F.col("_listed"), "block").otherwise("allow")).alias("verdict"))


RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))
FEED = "utm_source=feed"


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages against the five rules; the list is the canonical URL of every page that was reached through a feed."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge(pages, pages.where(F.contains("url", F.lit(FEED))).select("url"), RULES)


ORACLE = r"""
WITH p AS (
  SELECT page_id, coalesce(contains(url, 'utm_source=feed'), false) AS feed,
    translate(coalesce(regexp_extract(url, '^(?s:.*?)://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    coalesce(regexp_extract(url, '^(?s:.*?)://[^/?#]*([^?#]*)', 1), '') AS path
  FROM pages
), c AS (
  SELECT *, CASE WHEN host <> '' THEN regexp_replace(host, '^(www|m)\.', '') || regexp_replace(path, '(\.html)?/*\z', '') END AS canon FROM p
), j AS (
  SELECT *, CASE
    WHEN (host = 'example.com' OR host LIKE '%.example.com') AND starts_with(path, '/en/7') THEN 'example.com/en/7'
    WHEN (host = 'example.net' OR host LIKE '%.example.net') AND starts_with(path, '/de/8') THEN 'example.net/de/8'
    WHEN (host = 'com' OR host LIKE '%.com') AND starts_with(path, '/en/') THEN 'com/en/'
    WHEN (host = 'net' OR host LIKE '%.net') AND starts_with(path, '/de/') THEN 'net/de/'
    WHEN (host = 'org' OR host LIKE '%.org') AND starts_with(path, '/es/') THEN 'org/es/'
  END AS rule, canon IN (SELECT canon FROM c WHERE feed AND canon IS NOT NULL) AS is_listed
  FROM c
)
SELECT page_id, host, path, rule,
  CASE WHEN rule IN ('example.com/en/7', 'net/de/') THEN 'allow' WHEN rule IS NOT NULL THEN 'block'
       WHEN coalesce(is_listed, false) THEN 'block' ELSE 'allow' END AS verdict
FROM j
"""
