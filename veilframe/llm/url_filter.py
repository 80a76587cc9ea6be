"""URL filters: host and path rules, then a list of URLs behind a blocked Bloom filter.

The filter is a table of 512-bit blocks, eight words of 64 bits each; a listed canonical URL sets one bit in
every word of one block. Pages whose bits are all set are possible hits and go to an exact hash join with
the list, which removes the false positives; all other pages never meet the list. The filter is broadcast
only if its size, known from the count of the list, is within `broadcast_bytes`; beyond, it is joined by block.

A url that is null or has no `://` has an empty host and path, meets no rule and is never listed. Repeated
rows and page ids stay as they are; an empty page table or list is fine.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WORDS, BLOCK_BYTES = 8, 64


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path


RULES = (Rule("net", "/", "block"), Rule("example.net", "/en/", "allow"), Rule("example.com", "/de/", "block"), Rule("org", "/fr/", "allow"))


def _after_scheme(url: Column) -> Column:
    """What follows the first `://`, or an empty string."""
    at = F.instr(url, "://")
    return F.when(url.isNull() | (at == 0), F.lit("")).otherwise(F.substring(url, at + 3, F.length(url)))


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(_after_scheme(url), r"^[^/?#]*", 0), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def canonical_of(url: Column) -> Column:
    """Host, path without closing slashes, and the sorted query without tracking fields; null if there is no host."""
    query = F.regexp_extract(_after_scheme(url), r"^[^?#]*\?([^#]*)", 1)
    fields = F.array_sort(F.filter(F.split(query, "&"), lambda x: (x != "") & ~x.startswith("utm_")))
    host = host_of(url)
    tail = F.when(F.size(fields) > 0, F.concat(F.lit("?"), F.array_join(fields, "&"))).otherwise(F.lit(""))
    return F.when(host != "", F.concat(host, F.regexp_replace(path_of(url), "/+$", ""), tail))


def rule_of(host: Column, path: Column, rules: tuple[Rule, ...] = RULES, what: str = "name") -> Column:
    """The longest rule that fits, else null. Rules are a driver-side list of at most some hundreds."""
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r.name), r.name)):
        fits = ((host == rule.host) | host.endswith("." + rule.host)) & path.startswith(rule.path)
        out = F.when(fits, F.lit(getattr(rule, what))).otherwise(out)
    return out


def _block(key: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(blocks))


def _bits(key: Column) -> list[Column]:
    """One bit for each word, from six bits each of a second hash."""
    second = F.xxhash64(key, F.lit("bits"))
    return [F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(second, 6 * i).bitwiseAND(F.lit(63)).cast("int")) for i in range(WORDS)]


def bloom_filter(listed: DataFrame, key: str, bits_per_key: int = 16) -> tuple[DataFrame, int]:
    """The filter as rows (block, w0 to w7) and its number of blocks. `listed` has distinct keys."""
    blocks = max(1, -(-listed.count() * bits_per_key // (BLOCK_BYTES * 8)))
    words = [bit.alias(f"w{i}") for i, bit in enumerate(_bits(F.col(key)))]
    rows = listed.where(F.col(key).isNotNull()).select(_block(F.col(key), blocks).alias("block"), *words)
    return rows.groupBy("block").agg(*(F.bit_or(f"w{i}").alias(f"w{i}") for i in range(WORDS))), blocks


def url_verdicts(pages: DataFrame, listed: DataFrame, rules: tuple[Rule, ...] = RULES, broadcast_bytes: int = 64 << 20) -> DataFrame:
    """page_id, host, path, rule, verdict, canonical, maybe_listed. `listed` has a column url."""
    keys = listed.select(canonical_of(F.col("url")).alias("__listed")).where("__listed is not null").distinct()
    words, blocks = bloom_filter(keys, "__listed")
    words = words.withColumnRenamed("block", "__block")
    if blocks * (BLOCK_BYTES + 8) <= broadcast_bytes:
        words = F.broadcast(words)
    url = F.col("url").cast("string")
    judged = pages.select("page_id", host_of(url).alias("host"), path_of(url).alias("path"), canonical_of(url).alias("canonical"))
    judged = judged.withColumns({"rule": rule_of(F.col("host"), F.col("path"), rules), "__verdict": rule_of(F.col("host"), F.col("path"), rules, "verdict"), "__block": _block(F.coalesce("canonical", F.lit("")), blocks)})
    all_set = F.lit(True)
    for i, bit in enumerate(_bits(F.col("canonical"))):
        all_set = all_set & (F.col(f"w{i}").bitwiseAND(bit) != 0)
    probed = judged.join(words, "__block", "left").withColumn("maybe_listed", F.coalesce(all_set & F.col("canonical").isNotNull(), F.lit(False)))
    probed = probed.select("page_id", "host", "path", "rule", "__verdict", "canonical", "maybe_listed")
    sure = probed.where(~F.col("maybe_listed")).withColumn("__hit", F.lit(False))
    asked = probed.where("maybe_listed").join(keys.withColumn("__hit", F.lit(True)), F.col("canonical") == F.col("__listed"), "left").drop("__listed")
    both = sure.unionByName(asked)
    verdict = F.coalesce("__verdict", F.when(F.coalesce("__hit", F.lit(False)), F.lit("block")).otherwise(F.lit("allow")))
    return both.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "canonical", "maybe_listed")


def op6_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lists the canonical URLs of the table whose MD5 begins with 3, then judges every page."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    listed = pages.where(F.substring(F.md5(canonical_of(F.col("url"))), 1, 1) == "3").select("url")
    return url_verdicts(pages, listed).drop("maybe_listed")


ORACLE_URL = """
WITH cut AS (
  SELECT page_id, CASE WHEN url IS NULL OR strpos(url, '://') = 0 THEN '' ELSE substr(url, strpos(url, '://') + 3) END AS rest FROM pages
), parts AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path,
         list_sort(list_filter(string_split(regexp_extract(rest, '^[^?#]*[?]([^#]*)', 1), '&'), lambda x: x <> '' AND NOT starts_with(x, 'utm_'))) AS fields
  FROM cut
), named AS (
  SELECT page_id, host, path, CASE WHEN host <> '' THEN host || regexp_replace(path, '/+$', '') || CASE WHEN len(fields) > 0 THEN '?' || array_to_string(fields, '&') ELSE '' END END AS canonical FROM parts
), rules(rhost, rpath, said) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
judged AS (
  SELECT n.*, (SELECT max_by(rhost || rpath, length(rhost || rpath)) FROM rules WHERE (n.host = rhost OR ends_with(n.host, '.' || rhost)) AND starts_with(n.path, rpath)) AS rule FROM named n
), listed AS (SELECT DISTINCT canonical AS c FROM named WHERE substr(md5(canonical), 1, 1) = '3')
SELECT page_id, host, path, rule, coalesce((SELECT said FROM rules WHERE rhost || rpath = rule), CASE WHEN canonical IN (SELECT c FROM listed) THEN 'block' ELSE 'allow' END) AS verdict, canonical
FROM judged
"""

QUERIES = {"op6_url_filters": op6_url_filters}
ORACLES = {"op6_url_filters": ORACLE_URL}
