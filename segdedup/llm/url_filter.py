"""URL filtering: a blocked Bloom filter of the listed canonical URLs, then an exact hash join.

A canonical key is host + path prefix. Every URL yields the keys that could be listed: its
host and each parent domain, each with the prefixes of its path that are as long as some
listed path. The Bloom filter, an array of longs in which a key touches one block of eight
words only, lets the possible hits through; the exact join with the list removes its false
positives, and the longest rule wins (most host labels, then the longest path). The URL
decides alone, so each distinct URL is judged once, however many pages carry it.

The filter's size is bounded by `max_words`, whatever the list's length; beyond that more
false positives reach the exact join and the result stays the same. A null URL, or one
without ://, has empty host and path and fits no rule; URLs without a rule get `default`.
Repeated rows stay, very long URLs are judged whole, an empty table gives an empty result. Extra
columns may have any name: judge() gives page_id, url and its own columns, and rows of `whole`
pages carry theirs in one struct.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch

BLOCK = 8
#: Longs in a Bloom filter at most: 256 KB.
MAX_WORDS = 1 << 15
#: Rules up to which the list is broadcast for the exact join.
BROADCAST_RULES = 100_000
SALT = 7_919

RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _probes(key: Column, blocks: int) -> tuple[Column, list[tuple[int, Column]]]:
    """A key's block, and for each of its words the bit that the key sets there."""
    h = F.xxhash64(key)
    g = F.xxhash64(key, F.lit(SALT))
    return F.pmod(h, F.lit(blocks)), [(i, F.shiftrightunsigned(g, 6 * i).bitwiseAND(F.lit(63))) for i in range(BLOCK)]


def build_bloom(keys: DataFrame, max_words: int = MAX_WORDS) -> list[int]:
    """The filter of the column `key`: about 16 bits a key, in whole blocks, at most max_words."""
    n = keys.count()
    blocks = 1
    while blocks * BLOCK * 64 < 16 * n and blocks * BLOCK < max_words:
        blocks *= 2
    block, bits = _probes(F.col("key"), blocks)
    one = F.lit(1).cast("long")
    word = keys.select(block.alias("block"), *[F.call_function("shiftleft", one, bit.cast("int")).alias(f"w{i}") for i, bit in bits])
    rows = word.groupBy("block").agg(*[F.bit_or(f"w{i}").alias(f"w{i}") for i in range(BLOCK)]).collect()  # at most max_words longs
    filled = [0] * (blocks * BLOCK)
    for row in rows:
        filled[row["block"] * BLOCK : (row["block"] + 1) * BLOCK] = [row[f"w{i}"] for i in range(BLOCK)]
    return filled


def maybe_listed(key: Column, bloom: list[int]) -> Column:
    block, bits = _probes(key, len(bloom) // BLOCK)
    words = F.lit(bloom).cast("array<bigint>")  # a full word is -1, which alone would make ints
    test = None
    for i, bit in bits:
        has = F.call_function("getbit", F.get(words, (block * BLOCK + i).cast("int")), bit.cast("int")) == 1
        test = has if test is None else test & has
    return test


def candidates(host: Column, path: Column, lengths: list[int]) -> Column:
    """Keys host-suffix + path-prefix that could be in the list."""
    labels = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    long_enough = F.filter(F.array(*[F.lit(n) for n in lengths]), lambda n: n <= F.length(path))
    prefixes = F.transform(long_enough, lambda n: F.substring(path, F.lit(1), n))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, p))))


def judge(pages: DataFrame, rules: DataFrame, default: str = "allow", max_words: int = MAX_WORDS, whole: bool = False) -> DataFrame:
    """page_id, url, host, path, rule and verdict of each page; rules: host, path (from /), verdict.

    whole: carry each page along, as the struct `row`.
    """
    carried = [F.struct(*[F.col(f"`{c}`") for c in pages.columns]).alias("row")] if whole else []
    pages = pages.select("page_id", "url", *carried)
    listed = (
        rules.select(F.concat(F.lower("host"), "path").alias("key"), F.length("host").alias("host_len"), F.length("path").alias("path_len"), F.col("verdict").alias("rule_verdict"))
        .groupBy("key")
        .agg(F.first("host_len").alias("host_len"), F.first("path_len").alias("path_len"), F.min("rule_verdict").alias("rule_verdict"))
    )
    lengths = [r[0] for r in listed.select("path_len").distinct().orderBy("path_len").collect()]  # no more than the longest path has characters
    if not lengths:
        return pages.withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url")), "rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    bloom = build_bloom(listed, max_words)
    listed = F.broadcast(listed) if listed.count() <= BROADCAST_RULES else listed
    hits = (
        pages.select(F.col("url").alias("hit_url"))
        .where(F.col("hit_url").isNotNull())
        .distinct()
        .select("hit_url", F.filter(candidates(host_of(F.col("hit_url")), path_of(F.col("hit_url")), lengths), lambda k: maybe_listed(k, bloom)).alias("keys"))
        .select("hit_url", F.explode("keys").alias("key"))
        .join(listed, "key")
        .groupBy("hit_url")
        .agg(F.max(F.struct("host_len", "path_len", "key", "rule_verdict")).alias("best"))
    )
    return (
        pages.join(hits, pages["url"] == hits["hit_url"], "left")
        .withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url")), "rule": F.col("best.key"), "verdict": F.coalesce("best.rule_verdict", F.lit(default))})
        .drop("hit_url", "best")
    )


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = scratch.spread(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"))
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    return judge(pages, rules).select("page_id", "host", "path", "rule", "verdict")


QUERIES = {"op5_url_filter": op5_url_filter}

ORACLE_SQL = {
    "op5_url_filter": r"""
with p as (
  select page_id,
         translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
         regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) as path
  from pages),
r(h, p, v) as (values ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
m as (
  select *,
         (select max({'a': length(r.h), 'b': length(r.p), 'c': r.h || r.p, 'd': r.v}) from r
          where (p.host = r.h or suffix(p.host, '.' || r.h)) and prefix(p.path, r.p)) as best
  from p)
select page_id, host, path, best.c as rule, coalesce(best.d, 'allow') as verdict from m
"""
}
