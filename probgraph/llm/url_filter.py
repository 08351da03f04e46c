"""Operator 3: URL filter. A blocked Bloom filter of the listed canonical URLs, then an exact join of its hits.

A list entry covers the pages with that canonical URL; an entry for the root of a site covers the site's pages. The filter's
256-bit blocks are built by one aggregation (a bitwise or per block) and probed by a join on the block number, all in
generated code. Where the filter is larger than ``max_filter_rows`` blocks it isn't broadcast: the pages' keys then
go straight to the exact join, which is right on its own.

Canonical: lower-case host without user, port and leading www., m. or blog.; no scheme, query, fragment, default page ending or final slash.
A null URL, or one without a host, is never listed. Repeated rows stay."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from probgraph.runtime import cut, fresh, small

#: Sites on the list that the query uses; pages whose text has one of the words are listed by their URL.
SITES = ("spam-farm.example.org", "cheap-pills.example.com", "casino-win.example.org", "ads-track.example.org", "free-bets.example.com")
REPORTED = r"\b(idiot|moron|worthless|pathetic)\b"
KEYS_PER_BLOCK = 16  # 16 bits a key
WORDS = 4


def host(url: Column) -> Column:
    bare = F.regexp_replace(F.trim(url), r"^[A-Za-z][A-Za-z0-9+.-]*://", "")
    name = F.lower(F.regexp_extract(bare, r"^(?:[^/?#@]*@)?([^/?#:@]*)", 1))
    return F.regexp_replace(name, r"^(?:(?:www|m|blog)\.)+", "")


def canonical(url: Column) -> Column:
    """Host and path; null where there is no host."""
    bare = F.regexp_replace(F.trim(url), r"^[A-Za-z][A-Za-z0-9+.-]*://", "")
    path = F.regexp_extract(bare, r"^[^/?#]*([^?#]*)", 1)
    path = F.regexp_replace(path, r"(?:(?:/index)?\.html?|/+)$", "")
    h = host(url)
    return F.when(h != "", F.concat(h, path))


def _place(key: Column, blocks: int) -> tuple[Column, list[Column]]:
    """Block of a key and its bits in each word of the block: two bits a word, of one 64-bit hash."""
    a, b = F.xxhash64(key), F.xxhash64(key, F.lit(1))
    bits = []
    for i in range(WORDS):
        one = F.lit(1).cast("long")
        bits.append(F.call_function("shiftleft", one, F.shiftrightunsigned(b, 12 * i).bitwiseAND(F.lit(63)).cast("int")).bitwiseOR(F.call_function("shiftleft", one, F.shiftrightunsigned(b, 12 * i + 6).bitwiseAND(F.lit(63)).cast("int"))))
    return F.pmod(a, F.lit(blocks)), bits


def bloom(listed: DataFrame, blocks: int) -> DataFrame:
    """(block, w0..w3) of the column ``key``."""
    block, bits = _place(F.col("key"), blocks)
    return listed.select(block.alias("block"), *[b.alias(f"w{i}") for i, b in enumerate(bits)]).groupBy("block").agg(*[F.bit_or(f"w{i}").alias(f"w{i}") for i in range(WORDS)])


def url_filter(pages: DataFrame, listed: DataFrame, max_filter_rows: int = 2_000_000) -> DataFrame:
    """Columns of ``pages`` and ``canonical_url``, ``listed`` (true where the list covers the page). listed: column ``url``."""
    pages = pages.drop("canonical_url", "listed")
    keys = cut(listed.select(canonical(F.col("url")).alias("key")).filter("key is not null").distinct())
    blocks = max(1, -(-keys.count() // KEYS_PER_BLOCK))
    asked = pages.select(canonical(F.col("url")).alias("canonical_url"), host(F.col("url")).alias("site")).filter("canonical_url is not null")
    asked = asked.select("canonical_url", F.explode(F.array_distinct(F.array("canonical_url", "site"))).alias("key"))
    if blocks <= max_filter_rows:
        block, bits = _place(F.col("key"), blocks)
        probe = asked.select("canonical_url", "key", block.alias("block"), *[b.alias(f"b{i}") for i, b in enumerate(bits)])
        table = F.broadcast(bloom(keys, blocks))
        test = [(F.col(f"w{i}").bitwiseAND(F.col(f"b{i}"))) == F.col(f"b{i}") for i in range(WORDS)]
        for t in test:
            probe_test = t if t is test[0] else probe_test & t
        asked = probe.join(table, "block").filter(probe_test).select("canonical_url", "key")
    hits = cut(asked.join(keys, "key", "left_semi").select(F.col("canonical_url").alias("hit")).distinct())
    hit = fresh(pages, "hit")
    found = small(hits.withColumnRenamed("hit", hit))
    out = pages.withColumn("canonical_url", canonical(F.col("url")))
    return out.join(found, out.canonical_url == found[hit], "left").withColumn("listed", F.col(hit).isNotNull()).drop(hit)


def reported(pages: DataFrame, sites: tuple[str, ...] = SITES, words: str = REPORTED) -> DataFrame:
    """The list of the query: site roots, and the URLs of pages that hold one of the words."""
    roots = pages.sparkSession.createDataFrame([(f"http://{s}/",) for s in sites], "url string")
    return pages.filter(F.lower("html").rlike(words)).select("url").unionByName(roots)


_HOST = r"regexp_replace(lower(regexp_extract(regexp_replace(trim(url), '^[A-Za-z][A-Za-z0-9+.-]*://', ''), '^(?:[^/?#@]*@)?([^/?#:@]*)', 1)), '^(?:(?:www|m|blog)\.)+', '')"
_PATH = r"regexp_replace(regexp_extract(regexp_replace(trim(url), '^[A-Za-z][A-Za-z0-9+.-]*://', ''), '^[^/?#]*([^?#]*)', 1), '(?:(?:/index)?\.html?|/+)$', '')"
ORACLE = f"""
with p as (select page_id, url, html, {_HOST} as site, case when {_HOST} <> '' then {_HOST} || {_PATH} end as canonical_url from pages),
l as (select canonical_url as key from p where regexp_matches(lower(html), '{REPORTED}') and canonical_url is not null
      union select unnest([{", ".join(repr(s) for s in SITES)}]))
select page_id, url, canonical_url, coalesce(canonical_url in (select key from l) or (canonical_url is not null and site in (select key from l)), false) as listed from p
"""
