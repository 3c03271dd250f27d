"""URL filter: ordered rules, then a list of canonical URLs behind a blocked Bloom filter.

The filter has blocks of eight 32-bit words; a URL sets one bit in each word of one
block. The number of blocks follows the list up to ``max_blocks``, so what is
broadcast is bounded (36 bytes a block), and a fuller filter only passes more URLs on
to the exact hash join, which removes every false positive. URLs that the filter
rejects never meet the list. All of it is built-in expressions.

Defined results: a null URL or one without ``://`` has empty host and path and is
allowed unless the list holds the empty URL's canonical form; repeated rows are each
judged; list entries may repeat; extra columns are kept; empty tables are fine.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import need

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WORDS = 8


def parts(url: Column) -> Column:
    """struct (host, path)."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER)
    return F.struct(F.coalesce(host, F.lit("")).alias("host"), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit("")).alias("path"))


def canonical(host: Column, path: Column) -> Column:
    """One form for a page's addresses: no scheme, ``www.``, index page, suffix slash, query or fragment."""
    return F.concat(F.regexp_replace(host, r"^www\.", ""), F.regexp_replace(F.regexp_replace(path, r"/index\.html?$", "/"), r"/+$", ""))


def first_rule(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> Column:
    """struct (rule, verdict) of the longest rule that fits, or null. ``rules``: (host, path, verdict)."""
    out = F.lit(None).cast("struct<rule: string, verdict: string>")
    for h, p, verdict in sorted(rules, key=lambda r: (len(r[0]) + len(r[1]), r[0], r[1])):
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def _bits(url: Column, blocks: int) -> tuple[Column, list[Column]]:
    """A URL's block, and its bit in each word of it."""
    spread = F.xxhash64(F.lit("bits"), url)
    return F.pmod(F.xxhash64(url), F.lit(blocks)), [F.call_function("shiftleft", F.lit(1), F.shiftrightunsigned(spread, 5 * k).bitwiseAND(31).cast("int")) for k in range(WORDS)]


def bloom(listed: DataFrame, blocks: int) -> DataFrame:
    """(block, w0 .. w7) of the URLs in column ``url``."""
    block, bits = _bits(F.col("url"), blocks)
    rows = listed.select(block.alias("block"), *[b.alias(f"w{k}") for k, b in enumerate(bits)])
    return rows.groupBy("block").agg(*[F.bit_or(f"w{k}").alias(f"w{k}") for k in range(WORDS)])


def judge(pages: DataFrame, listed: DataFrame, rules: list[tuple[str, str, str]], bits_each: int = 16, max_blocks: int = 1 << 15) -> DataFrame:
    """The columns of ``pages`` and host, path, rule, verdict, listed.

    ``listed``: canonical URLs in column ``url``. A rule's verdict holds; without one,
    a listed page is blocked and any other allowed. Columns of those names are replaced.
    """
    need(pages, "url")
    need(listed, "url")
    listed = listed.select(F.col("url").cast("string").alias("_listed")).where("_listed is not null").distinct()
    count = listed.count()
    blocks = max(1, min(max_blocks, -(-count * bits_each // (32 * WORDS))))
    # A row's own columns travel in one struct, so that no name of theirs can clash.
    own = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict", "listed")]
    rows = pages.select(F.struct(*[F.col(f"`{c}`") for c in own]).alias("row"), parts(F.col("url").cast("string")).alias("at"))
    rows = rows.withColumn("key", canonical(F.col("at.host"), F.col("at.path")))
    block, bits = _bits(F.col("key"), blocks)
    held = bloom(listed.withColumnRenamed("_listed", "url"), blocks)
    tested = rows.withColumn("block", block).join(F.broadcast(held), "block", "left")
    hit = F.lit(True)
    for k, b in enumerate(bits):
        hit = hit & (F.col(f"w{k}").bitwiseAND(b) != 0)
    tested = tested.select("row", "at", "key", F.coalesce(hit, F.lit(False)).alias("maybe"))
    maybe = tested.where("maybe").join(listed.withColumn("sure", F.lit(True)), F.col("key") == F.col("_listed"), "left").drop("_listed")
    never = tested.where("not maybe").withColumn("sure", F.lit(None).cast("boolean"))
    rule = first_rule(F.col("at.host"), F.col("at.path"), rules)
    out = maybe.unionByName(never).withColumns({"listed": F.coalesce("sure", F.lit(False)), "rule": rule})
    verdict = F.coalesce(F.col("rule.verdict"), F.when(F.col("listed"), F.lit("block")).otherwise(F.lit("allow")))
    return out.select("row.*", F.col("at.host").alias("host"), F.col("at.path").alias("path"), F.col("rule.rule").alias("rule"), verdict.alias("verdict"), "listed")
