"""URL verdicts: host and path rules, and a list of canonical URLs behind a blocked Bloom filter.

The filter's blocks are eight 32-bit words; a URL sets one bit in each word of its block. Blocks are built by grouped bit-or
and probed by an equi-join with the block's number, which Spark broadcasts only below its own size threshold. What
passes may be listed; an exact hash join with the listed URLs then removes the false positives."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import staged

#: Listed URLs for each block of 256 bits.
PER_BLOCK = 16


def host(url: Column) -> Column:
    """After the first :// up to /, ?, # or the end, A-Z in lower case; empty without ://."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    name = F.regexp_extract(rest, r"(?s)\A[^/?#]*", 0)
    return F.coalesce(F.translate(name, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path(url: Column) -> Column:
    """After the host up to ? or # or the end; empty without ://."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    return F.coalesce(F.regexp_extract(rest, r"(?s)\A[^/?#]*([^?#]*)", 1), F.lit(""))


def canonical(url: Column) -> Column:
    """host and path without a leading www. or m., a trailing slash, .html; scheme, query and fragment do not count."""
    name = F.regexp_replace(host(url), r"\A(www|m)\.", "")
    return F.concat(name, F.regexp_replace(path(url), r"(\.html)?/*\z", ""))


def ruled(pages: DataFrame, rules: list[tuple[str, str, str]], url: str = "url") -> DataFrame:
    """pages with host, path, rule, ruling: the longest of the rules (host, path, verdict) that fits, or nulls.

    A rule fits its host and the hosts below it if the path starts with the rule's path."""
    out = pages.withColumn("host", host(F.col(url))).withColumn("path", path(F.col(url)))
    rule, ruling = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, verdict in sorted(rules, key=lambda r: (len(r[0] + r[1]), r[0] + r[1])):
        fits = ((F.col("host") == h) | F.col("host").endswith("." + h)) & F.col("path").startswith(p)
        rule, ruling = F.when(fits, h + p).otherwise(rule), F.when(fits, verdict).otherwise(ruling)
    return out.withColumn("rule", rule).withColumn("ruling", ruling)


def _bits(of: Column, blocks: int) -> tuple[Column, list[Column]]:
    h = F.xxhash64(of)
    g = F.xxhash64(of, F.lit(17))
    return F.pmod(h, F.lit(blocks)), [F.call_function("shiftleft", F.lit(1), F.shiftrightunsigned(g, 5 * i).bitwiseAND(31).cast("int")) for i in range(8)]


def bloom(listed: DataFrame, column: str = "canon", per_block: int = PER_BLOCK) -> tuple[DataFrame, int]:
    """(block, w0..w7) of a column of listed strings, and the number of blocks."""
    rows = listed.count()
    blocks = max(1, -(-rows // per_block))
    block, bits = _bits(F.col(column), blocks)
    spread = listed.select(block.alias("block"), *(b.alias(f"w{i}") for i, b in enumerate(bits)))
    return spread.groupBy("block").agg(*(F.bit_or(f"w{i}").alias(f"w{i}") for i in range(8))), blocks


def members(rows: DataFrame, listed: DataFrame, column: str = "canon") -> DataFrame:
    """The distinct values of column in rows that listed holds, by way of the filter."""
    table = staged(listed.select(column).filter(F.col(column).isNotNull()).distinct(), "listed")
    words, blocks = bloom(table, column)
    block, bits = _bits(F.col(column), blocks)
    asked = rows.select(column).filter(F.col(column).isNotNull()).distinct().withColumn("block", block)
    passed = asked.join(words, "block")
    for i, bit in enumerate(bits):
        passed = passed.filter(F.col(f"w{i}").bitwiseAND(bit) != 0)
    return passed.select(column).join(table, column, "left_semi")


def judge(pages: DataFrame, rules: list[tuple[str, str, str]], listed: DataFrame, key: str = "page_id", url: str = "url") -> DataFrame:
    """(key, host, path, rule, verdict, listed) for every page: the rule's verdict, else block where the canonical URL is
    listed (canon) and allow where not. A null url has empty host and path and is listed only if '' is."""
    out = ruled(pages.select(key, url), rules, url).withColumn("canon", canonical(F.col(url)))
    hits = members(out.filter("rule is null"), listed).select(F.col("canon").alias("canon"), F.lit(True).alias("hit"))
    out = out.join(hits, "canon", "left").withColumn("listed", F.col("rule").isNull() & F.coalesce("hit", F.lit(False)))
    return out.select(key, "host", "path", "rule", F.coalesce("ruling", F.when(F.col("listed"), "block").otherwise("allow")).alias("verdict"), "listed")
