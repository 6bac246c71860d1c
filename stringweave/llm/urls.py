"""URL filter: rules by host and path, then a blocked Bloom filter and an exact join.

The listed canonical URLs are set into a Bloom filter whose blocks are single 64-bit
words: one hash picks the block, four more the bits.  The filter is a table of
(block, bits), so it grows as large as the list needs; probing is an equi-join on
the block, which is broadcast only when the sizes at run time allow.  URLs whose bits
are not all set can't be listed.  Possible hits then meet the list itself in a hash
join on the canonical URL, which removes false positives.  All of it is built from
DataFrame functions.

A null URL, or one without ``://``, has an empty host and path, meets no rule and is
allowed.  Repeated rows keep their number.  An empty list allows everything.  Of rules of
one length that fit, the one first in RULES counts; two different ones of one length can't
fit one URL here.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Host, path prefix and verdict of each rule.
RULES = (
    ("net", "/", "block"),
    ("example.net", "/en/", "allow"),
    ("example.com", "/de/", "block"),
    ("org", "/fr/", "allow"),
)
PROBES = 4
BITS_PER_URL = 16


def host_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path, both empty without a scheme."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return host, F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column) -> tuple[Column, Column]:
    """The longest rule that fits, as text, and its verdict; both null if none fits."""
    ordered = sorted(RULES, key=lambda r: -len(r[0] + r[1]))
    fits = [((host == h) | host.endswith("." + h)) & path.startswith(p) for h, p, _ in ordered]
    name = verdict = F.lit(None).cast("string")
    for (h, p, v), ok in reversed(list(zip(ordered, fits))):
        name, verdict = F.when(ok, h + p).otherwise(name), F.when(ok, v).otherwise(verdict)
    return name, verdict


def canonical(host: Column, path: Column) -> Column:
    """Host without www. or m., and the path without .html or a slash at its end."""
    return F.concat(F.regexp_replace(host, r"^(www|m)\.", ""), F.regexp_replace(path, r"(\.html|/)+$", ""))


def _block(url: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(url), F.lit(blocks))


def _mask(url: Column) -> Column:
    """PROBES bits of a block's word, from a second hash."""
    h, out = F.xxhash64(url, F.lit(1)), F.lit(0).cast("long")
    for i in range(PROBES):
        out = out.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftright(h, 6 * i).bitwiseAND(F.lit(63)).cast("int")))
    return out


def bloom(listed: DataFrame, blocks: int) -> DataFrame:
    """The filter of ``listed.url``: ``(block, bits)`` of the blocks with any bit set."""
    return listed.groupBy(_block(F.col("url"), blocks).alias("block")).agg(F.bit_or(_mask(F.col("url"))).alias("bits"))


def judge(pages: DataFrame, listed: DataFrame, url: str = "url") -> DataFrame:
    """Append host, path, rule, canonical, possible_hit and verdict to every row of ``pages``.

    ``listed`` has one column ``url`` of canonical URLs to block; repeats and nulls are allowed.
    """
    new = ("host", "path", "rule", "canonical", "possible_hit", "verdict")
    rows = pages.select(*[F.col(f"`{c}`") for c in pages.columns if c.lower() not in new or c == url])
    carried = rows.columns
    host, path = host_path(F.col(f"`{url}`"))
    rows = rows.withColumn("__host", host).withColumn("__path", path)
    rule, verdict = rule_of(F.col("__host"), F.col("__path"))
    rows = rows.withColumn("__rule", rule).withColumn("__verdict", verdict).withColumn("__url", canonical(F.col("__host"), F.col("__path")))
    unique = listed.select("url").where("url is not null").distinct()
    n = unique.count()
    blocks = 1 << max(4, (n * BITS_PER_URL // 64).bit_length())
    words = bloom(unique, blocks).select(F.col("block").alias("__block"), "bits")
    mask = _mask(F.col("__url"))
    probed = rows.withColumn("__block", _block(F.col("__url"), blocks)).join(words, "__block", "left")
    hit = F.coalesce(F.col("bits").bitwiseAND(mask) == mask, F.lit(False))
    # rows that are no possible hit get keys of their own that equal no URL, so that they spread evenly
    key = F.when(F.col("__hit"), F.col("__url")).otherwise(F.concat(F.lit(" "), F.xxhash64("__url", F.lit(2)).cast("string")))
    exact = unique.select(F.col("url").alias("__key"), F.lit(True).alias("__listed"))
    judged = probed.withColumn("__hit", hit).withColumn("__key", key).join(exact, "__key", "left")
    return judged.select(
        *[F.col(f"`{c}`") for c in carried if c.lower() not in new or c == url],
        F.col("__host").alias("host"), F.col("__path").alias("path"), F.col("__rule").alias("rule"), F.col("__url").alias("canonical"), F.col("__hit").alias("possible_hit"),
        F.coalesce("__verdict", F.when(F.col("__listed"), "block").otherwise("allow")).alias("verdict"),
    )
