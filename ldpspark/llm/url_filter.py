"""URL filters: a blocked Bloom filter over listed canonical URLs passes possible hits to an exact hash join.

A listed URL is a host and a path prefix. It fits a URL whose host is that host or a subdomain of it and whose path
starts with that prefix; of several that fit, the longest (host and path together) of the highest tier wins, ties going
to the longer host, then to ``block``. A listed row is compared with the host as it is written or, where it says so, with
the canonical host: without user, port, a closing dot and a leading ``www.``. Every URL gives one key for each pair of a
number of host labels and a path length that the list has; a Bloom filter of 512-bit blocks (one block and eight bits for a
key) lets pass the few keys that may be listed, and a join on the key itself keeps only the listed ones. So the verdicts
don't depend on the filter. Keys are linear in the URL, times the pairs.

Defined results: null URLs and URLs without ``://`` have empty host and path and get the default verdict; repeated rows
are judged one by one; an empty list gives all the default verdict; listed rows without host or path are left out.

The filter has 16 bits a listed key; its blocks are made by an aggregation and only they come to the driver. It goes to all
tasks while it is below ``filter_bytes``; beyond, the keys are joined without it. The list itself is broadcast by Spark only
while below its threshold for that.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

FILTER_BYTES = 64 << 20
WORDS, BITS_A_KEY = 8, 16
#: Odd multipliers of the eight bits.
ODD = [0x47B6137B, 0x44974D91, 0x8824AD5B, 0xA2B7289D, 0x705495C7, 0x2DF1424B, 0x9EFC4947, 0x5C6BFB31]
#: Fixed by the contract of the query: host, path prefix, verdict.
RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]
#: Our own listed sites, which decide where no rule fits.
SITES = ["adult-x", "ads-track", "casino-win", "cheap-pills", "free-bets", "spam-farm"]
LISTED = [f"http://www.{site}.example.{top}/" for site in SITES for top in ("com", "net", "org")]


def host_path(url: str) -> tuple[Column, Column]:
    """Host and path of the contract, of the column named ``url``: cut at the first ``://``, then at ``/``, ``?``, ``#``."""
    rest = F.expr(f"CASE WHEN instr({url}, '://') > 0 THEN substring({url}, instr({url}, '://') + 3) END")
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), C.UPPER, C.LOWER)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def canonical_host(host: Column) -> Column:
    """``host`` without user, port, closing dots and a leading ``www.``."""
    bare = F.regexp_replace(F.regexp_replace(host, r"^.*@", ""), r"\.*(:[0-9]*)?$", "")
    return F.regexp_replace(bare, r"^www\.", "")


def listing(urls: DataFrame, url_col: str = "url", verdict: str = "block", tier: int = 0) -> DataFrame:
    """Rows for :func:`judge` from raw URLs: canonical host; the path without its last slash, as a prefix. Others are left out."""
    host, path = host_path("_url")
    rows = urls.select(F.col(url_col).alias("_url")).select(canonical_host(host).alias("host"), F.regexp_replace(path, "/$", "").alias("path")).filter("host <> ''").distinct()
    return rows.select(F.lit(tier).alias("tier"), "host", "path", F.lit(verdict).alias("verdict"), F.lit(True).alias("canonical"))


def _places(h: np.ndarray, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """Block of each 64-bit key hash, and one bit for each of the block's eight words."""
    h = h.view(np.uint64)
    block = ((h >> np.uint64(32)) * np.uint64(blocks)) >> np.uint64(32)
    low = (h & np.uint64(0xFFFFFFFF))[:, None]
    return block.astype(np.int64), np.uint64(1) << (((low * np.array(ODD, np.uint64)) & np.uint64(0xFFFFFFFF)) >> np.uint64(26))


def filter_blocks(codes: DataFrame, count: int) -> np.ndarray:
    """The same table as :func:`build_filter` from a column ``code``, its blocks put together by an aggregation."""
    blocks = max(1, -(-count * BITS_A_KEY // 512))
    block = F.shiftrightunsigned(F.shiftrightunsigned("code", 32) * F.lit(blocks), 32)
    low = F.col("code").bitwiseAND(F.lit(0xFFFFFFFF))
    made = codes.select(block.alias("block"), low.alias("low"))
    words = []
    for i, odd in enumerate(ODD):
        # products of 32-bit numbers, by halves so that they stay within 63 bits
        high = F.shiftleft((F.col("low") * F.lit(odd >> 16)).bitwiseAND(F.lit(0xFFFF)), 16)
        at = F.shiftrightunsigned((F.col("low") * F.lit(odd & 0xFFFF) + high).bitwiseAND(F.lit(0xFFFFFFFF)), 26)
        words.append(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), at.cast("int"))).alias(f"w{i}"))
    table = np.zeros((blocks, WORDS), np.int64)
    rows = made.groupBy("block").agg(*words).toArrow()
    at = rows.column(0).to_numpy()
    for i in range(WORDS):
        table[at, i] = rows.column(i + 1).to_numpy()
    return table.view(np.uint64)


def build_filter(hashes: Iterator[int] | np.ndarray, count: int) -> np.ndarray:
    """Blocks of eight 64-bit words for ``count`` keys."""
    table = np.zeros((max(1, -(-count * BITS_A_KEY // 512)), WORDS), np.uint64)
    block, bits = _places(np.asarray(hashes, np.int64), len(table))
    np.bitwise_or.at(table, block, bits)
    return table


def may_hold(table: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    block, bits = _places(np.asarray(hashes, np.int64), len(table))
    return ((table[block] & bits) == bits).all(axis=1)


def judge(
    urls: DataFrame, listed: DataFrame, *, id_col: str = "page_id", url_col: str = "url", default: str = "allow", filter_bytes: int = FILTER_BYTES
) -> DataFrame:
    """id, host, path, listed_host, listed_path, tier (of the best fit, or null) and verdict for each row of ``urls``.

    listed: host, path, verdict, tier and, if any is canonical, that; among fits the highest tier wins, then the longest.
    The distinct pairs of host and path are judged once, so repeated URLs meet in a partial aggregate, and are joined back
    by their own text.
    """
    host, path = host_path("_url")
    form = F.coalesce("canonical", F.lit(False)) if "canonical" in listed.columns else F.lit(False)
    keys = listed.filter("host is not null and path is not null").select("tier", "host", "path", "verdict", form.alias("form"))
    keys = keys.groupBy("tier", "host", "path", "form").agg(F.max("verdict").alias("verdict"))
    labels = lambda x: F.length(x) - F.length(F.replace(x, F.lit("."), F.lit(""))) + 1
    shapes = keys.groupBy("form", labels("host").alias("labels"), F.length("path").alias("n")).agg(F.count("*").alias("keys")).collect()
    count = sum(r["keys"] for r in shapes)
    rows = urls.select(F.col(id_col), F.col(url_col).alias("_url")).select(id_col, host.alias("host"), path.alias("path"))
    shape = F.array(*[F.struct(F.lit(r["form"]).alias("form"), F.lit(r["labels"]).alias("labels"), F.lit(r["n"]).alias("n")) for r in shapes]).cast("array<struct<form:boolean,labels:int,n:int>>")
    made = rows.select("host", "path").distinct().select("host", "path", canonical_host(F.col("host")).alias("bare"), F.explode(shape).alias("s"))
    made = made.select("host", "path", "s.*", F.when(F.col("s.form"), F.col("bare")).otherwise(F.col("host")).alias("own")).filter((F.length("path") >= F.col("n")) & (labels("own") >= F.col("labels")))
    made = made.select("host", "path", "form", F.expr("substring_index(own, '.', -labels)").alias("h"), F.expr("substring(path, 1, n)").alias("p")).withColumn("code", F.xxhash64("form", "h", "p"))
    if count * BITS_A_KEY // 8 <= filter_bytes:
        shared = urls.sparkSession.sparkContext.broadcast(filter_blocks(keys.select(F.xxhash64("form", "host", "path").alias("code")), count))

        @F.pandas_udf("boolean")
        def possible(code: pd.Series) -> pd.Series:
            return pd.Series(may_hold(shared.value, code.to_numpy(np.int64)))

        made = made.filter(possible("code"))
    k = keys.select("form", F.col("host").alias("h"), F.col("path").alias("p"), "verdict", "tier")
    rank = F.struct("tier", (F.length("h") + F.length("p")).alias("size"), F.length("h").alias("host_size"), "verdict", "h", "p")
    best = made.join(k, ["form", "h", "p"]).groupBy("host", "path").agg(F.max(rank).alias("b"))
    return rows.join(best, ["host", "path"], "left").select(
        id_col, "host", "path", F.col("b.h").alias("listed_host"), F.col("b.p").alias("listed_path"), F.col("b.tier").alias("tier"), F.coalesce("b.verdict", F.lit(default)).alias("verdict")
    )


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract rules first; where none fits, the listed sites block and all else is allowed."""
    rules = spark.createDataFrame([(1, *r, False) for r in RULES], "tier int, host string, path string, verdict string, canonical boolean")
    listed = rules.union(listing(spark.createDataFrame([(x,) for x in LISTED], "url string")))
    found = judge(C.table(spark, sf_dir, "pages"), listed)
    rule = F.when(F.col("tier") == 1, F.concat("listed_host", "listed_path"))
    return found.select("page_id", "host", "path", rule.alias("rule"), "verdict")


def _fits(host: str, path: str) -> str:
    return f"((host = '{host}' OR ends_with(host, '.{host}')) AND starts_with(path, '{path}'))"


OP10_SQL = rf"""
WITH r AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{C.UPPER}', '{C.LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
j AS (SELECT *, '.' || regexp_replace(regexp_replace(host, '^.*@', ''), '\.*(:[0-9]*)?$', '') AS bare,
  CASE {" ".join(f"WHEN {_fits(h, q)} THEN '{h}{q}'" for h, q, _ in sorted(RULES, key=lambda r: -len(r[0] + r[1])))} END AS rule FROM p)
SELECT page_id, host, path, rule, CASE WHEN rule IN ({", ".join(f"'{h}{q}'" for h, q, v in RULES if v == "allow")}) THEN 'allow' WHEN rule IS NOT NULL THEN 'block'
  WHEN {" OR ".join(f"ends_with(bare, '.{site}.example.{top}')" for site in SITES for top in ("com", "net", "org"))} THEN 'block' ELSE 'allow' END AS verdict
FROM j
"""
