"""Connected components of a graph given as a table of links, without holding it in one place."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, label (least node of its component) for every node of ``links``; nodes of any orderable type.

    Links are turned towards smaller nodes in rounds: first every node hands its least neighbour to the larger ones,
    then to the smaller ones, until each node points at its component's least node. Rounds grow with the logarithm of a
    component's width. Least neighbours are partial aggregates, so a node with many links is no hot spot there.
    """
    now = C.stored(_turned(links.select(F.col(a).alias("u"), F.col(b).alias("v"))), "links")
    while True:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = _turned(large)
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        turned = C.stored(_turned(small.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))), "links")
        # settled: every node has one link, to a node that has none itself
        heads = turned.select(F.col("v").alias("u")).distinct()
        many = turned.groupBy("u").count().filter("count > 1").limit(1).count()
        if not many and not turned.join(heads, "u", "left_semi").limit(1).count():
            heads = heads.select(F.col("u").alias("node"), F.col("u").alias("label"))
            return turned.select(F.col("u").alias("node"), F.col("v").alias("label")).union(heads)
        now = turned


def _turned(links: DataFrame) -> DataFrame:
    """Distinct links from the larger to the smaller node, without loops."""
    return links.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
