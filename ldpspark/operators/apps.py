"""Applications on the small-domain oracle: quantiles, range counts, top lists, histograms by group, cell centres."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.functions.dialect import SPARK

from .oracle import DirectOracle


def answers(users: DataFrame, oracle: DirectOracle, size: int) -> DataFrame:
    """item, est of the whole domain 0..size-1."""
    return oracle.table(oracle.fit(oracle.reports(users))).filter(F.col("item") < size)


def quantile(users: DataFrame, oracle: DirectOracle, size: int, q: float) -> DataFrame:
    """Least value whose running estimate reaches q of the total."""
    est = answers(users, oracle, size)
    run = est.withColumn("run", F.sum("est").over(Window.orderBy("item").rowsBetween(Window.unboundedPreceding, 0))).withColumn("all", F.sum("est").over(Window.partitionBy()))
    return run.filter(F.col("run") >= q * F.col("all")).agg(F.min("item").alias("value"))


def dyadic(users: DataFrame, bits: int) -> DataFrame:
    """user, level, item >> level: one user answers one level, drawn by the key."""
    level = f"({SPARK.digits(SPARK.digest('level', 1, 'user'), 1, 8)} % {bits})"
    return users.select("user", "item", F.expr(level).alias("level")).select("user", "level", F.expr("shiftright(item, cast(level as int))").alias("item"))


def range_count(users: DataFrame, oracle: DirectOracle, size: int, lo: int, hi: int) -> DataFrame:
    return answers(users, oracle, size).filter(F.col("item").between(lo, hi)).agg(F.sum("est").alias("est"))


def top_k(users: DataFrame, oracle: DirectOracle, size: int, k: int) -> DataFrame:
    return answers(users, oracle, size).orderBy(F.desc("est"), "item").limit(k)


def histogram(users: DataFrame, group: str, oracle: DirectOracle, size: int) -> DataFrame:
    """group, item, est: one oracle a group; groups are public, and each user is in one."""
    from ldpspark.functions.hadamard import transform

    from .randomizers import unbias

    r, s = oracle.row_sign(SPARK, "item", "user")
    sums = users.select(F.col(group).cast("long").alias("part"), F.expr(r).alias("r"), F.expr(s).alias("s")).groupBy("part", "r").agg(F.sum("s").alias("s"))
    return transform(sums, oracle.bits).filter(F.col("cell") < size).select(F.col("part").alias(group), F.col("cell").alias("item"), (F.col("total") * unbias(oracle.eps)).alias("est"))


def cell_centres(vectors: DataFrame, cells: DataFrame, least: float) -> DataFrame:
    """Cells (item, est) over ``least``: seeds for clustering, as the signs of each cell's bits."""
    return cells.filter(F.col("est") >= least).select("item", "est")
