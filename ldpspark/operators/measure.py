"""Accuracy measures over answers (item, est) and truths (item, f)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def heavy_set(users: DataFrame, threshold: int) -> DataFrame:
    """Items held by at least ``threshold`` users."""
    return users.groupBy("item").agg(F.count("*").alias("f")).filter(F.col("f") >= threshold)


def list_error(answer: DataFrame, truth: DataFrame) -> DataFrame:
    """Largest error over the list, the largest count missed and the list's length."""
    both = answer.select("item", "est").join(truth.select("item", "f"), "item", "full")
    error = F.max(F.when(F.col("est").isNotNull(), F.abs(F.col("est") - F.coalesce("f", F.lit(0)))))
    return both.agg(error.alias("max_error"), F.coalesce(F.max(F.when(F.col("est").isNull(), F.col("f"))), F.lit(0)).alias("largest_missed"), F.count("est").alias("list_size"))


def oracle_error(answer: DataFrame, truth: DataFrame) -> DataFrame:
    """Largest, mean and root mean square error over the queried items."""
    e = F.col("est") - F.coalesce("f", F.lit(0))
    return answer.join(truth, "item", "left").agg(F.count("*").alias("queries"), F.max(F.abs(e)).alias("max_error"), F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"))


def missed_heavy(answer: DataFrame, truth: DataFrame, threshold: int) -> DataFrame:
    """Heavy items that the list lacks."""
    return truth.filter(F.col("f") >= threshold).join(answer, "item", "left_anti").select("item", "f")


def recall(answer: DataFrame, truth: DataFrame, threshold: int) -> DataFrame:
    """Heavy items, those found, and listed items below the threshold."""
    heavy = truth.withColumn("heavy", F.col("f") >= threshold)
    both = heavy.join(answer.select("item", F.lit(1).alias("listed")), "item", "full")
    n = lambda c: F.count(F.when(c, 1))
    return both.agg(n(F.col("heavy")).alias("heavy"), n(F.col("heavy") & F.col("listed").isNotNull()).alias("found"), n(F.col("listed").isNotNull() & ~F.coalesce("heavy", F.lit(False))).alias("false_positives"))


def hash_collisions(users: DataFrame, heavy: DataFrame, hashed: str) -> DataFrame:
    """For each heavy item, users of other items with its value of the public hash (a text over ``item``)."""
    h = heavy.select(F.col("item").alias("heavy_item")).withColumn("h", F.expr(hashed.replace("item", "heavy_item")))
    counts = users.groupBy("item").agg(F.count("*").alias("f")).withColumn("h", F.expr(hashed))
    met = h.join(counts, (h["h"] == counts["h"]) & (h["heavy_item"] != counts["item"]), "left")
    return met.groupBy("heavy_item").agg(F.coalesce(F.sum("f"), F.lit(0)).alias("collisions"))


def tv(first: DataFrame, second: DataFrame) -> DataFrame:
    """Half the L1 distance of two laws (output, prob)."""
    both = first.select("output", F.col("prob").alias("p")).join(second.select("output", F.col("prob").alias("q")), "output", "full")
    return both.agg((F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))) / 2).alias("tv"))


def failure_rate(trials: DataFrame, limit: float) -> DataFrame:
    """Share of trials (max_err, missed) whose error or largest missed count is above ``limit``."""
    bad = (F.col("max_err") > limit) | (F.col("missed") > limit)
    return trials.agg(F.count("*").alias("trials"), F.avg(bad.cast("double")).alias("failure_rate"))


def list_expansion(candidates: DataFrame, cap: int) -> DataFrame:
    """Candidates of a decoder against its list cap."""
    return candidates.agg(F.count("*").alias("candidates"), (F.count("*") / F.lit(cap)).alias("expansion"))
