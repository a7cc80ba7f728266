"""Audits of finite channels (name, input, output, prob) and joint laws (z, w, prob)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pure_epsilon(channels: DataFrame) -> DataFrame:
    """name, eps: the largest log-ratio over outputs; from the extremes of each output, without a join of inputs."""
    per = channels.groupBy("name", "output").agg(F.max("prob").alias("hi"), F.min("prob").alias("lo"))
    ratio = F.when(F.col("hi") == 0, 0.0).when(F.col("lo") == 0, F.lit(float("inf"))).otherwise(F.log(F.col("hi") / F.col("lo")))
    return per.groupBy("name").agg(F.max(ratio).alias("eps"))


def delta_at(channels: DataFrame, eps: float) -> DataFrame:
    """name, delta: over ordered pairs of inputs, the largest sum of the positive parts of p - e^eps q."""
    a, b = channels.alias("a"), channels.alias("b")
    both = a.join(b, (F.col("a.name") == F.col("b.name")) & (F.col("a.output") == F.col("b.output")) & (F.col("a.input") != F.col("b.input")))
    part = F.greatest(F.lit(0.0), F.col("a.prob") - math.exp(eps) * F.col("b.prob"))
    return both.groupBy(F.col("a.name").alias("name"), F.col("a.input").alias("x"), F.col("b.input").alias("y")).agg(F.sum(part).alias("d")).groupBy("name").agg(F.max("d").alias("delta"))


def privacy_loss(channels: DataFrame, x: int, y: int) -> DataFrame:
    """name, mean and largest magnitude of the loss between two inputs, and the bound of its mean."""
    p, q = channels.filter(F.col("input") == x), channels.filter(F.col("input") == y)
    both = p.select("name", "output", F.col("prob").alias("p")).join(q.select("name", "output", F.col("prob").alias("q")), ["name", "output"]).filter("p > 0 and q > 0")
    loss = F.log(F.col("p") / F.col("q"))
    return both.groupBy("name").agg(F.sum(F.col("p") * loss).alias("mean_loss"), F.max(F.abs(loss)).alias("max_loss"))


def group_loss(eps: float, k: int) -> list[tuple[float, float]]:
    """(loss, probability) of k flipped bits: k independent losses of +-eps, exact."""
    from ldpspark.plans.bounds import binomial

    p = math.exp(eps) / (math.exp(eps) + 1)
    return [(eps * (2 * i - k), q) for i, q in enumerate(binomial(k, p))]


def group_quantile(eps: float, k: int, delta: float) -> float:
    """Least v with a chance of at most delta that the loss of k users exceeds it."""
    tail = 0.0
    for loss, q in reversed(group_loss(eps, k)):
        tail += q
        if tail > delta:
            return loss
    return -eps * k


def max_information(joint: DataFrame, beta: float) -> DataFrame:
    """name, k: the beta-approximate max-information of each joint law (name, z, w, prob).

    The worst event takes atoms by falling ratio to the product of the marginals; windows give the running masses.
    """
    z, w = Window.partitionBy("name", "z"), Window.partitionBy("name", "w")
    atoms = joint.withColumn("product", F.sum("prob").over(z) * F.sum("prob").over(w))
    run = Window.partitionBy("name").orderBy(F.desc(F.col("prob") / F.col("product")), "z", "w").rowsBetween(Window.unboundedPreceding, 0)
    summed = atoms.withColumns({"mass": F.sum("prob").over(run), "mass0": F.sum("product").over(run)})
    value = F.when(F.col("mass") > beta, F.log((F.col("mass") - beta) / F.col("mass0")))
    return summed.groupBy("name").agg(F.max(value).alias("k"))


def mutual_information(joint: DataFrame) -> DataFrame:
    """name, bits."""
    z, w = Window.partitionBy("name", "z"), Window.partitionBy("name", "w")
    atoms = joint.withColumns({"pz": F.sum("prob").over(z), "pw": F.sum("prob").over(w)}).filter("prob > 0")
    return atoms.groupBy("name").agg(F.sum(F.col("prob") * F.log2(F.col("prob") / (F.col("pz") * F.col("pw")))).alias("bits"))


def bad_mass(channels: DataFrame, eps: float, default: int = 0) -> DataFrame:
    """name, bad: largest probability, over inputs, of outputs whose ratio to the default input leaves e^(+-2 eps)."""
    base = channels.filter(F.col("input") == default).select("name", "output", F.col("prob").alias("q"))
    both = channels.join(base, ["name", "output"])
    out = (F.col("prob") > math.exp(2 * eps) * F.col("q")) | (F.col("prob") < math.exp(-2 * eps) * F.col("q"))
    return both.groupBy("name", "input").agg(F.sum(F.when(out, F.greatest("prob", "q")).otherwise(0.0)).alias("m")).groupBy("name").agg(F.max("m").alias("bad"))


def purify_law(p: list[float]) -> list[float]:
    """Law of the reported index for acceptance probabilities ``p``: uniform over accepted ones, over all if none is."""
    from ldpspark.plans.bounds import poisson_binomial

    t, none = len(p), math.prod(1 - x for x in p)
    out = []
    for g in range(t):
        others = poisson_binomial(p[:g] + p[g + 1 :])
        out.append(p[g] * math.fsum(q / (w + 1) for w, q in enumerate(others)) + none / t)
    return out


def purify_epsilon(eps: float, t: int) -> float:
    """Exact worst log-ratio of an index's probability for acceptance probabilities within e^(+-2 eps) / 2."""
    lo, hi = math.exp(-2 * eps) / 2, math.exp(2 * eps) / 2
    return math.log(purify_law([hi] + [lo] * (t - 1))[0] / purify_law([lo] + [hi] * (t - 1))[0])
