"""A pure-private stand-in for k randomized responses: keep a draw near its expected distance, else draw far away."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions.dialect import SPARK, Dialect
from ldpspark.plans.bounds import value

from .randomizers import VectorFlip


def bounds(k: int, eps: float, beta: float) -> tuple[int, int]:
    """Least and largest Hamming distance of the shell around an input."""
    centre, radius = k / (math.exp(eps) + 1), math.sqrt(k * math.log(2 / beta) / 2)
    return max(0, math.ceil(centre - radius)), min(k, math.floor(centre + radius))


def law(k: int, eps: float, beta: float) -> list[tuple[int, int, bool, float, float]]:
    """(distance, strings at it, inside, probability of each under the stand-in, under k flips)."""
    lo, hi = bounds(k, eps, beta)
    q = 1 / (math.exp(eps) + 1)
    flips = [q**d * (1 - q) ** (k - d) for d in range(k + 1)]
    outside = [d for d in range(k + 1) if not lo <= d <= hi]
    strings = sum(math.comb(k, d) for d in outside)
    common = sum(math.comb(k, d) * flips[d] for d in outside) / strings if strings else 0.0
    return [(d, math.comb(k, d), lo <= d <= hi, flips[d] if lo <= d <= hi else common, flips[d]) for d in range(k + 1)]


def exact_epsilon(k: int, eps: float, beta: float) -> float:
    """Any two distances can be those of one output to two inputs, so extremes over distances decide."""
    p = [x[3] for x in law(k, eps, beta)]
    return math.log(max(p) / min(p))


def tv_exact(k: int, eps: float, beta: float) -> float:
    return sum(n * abs(p - f) for _, n, _, p, f in law(k, eps, beta)) / 2


def feasible(k: int, eps: float, beta: float) -> bool:
    return 0 < beta < value("shell_beta_limit", eps=eps, k=k) and value("shell_eps", eps=eps, k=k, beta=beta) <= 1


def law_frame(spark: SparkSession, k: int, eps: float, beta: float) -> DataFrame:
    return spark.createDataFrame(law(k, eps, beta), "distance int, strings long, inside boolean, prob double, flip_prob double")


@dataclass(frozen=True)
class ShellResponse:
    eps: float
    k: int
    beta: float
    seed: int = 1
    role: str = "shell"

    @property
    def flips(self) -> VectorFlip:
        return VectorFlip(self.eps, self.seed, self.role, self.k)

    def mask(self, d: Dialect, user: str) -> str:
        """The bits that the report differs in from the input."""
        lo, hi = bounds(self.k, self.eps, self.beta)
        drawn = "CAST(" + " + ".join(self.flips.flips(d, user)) + " AS BIGINT)"
        outside = [x for x in range(self.k + 1) if not lo <= x <= hi]
        if not outside:  # the shell holds all strings
            return drawn
        total, so_far, cases = sum(math.comb(self.k, x) for x in outside), 0, []
        g = d.digits(d.digest(self.role + "-far", self.seed, user), 1, 13)
        for x in outside[:-1]:
            so_far += math.comb(self.k, x)
            cases.append(f"WHEN {g} < {(so_far << 52) // total} THEN {x}")
        distance = f"CASE {' '.join(cases)} ELSE {outside[-1]} END" if cases else str(outside[0])
        # the bits of the least keyed numbers make a random subset of that size; a bit is the number's last digits
        ranks = [f"{d.digits(d.digest(f'{self.role}-bit{i // 2}', self.seed, user), 1 + 13 * (i % 2), 11)} * 64 + {i}" for i in range(self.k)]
        if d.duck:
            far = f"CAST(coalesce(list_sum(list_transform(list_sort([{', '.join(ranks)}])[1:{distance}], lambda v: CAST(1 AS BIGINT) << CAST(v % 64 AS INTEGER))), 0) AS BIGINT)"
        else:
            far = f"aggregate(slice(array_sort(array({', '.join(ranks)})), 1, {distance}), CAST(0 AS BIGINT), (s, v) -> s + shiftleft(CAST(1 AS BIGINT), CAST(v % 64 AS INT)))"
        return f"(CASE WHEN bit_count({drawn}) BETWEEN {lo} AND {hi} THEN {drawn} ELSE {far} END)"

    def report(self, d: Dialect, item: str, user: str) -> str:
        m = self.mask(d, user)
        return f"xor(CAST({item} AS BIGINT), {m})" if d.duck else f"(CAST({item} AS BIGINT) ^ {m})"

    def reports(self, users: DataFrame) -> DataFrame:
        return users.select("user", F.expr(self.report(SPARK, "item", "user")).alias("report"))

    def estimate(self, reports: DataFrame) -> DataFrame:
        """bit, est: as for independent flips, which the reports are but for a chance of beta."""
        p = self.flips.keep
        bits = reports.select(F.explode(F.array(*[F.struct(F.lit(i).alias("bit"), F.expr(f"CAST(report & {1 << i} <> 0 AS INT)").alias("one")) for i in range(self.k)])).alias("x")).select("x.*")
        return bits.groupBy("bit").agg(((F.sum("one") - F.count("*") * (1 - p)) / (2 * p - 1)).alias("est"))


def half_cube_keep(eps: float) -> float:
    return math.exp(eps) / (math.exp(eps) + 1)


@dataclass(frozen=True)
class HalfCube:
    """Earlier pure scheme's stand-in: a uniform vector of the half of the cube nearer to the input, or of the other.

    ``k`` odd. Distances up to (k - 1) / 2 are the near half; the law within a half is uniform, unlike k flips.
    """

    eps: float
    k: int
    seed: int = 1
    role: str = "half"

    def reports(self, users: DataFrame) -> DataFrame:
        d = SPARK
        g = d.digest(self.role, self.seed, "user")
        uniform = f"({d.digits(g, 14, 12)} % {1 << self.k})"
        near = f"(bit_count(CAST(item AS BIGINT) ^ {uniform}) <= {(self.k - 1) // 2})"
        full = (1 << self.k) - 1
        # a uniform vector, turned to its opposite if it lies in the half that the coin didn't pick
        pick = d.below(g, 1, half_cube_keep(self.eps))
        return users.select("user", F.expr(f"CASE WHEN {pick} = {near} THEN {uniform} ELSE {uniform} ^ {full} END").alias("report"))

    def estimate(self, reports: DataFrame) -> DataFrame:
        near = sum(math.comb(self.k - 1, i) for i in range((self.k - 1) // 2 + 1)) / 2 ** (self.k - 1)
        p = half_cube_keep(self.eps)
        agree = p * near + (1 - p) * (1 - near)
        bits = reports.select(F.explode(F.array(*[F.struct(F.lit(i).alias("bit"), F.expr(f"CAST(report & {1 << i} <> 0 AS INT)").alias("one")) for i in range(self.k)])).alias("x")).select("x.*")
        return bits.groupBy("bit").agg(((F.sum("one") - F.count("*") * (1 - agree)) / (2 * agree - 1)).alias("est"))
