"""The lower bound's hard instance: few random bits, each held by a block of users."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.functions.dialect import DUCK, SPARK, Dialect

from .randomizers import BitFlip


@dataclass(frozen=True)
class HardInstance:
    """m = c eps^2 n source bits; user i holds bit floor(i m / n) and reports it by a bit flip at eps."""

    n: int
    eps: float
    c: float = 1.0
    seed: int = 1

    @property
    def m(self) -> int:
        return max(1, round(self.c * self.eps**2 * self.n))

    def source(self, d: Dialect, block: str) -> str:
        return f"({d.digits(d.digest('source', self.seed, block), 1, 1)} % 2)"

    def users(self, places: DataFrame) -> DataFrame:
        """user, block, item for users 0..n-1 (column user)."""
        rows = places.select("user", F.expr(f"(user * {self.m}) div {self.n}").alias("block"))
        return rows.select("user", "block", F.expr(self.source(SPARK, "block")).alias("item"))

    def users_sql(self) -> str:
        return f"SELECT \"user\", block, {self.source(DUCK, 'block')} AS item FROM (SELECT \"user\", (\"user\" * {self.m}) // {self.n} AS block FROM (SELECT unnest(generate_series(0, {self.n - 1})) AS \"user\"))"

    @property
    def flip(self) -> BitFlip:
        return BitFlip(self.eps, self.seed, "hard")

    def blocks(self, users: DataFrame) -> DataFrame:
        """block, len, ones of the reports, and the source bit."""
        told = users.select("block", "item", F.expr(self.flip.report(SPARK, "item", "user")).alias("report"))
        return told.groupBy("block").agg(F.count("*").alias("len"), F.sum("report").alias("ones"), F.max("item").alias("bit"))

    def posterior(self, blocks: DataFrame) -> DataFrame:
        """block, post (chance of a one given the block's reports), entropy in bits, good (entropy of a half or more)."""
        odds = F.lit(self.eps) * (2 * F.col("ones") - F.col("len"))
        post = 1 / (1 + F.exp(-odds))
        h = -(F.col("post") * F.log2("post") + (1 - F.col("post")) * F.log2(1 - F.col("post")))
        return blocks.withColumn("post", post).withColumn("entropy", h).withColumn("good", F.col("entropy") >= 0.5)

    def posterior_sql(self) -> str:
        q = '"user"'
        return f"""SELECT *, -(post * log2(post) + (1 - post) * log2(1 - post)) AS entropy FROM (SELECT *, 1 / (1 + exp(-{self.eps!r}::DOUBLE * (2 * ones - len))) AS post FROM
(SELECT block, count(*) AS len, CAST(sum({self.flip.report(DUCK, 'item', q)}) AS BIGINT) AS ones, max(item) AS bit FROM ({self.users_sql()}) GROUP BY block))"""

    def error(self, blocks: DataFrame) -> DataFrame:
        """Error of the unbiased count over users, and the same error scaled to the source bits by m / n."""
        p = math.exp(self.eps) / (math.exp(self.eps) + 1)
        est = (F.sum("ones") - F.sum("len") * (1 - p)) / (2 * p - 1)
        out = blocks.agg(est.alias("est"), F.sum(F.col("bit") * F.col("len")).alias("truth"), F.sum("bit").alias("source_truth"))
        return out.select("est", "truth", (F.col("est") - F.col("truth")).alias("error"), (F.col("est") * self.m / self.n - F.col("source_truth")).alias("source_error"))


def sum_law(ps: list[float]) -> list[float]:
    """Probabilities of 0, 1, ... ones among independent bits."""
    law = [1.0]
    for p in ps:
        law = [(law[k] * (1 - p) if k < len(law) else 0.0) + (law[k - 1] * p if k else 0.0) for k in range(len(law) + 1)]
    return law


def outside(ps: list[float], low: float, high: float) -> float:
    """Probability that the sum of independent bits leaves the interval."""
    return sum(x for k, x in enumerate(sum_law(ps)) if not low <= k <= high)


def exchange(ps: list[float], c: float, low: float, high: float) -> list[tuple[int, str, float, float, float]]:
    """Steps from any bits with means in 1/2 +- c to one binomial: (step, what, low, high, probability outside), never rising.

    First each mean is moved to the end of its range that leaves the sum outside less often; then the bits of the rarer end
    become constants, which moves the interval. Left is a binomial of at least half the bits and an interval as long.
    """
    now, out = list(ps), [(0, "given", low, high, outside(ps, low, high))]
    for i in range(len(now)):
        now[i] = min((0.5 - c, 0.5 + c), key=lambda p: outside([*now[:i], p, *now[i + 1 :]], low, high))
        out.append((i + 1, "end of range", low, high, outside(now, low, high)))
    ends = sorted((0.5 - c, 0.5 + c), key=now.count)
    rest = [p for p in now if p == ends[1]] + [p for p in now if p == ends[0]]
    while len(rest) > max(now.count(ends[1]), 1) or len(rest) > (len(ps) + 1) // 2:
        rest.pop()
        shift = min((0, 1), key=lambda x: outside(rest, low - x, high - x))
        low, high = low - shift, high - shift
        out.append((len(out), "constant", low, high, outside(rest, low, high)))
    return out
