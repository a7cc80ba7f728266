"""Heavy hitters: the main algorithm, the single-hash baseline and its repetitions, the exact sketch, the domain scan."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.functions.dialect import DUCK, SPARK, Dialect, coefficients, linear
from ldpspark.functions import hadamard
from ldpspark.functions.hadamard import butterfly, dense
from ldpspark.plans.planner import ExpanderPlan

from . import decode as D
from .oracle import DirectOracle, HashedOracle
from .randomizers import unbias

WINNERS = "b bigint, m bigint, y bigint, z bigint, est double"


@dataclass(frozen=True)
class ExpanderHeavyHitters:
    """One report a user holds both halves: a sign on the cell of the user's coordinate, a sign for the final oracle."""

    plan: ExpanderPlan

    @property
    def final(self) -> HashedOracle:
        p = self.plan
        return HashedOracle(p.eps_final, p.oracle_rows, p.oracle_bits, p.seed, role="final")

    def _draw(self, d: Dialect, user: str) -> tuple[str, str, str, str]:
        """Digest, coordinate, row and sign coin of the coordinate half."""
        p, g = self.plan, d.digest("expander", self.plan.seed, user)
        from math import exp

        keep = exp(p.eps_coordinate) / (exp(p.eps_coordinate) + 1)
        return g, p.group_text(d, g), f"({d.digits(g, 9, 8)} % {1 << p.cell_bits})", f"CASE WHEN {d.below(g, 17, keep)} THEN 1 ELSE -1 END"

    def reports(self, users: DataFrame) -> DataFrame:
        """user, m, r1, s1, j, r2, s2: both halves by one projection of one scan."""
        _, m, r, coin = self._draw(SPARK, "user")
        j, r2, s2 = self.final.draw(SPARK, "item", "user")
        drawn = users.select("user", "item", F.expr(m).alias("m"), F.expr(r).alias("r1"))
        sign = SPARK.sign("r1", self.plan.cell_text(SPARK, "item", "m"))
        return drawn.select("user", "m", "r1", F.expr(f"{sign} * {coin}").alias("s1"), F.expr(j).alias("j"), F.expr(r2).alias("r2"), F.expr(s2).alias("s2"))

    def cells_sql(self, view: str) -> str:
        _, m, r, coin = self._draw(DUCK, '"user"')
        return f'SELECT "user", m, {self.plan.cell_text(DUCK, "item", "m")} AS cell, r, coin FROM (SELECT "user", item, {m} AS m, {r} AS r, {coin} AS coin FROM ({view}))'

    def cells(self, users: DataFrame) -> DataFrame:
        """user, m, cell: what the coordinate half counts (it never leaves the client)."""
        _, m, _, _ = self._draw(SPARK, "user")
        return users.select("user", "item", F.expr(m).alias("m")).select("user", "m", F.expr(self.plan.cell_text(SPARK, "item", "m")).alias("cell"))

    def sums_sql(self, view: str) -> str:
        return f"SELECT m, r, CAST(sum({DUCK.sign('r', 'cell')} * coin) AS BIGINT) AS s, count(*) AS n FROM ({self.cells_sql(view)}) GROUP BY m, r"

    def coordinate_sums(self, reports: DataFrame) -> DataFrame:
        """m, r, s, n: at most M * K rows, whatever the number of users."""
        return reports.groupBy("m", F.col("r1").alias("r")).agg(F.sum("s1").alias("s"), F.count("*").alias("n"))

    def final_sums_sql(self, view: str) -> str:
        return f"SELECT j, r, CAST(sum(s) AS BIGINT) AS s, count(*) AS n FROM ({self.final.reports_sql(view)}) GROUP BY j, r"

    def final_sums(self, reports: DataFrame) -> DataFrame:
        """j, r, s, n: at most t * R rows."""
        return reports.groupBy("j", F.col("r2").alias("r")).agg(F.sum("s2").alias("s"), F.count("*").alias("n"))

    def winners(self, sums: DataFrame, threshold: float | None = None) -> DataFrame:
        """Best z of each (b, m, y) over the threshold.

        Up to ``hadamard.LOCAL_BITS`` a task transforms one coordinate; beyond, the transform is split and a task holds a
        block of cells with all z of its (b, y). Either returns winners only.
        """
        p, limit = self.plan, self.plan.threshold if threshold is None else threshold
        scale = unbias(p.eps_coordinate)
        if p.cell_bits <= hadamard.LOCAL_BITS:

            def coordinate(g: pd.DataFrame) -> pd.DataFrame:
                est = butterfly(dense(g["r"].to_numpy(), g["s"].to_numpy(), p.cell_bits)) * scale
                return _best(est, int(g["m"].iloc[0]), p, limit)

            return sums.select("m", "r", "s").groupBy("m").applyInPandas(coordinate, WINNERS)
        low = max(p.code.z_bits, p.cell_bits // 2)
        return hadamard.transform_blocks(sums.select(F.col("m").alias("part"), "r", "s"), p.cell_bits, low, lambda m, first, total: _best(total * scale, m, p, limit, first), WINNERS)

    def lists(self, winners: DataFrame) -> DataFrame:
        return D.cap_lists(winners, self.plan.cap)

    def decode(self, lists: DataFrame) -> DataFrame:
        """(b, item, agree) of items that also fall into their bucket."""
        own = F.expr(self.plan.bucket_text(SPARK, "item"))
        return D.decode(lists, self.plan.code, self.plan.agree).filter(own == F.col("b"))

    def final_estimates(self, sums: DataFrame, candidates: DataFrame) -> DataFrame:
        return self.final.estimate(sums, candidates)

    def from_reports(self, reports: DataFrame) -> DataFrame:
        """Server side alone: item, est from the reports."""
        found = self.decode(self.lists(self.winners(self.coordinate_sums(reports)))).select("item").distinct()
        return self.final_estimates(self.final_sums(reports), found)

    def run(self, users: DataFrame) -> DataFrame:
        return self.from_reports(self.reports(users))


def _best(est: np.ndarray, m: int, p: ExpanderPlan, limit: float, first: int = 0) -> pd.DataFrame:
    """Winners among cells from ``first`` on, which hold all z of each (b, y), ties to the smaller z."""
    rows = est.reshape(-1, 1 << p.code.z_bits)
    z = rows.argmax(axis=1)
    top = np.take_along_axis(rows, z[:, None], axis=1)[:, 0]
    k = np.flatnonzero(top >= limit)
    at = k + (first >> p.code.z_bits)
    return pd.DataFrame({"b": at >> p.code.y_bits, "m": np.full(len(k), m, np.int64), "y": at & (1 << p.code.y_bits) - 1, "z": z[k].astype(np.int64), "est": top[k]})


@dataclass(frozen=True)
class ExactCodeSketch:
    """The same code with exact counts: not private, no noise, and each coordinate counts all of its users."""

    plan: ExpanderPlan

    def counts(self, users: DataFrame) -> DataFrame:
        p = self.plan
        _, m, _, _ = ExpanderHeavyHitters(p)._draw(SPARK, "user")
        drawn = users.select("item", F.expr(m).alias("m"))
        cell = drawn.select("m", F.expr(p.bucket_text(SPARK, "item")).alias("b"), F.expr(p.code.y_text(SPARK, "item", "m")).alias("y"), F.expr(p.code.z_text(SPARK, "item", "m")).alias("z"))
        return cell.groupBy("b", "m", "y", "z").agg(F.count("*").alias("f"))

    def lists(self, users: DataFrame, least: int) -> DataFrame:
        """Largest count of each (b, m, y), ties to the smaller z, at least ``least``."""
        best = self.counts(users).groupBy("b", "m", "y").agg(F.max(F.struct("f", (-F.col("z")).alias("neg"))).alias("x"))
        return D.cap_lists(best.select("b", "m", "y", (-F.col("x.neg")).alias("z"), F.col("x.f").alias("est")).filter(F.col("est") >= least), self.plan.cap)

    def lists_sql(self, view: str, least: int) -> str:
        p = self.plan
        _, m, _, _ = ExpanderHeavyHitters(p)._draw(DUCK, '"user"')
        return f"""WITH c AS (SELECT m, {p.bucket_text(DUCK, 'item')} AS b, {p.code.y_text(DUCK, 'item', 'm')} AS y, {p.code.z_text(DUCK, 'item', 'm')} AS z FROM (SELECT item, {m} AS m FROM ({view}))),
f AS (SELECT b, m, y, z, count(*) AS est FROM c GROUP BY ALL), w AS (SELECT *, row_number() OVER (PARTITION BY b, m, y ORDER BY est DESC, z) AS k FROM f),
l AS (SELECT *, row_number() OVER (PARTITION BY b, m ORDER BY est DESC, y) AS rank FROM w WHERE k = 1 AND est >= {least})
SELECT b, m, y, z, est FROM l WHERE rank <= {p.cap}"""

    def candidates(self, users: DataFrame, least: int) -> DataFrame:
        return D.decode(self.lists(users, least), self.plan.code, self.plan.agree).select("item").distinct()


@dataclass(frozen=True)
class SingleHash:
    """Baseline: one public hash for all coordinates, items as plain symbols joined by the shared hash value.

    ``reps`` repetitions with hashes of their own; ``split="users"`` deals the users out to them, ``"budget"`` lets all
    users take part in each at eps / reps.
    """

    eps: float
    n: int
    bits: int = 24
    s: int = 8
    y_bits: int = 6
    reps: int = 1
    split: str = "users"
    seed: int = 9
    sigmas: float = 5.0
    oracle_bits: int = 10

    @property
    def m(self) -> int:
        return -(-self.bits // self.s)

    @property
    def cell_bits(self) -> int:
        return self.y_bits + self.s

    @property
    def eps_coordinate(self) -> float:
        return self.eps / 2 / (self.reps if self.split == "budget" else 1)

    @property
    def final(self) -> HashedOracle:
        return HashedOracle(self.eps / 2, 5, self.oracle_bits, self.seed, role="single-final")

    @property
    def threshold(self) -> float:
        share = self.n / self.m / (self.reps if self.split == "users" else 1)
        return self.sigmas * unbias(self.eps_coordinate) * share**0.5

    def h(self, d: Dialect, item: str, rep: str) -> str:
        a0, a1, b = (d.at(coefficients(f"single{k}", self.seed, self.reps), rep) for k in range(3))
        return f"(({linear(d, item, a0, a1, b)}) % {1 << self.y_bits})"

    def symbol(self, d: Dialect, item: str, m: str) -> str:
        return f"({d.div(item, d.at([1 << self.s * k for k in range(self.m)], m))} % {1 << self.s})"

    def sums(self, users: DataFrame) -> DataFrame:
        """rep, m, r, s."""
        rep, m, r, sign = self._texts(SPARK, "user")
        if self.split == "budget":
            users = users.withColumn("rep", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(self.reps - 1).cast("long"))))
        else:
            users = users.withColumn("rep", F.expr(rep))
        drawn = users.select("item", "rep", F.expr(m).alias("m"), F.expr(r).alias("r"), F.expr(sign).alias("coin"))
        cell = f"({self.h(SPARK, 'item', 'rep')} * {1 << self.s} + {self.symbol(SPARK, 'item', 'm')})"
        return drawn.select("rep", "m", "r", F.expr(f"{SPARK.sign('r', cell)} * coin").alias("s")).groupBy("rep", "m", "r").agg(F.sum("s").alias("s"))

    def _texts(self, d: Dialect, user: str) -> tuple[str, str, str, str]:
        from math import exp

        keep = exp(self.eps_coordinate) / (exp(self.eps_coordinate) + 1)
        rep = f"({d.digits(d.digest('single-rep', self.seed, user), 1, 8)} % {self.reps})"
        g = d.digest("single", self.seed, "rep", user)
        return rep, f"({d.digits(g, 1, 8)} % {self.m})", f"({d.digits(g, 9, 8)} % {1 << self.cell_bits})", f"CASE WHEN {d.below(g, 17, keep)} THEN 1 ELSE -1 END"

    def sums_sql(self, view: str) -> str:
        rep, m, r, sign = self._texts(DUCK, '"user"')
        source = f'SELECT "user", item, {rep} AS rep FROM ({view})' if self.split == "users" else f'SELECT "user", item, unnest(generate_series(0, {self.reps - 1})) AS rep FROM ({view})'
        cell = f"({self.h(DUCK, 'item', 'rep')} * {1 << self.s} + {self.symbol(DUCK, 'item', 'm')})"
        return f"SELECT rep, m, r, CAST(sum({DUCK.sign('r', cell)} * coin) AS BIGINT) AS s FROM (SELECT item, rep, {m} AS m, {r} AS r, {sign} AS coin FROM ({source})) GROUP BY rep, m, r"

    def candidates(self, sums: DataFrame) -> DataFrame:
        """Items joined from the winning symbols of a hash value that pass the threshold in every coordinate."""
        scale, limit, s, y_bits, bits, parts = unbias(self.eps_coordinate), self.threshold, self.s, self.y_bits, self.cell_bits, self.m

        def best(part: int, first: int, total: np.ndarray) -> pd.DataFrame:
            est = (total * scale).reshape(-1, 1 << s)
            z, y = est.argmax(axis=1), np.flatnonzero(est.max(axis=1) >= limit)
            return pd.DataFrame({"rep": np.full(len(y), part // parts, np.int64), "y": y + (first >> s), "part": z[y].astype(np.int64) << (s * (part % parts))})

        schema, of_part = "rep bigint, y bigint, part bigint", sums.select((F.col("rep") * parts + F.col("m")).alias("part"), "r", "s")
        if bits <= hadamard.LOCAL_BITS:
            won = of_part.groupBy("part").applyInPandas(lambda g: best(int(g["part"].iloc[0]), 0, butterfly(dense(g["r"].to_numpy(), g["s"].to_numpy(), bits))), schema)
        else:
            won = hadamard.transform_blocks(of_part, bits, max(s, bits // 2), best, schema)
        return won.groupBy("rep", "y").agg(F.sum("part").alias("item"), F.count("*").alias("parts")).filter(F.col("parts") == self.m).select("item").distinct()

    def run(self, users: DataFrame) -> DataFrame:
        return self.final.estimate(self.final.fit(self.final.reports(users)), self.candidates(self.sums(users)))


def scan_domain(users: DataFrame, oracle: DirectOracle, size: int, threshold: float) -> DataFrame:
    """For more users than items: the oracle asked for every item, those over the threshold kept."""
    t = oracle.table(oracle.fit(oracle.reports(users)))
    return t.filter((F.col("item") < size) & (F.col("est") >= threshold))


def auto(users: DataFrame, plan: ExpanderPlan, domain: int) -> DataFrame:
    """The domain scan if there are more users than items, else the main algorithm."""
    if plan.n > domain:
        oracle = DirectOracle(plan.eps, max(1, (domain - 1).bit_length()), plan.seed)
        return scan_domain(users, oracle, domain, plan.sigmas * unbias(plan.eps) * plan.n**0.5)
    return ExpanderHeavyHitters(plan).run(users)


def half(plan: ExpanderPlan, **changes) -> ExpanderPlan:
    """A plan with some values changed, for ablations."""
    return replace(plan, **changes)
