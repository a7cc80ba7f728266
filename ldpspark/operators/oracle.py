"""Frequency oracles: exact counts, the small-domain and the large-domain private oracle, and what is built on them.

A private oracle has a client side (``reports``: one row-local projection) and a server side (``fit``: one aggregation of
the reports, which needs no other column; ``estimate``: answers for queried items from the sums).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.functions.dialect import DUCK, SPARK, Dialect, coefficients, linear
from ldpspark.functions.hadamard import transform

from .randomizers import unbias


def exact_counts(users: DataFrame) -> DataFrame:
    return users.groupBy("item").agg(F.count("*").alias("f"))


@dataclass(frozen=True)
class DirectOracle:
    """Small domain of ``1 << bits`` cells: a public row, and the flipped sign of the Hadamard entry (row, item)."""

    eps: float
    bits: int
    seed: int = 1
    role: str = "direct"

    @property
    def keep(self) -> float:
        from math import exp

        return exp(self.eps) / (exp(self.eps) + 1)

    def row_sign(self, d: Dialect, item: str, user: str) -> tuple[str, str]:
        g = d.digest(self.role, self.seed, user)
        r = f"({d.digits(g, 1, 8)} % {1 << self.bits})"
        return r, f"({d.sign(r, item)} * CASE WHEN {d.below(g, 9, self.keep)} THEN 1 ELSE -1 END)"

    def reports(self, users: DataFrame) -> DataFrame:
        r, s = self.row_sign(SPARK, "item", "user")
        return users.select("user", F.expr(r).alias("r"), F.expr(s).alias("s"))

    def reports_sql(self, view: str) -> str:
        r, s = self.row_sign(DUCK, "item", '"user"')
        return f'SELECT "user", {r} AS r, CAST({s} AS BIGINT) AS s FROM ({view})'

    def fit(self, reports: DataFrame) -> DataFrame:
        return reports.groupBy("r").agg(F.sum("s").alias("s"), F.count("*").alias("n"))

    def table(self, sums: DataFrame) -> DataFrame:
        """item, est for every cell."""
        t = transform(sums.withColumn("part", F.lit(0).cast("long")), self.bits)
        return t.select(F.col("cell").alias("item"), (F.col("total") * unbias(self.eps)).alias("est"))

    def estimate(self, sums: DataFrame, items: DataFrame) -> DataFrame:
        """item, est of queried items (item): the transform answers any number of them.

        An item beyond the cells falls on the cell of its low bits, in reports and answers alike.
        """
        asked = items.select("item").distinct().withColumn("cell", F.col("item").bitwiseAND(F.lit((1 << self.bits) - 1).cast("long")))
        return asked.join(self.table(sums).withColumnRenamed("item", "cell"), "cell").select("item", "est")

    def estimate_sql(self, view: str, items: str) -> str:
        """The same by the defining sum over all rows, for each queried item."""
        return f"SELECT i.item, round({unbias(self.eps)!r}::DOUBLE * sum({DUCK.sign('r.r', 'i.item')} * r.s), 6) AS est FROM ({items}) i, (SELECT r, sum(s) AS s FROM ({self.reports_sql(view)}) GROUP BY r) r GROUP BY i.item"


@dataclass(frozen=True)
class HashedOracle:
    """Large domain: users fall into ``rows`` groups; each hashes items to ``1 << bits`` cells and a sign.

    Estimate of an item: the median (or mean) over groups of rows * sign * estimate of its cell.

    With ``public_coins`` off nothing random is shared: the hashes are a fixed numbered family of ``rows`` members, each user
    draws the number of one with coins of their own and sends it along, and the server groups reports by it.
    """

    eps: float
    rows: int = 5
    bits: int = 8
    seed: int = 1
    combine: str = "median"
    role: str = "hashed"
    public_coins: bool = True

    @property
    def keep(self) -> float:
        from math import exp

        return exp(self.eps) / (exp(self.eps) + 1)

    def cell_sign(self, d: Dialect, item: str, row: str) -> tuple[str, str]:
        family, seed = (self.role, self.seed) if self.public_coins else ("family", 0)
        a0, a1, b = (d.at(coefficients(f"{family}-cell{k}", seed, self.rows), row) for k in range(3))
        c0, c1, e = (d.at(coefficients(f"{family}-sign{k}", seed, self.rows), row) for k in range(3))
        return f"(({linear(d, item, a0, a1, b)}) % {1 << self.bits})", f"(1 - 2 * (({linear(d, item, c0, c1, e)}) % 2))"

    def draw(self, d: Dialect, item: str, user: str) -> tuple[str, str, str]:
        g = d.digest(self.role, self.seed, user)
        j, r = f"({d.digits(g, 1, 8)} % {self.rows})", f"({d.digits(g, 9, 8)} % {1 << self.bits})"
        cell, sign = self.cell_sign(d, item, j)
        return j, r, f"({d.sign(r, cell)} * {sign} * CASE WHEN {d.below(g, 17, self.keep)} THEN 1 ELSE -1 END)"

    def reports(self, users: DataFrame) -> DataFrame:
        j, r, s = self.draw(SPARK, "item", "user")
        return users.select("user", F.expr(j).alias("j"), F.expr(r).alias("r"), F.expr(s).alias("s"))

    def reports_sql(self, view: str) -> str:
        j, r, s = self.draw(DUCK, "item", '"user"')
        return f'SELECT "user", {j} AS j, {r} AS r, CAST({s} AS BIGINT) AS s FROM ({view})'

    def fit(self, reports: DataFrame) -> DataFrame:
        return reports.groupBy("j", "r").agg(F.sum("s").alias("s"), F.count("*").alias("n"))

    def table(self, sums: DataFrame) -> DataFrame:
        """part (group), cell, est of the signed cell."""
        return self._totals(sums).select("part", "cell", (F.col("total") * unbias(self.eps)).alias("est"))

    def _totals(self, sums: DataFrame) -> DataFrame:
        return transform(sums.select(F.col("j").alias("part"), "r", "s"), self.bits)

    def estimate(self, sums: DataFrame, items: DataFrame) -> DataFrame:
        """item, est: every queried item meets its cell in each group by an equi-join, then the groups are combined.

        Factors stand in the order of ``estimate_sql``: another order gives other last bits, which rounding can show.
        """
        asked = items.select("item").distinct().withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(self.rows - 1))))
        cell, sign = self.cell_sign(SPARK, "item", "j")
        asked = asked.select("item", F.col("j").cast("long").alias("part"), F.expr(cell).alias("cell"), F.expr(sign).alias("sign"))
        each = asked.join(self._totals(sums), ["part", "cell"]).select("item", (F.col("sign") * self.rows * unbias(self.eps) * F.col("total")).alias("e"))
        return each.groupBy("item").agg((F.median("e") if self.combine == "median" else F.avg("e")).alias("est"))

    def estimate_sql(self, view: str, items: str) -> str:
        cell, sign = self.cell_sign(DUCK, "i.item", "g.j")
        return f"""WITH r AS (SELECT j, r, sum(s) AS s FROM ({self.reports_sql(view)}) GROUP BY j, r),
q AS (SELECT i.item, g.j, {cell} AS cell, {sign} AS sign FROM ({items}) i, (SELECT unnest(generate_series(0, {self.rows - 1})) AS j) g),
e AS (SELECT q.item, q.j, {self.rows} * q.sign * {unbias(self.eps)!r}::DOUBLE * sum({DUCK.sign('r.r', 'q.cell')} * coalesce(r.s, 0)) AS e FROM q LEFT JOIN r USING (j) GROUP BY q.item, q.j, q.sign)
SELECT item, round({'median' if self.combine == 'median' else 'avg'}(e), 6) AS est FROM e GROUP BY item"""


@dataclass(frozen=True)
class ProjectionOracle:
    """Stand-in for the oldest baseline: a dense keyed +-1 projection of a listed domain.

    Every user reports the flipped sign of one random row's entry for their item; the entries are digits of md5, so
    there is no fast transform: an item's answer is a sum over all rows.
    """

    eps: float
    width: int
    seed: int = 1
    role: str = "dense"

    def entry(self, d: Dialect, row: str, item: str) -> str:
        return f"(1 - 2 * ({d.digits(d.digest(self.role + '-m', self.seed, row, item), 1, 4)} % 2))"

    def reports_text(self, d: Dialect, item: str, user: str) -> tuple[str, str]:
        from math import exp

        g = d.digest(self.role, self.seed, user)
        r = f"({d.digits(g, 1, 8)} % {self.width})"
        return r, f"({self.entry(d, r, item)} * CASE WHEN {d.below(g, 9, exp(self.eps) / (exp(self.eps) + 1))} THEN 1 ELSE -1 END)"

    def fit(self, users: DataFrame) -> DataFrame:
        r, s = self.reports_text(SPARK, "item", "user")
        return users.select(F.expr(r).alias("r"), F.expr(s).alias("s")).groupBy("r").agg(F.sum("s").alias("s"))

    def estimate(self, sums: DataFrame, items: DataFrame) -> DataFrame:
        """The queried set (small, listed) against all rows of the projection."""
        both = sums.crossJoin(F.broadcast(items.select("item").distinct()))
        return both.groupBy("item").agg((F.sum(F.expr(self.entry(SPARK, "r", "item")) * F.col("s")) * unbias(self.eps)).alias("est"))

    def estimate_sql(self, view: str, items: str) -> str:
        r, s = self.reports_text(DUCK, "item", '"user"')
        return f"SELECT item, round({unbias(self.eps)!r}::DOUBLE * sum({self.entry(DUCK, 'r', 'item')} * s), 6) AS est FROM (SELECT r, sum(s) AS s FROM (SELECT {r} AS r, {s} AS s FROM ({view})) GROUP BY r), ({items}) GROUP BY item"


def from_list(answer: DataFrame, items: DataFrame) -> DataFrame:
    """A heavy-hitter answer as an oracle: listed items have their estimate, all others 0."""
    return items.select("item").distinct().join(answer, "item", "left").select("item", F.coalesce("est", F.lit(0.0)).alias("est"))


def post_process(answer: DataFrame, n: int, error: float, threshold: float | None = None) -> DataFrame:
    """Estimates held to [0, n] with an interval of +-error; those below ``threshold`` are dropped."""
    out = answer.withColumn("est", F.least(F.greatest(F.col("est"), F.lit(0.0)), F.lit(float(n))))
    out = out.withColumns({"low": F.greatest(F.col("est") - error, F.lit(0.0)), "high": F.least(F.col("est") + error, F.lit(float(n)))})
    return out if threshold is None else out.filter(F.col("est") >= threshold)


def bit_count(reports: DataFrame, eps: float) -> DataFrame:
    """n and the unbiased number of ones behind flipped bits (report)."""
    import math

    p = math.exp(eps) / (math.exp(eps) + 1)
    return reports.agg(F.count("*").alias("n"), F.sum("report").alias("ones")).select("n", "ones", ((F.col("ones") - F.col("n") * (1 - p)) / (2 * p - 1)).alias("est"))

