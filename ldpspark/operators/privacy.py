"""Accounting: budgets of users over all randomizers that touch them, and of adaptive analyses by max-information."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class Ledger:
    """Budgets by scope (a round, a population). ``spend`` refuses what would exceed the limit; sums are what composes."""

    limit: float
    delta_limit: float = 0.0
    spent: dict[str, tuple[float, float]] = field(default_factory=dict)

    def spend(self, scope: str, eps: float, delta: float = 0.0) -> tuple[float, float]:
        e, d = self.spent.get(scope, (0.0, 0.0))
        if e + eps > self.limit + 1e-12 or d + delta > self.delta_limit + 1e-12:
            raise ValueError(f"{scope}: {e + eps:g} is over the budget of {self.limit:g}")
        self.spent[scope] = (e + eps, d + delta)
        return self.spent[scope]

    def per_user(self, reports: DataFrame) -> DataFrame:
        """user, eps, messages, over: from reports (user, eps), one row a message."""
        spent = reports.groupBy("user").agg(F.sum("eps").alias("eps"), F.count("*").alias("messages"))
        return spent.withColumn("over", F.col("eps") > self.limit + 1e-12)


@dataclass(frozen=True)
class Frozen:
    """A non-interactive protocol: every randomizer is fixed before the first answer, so none can depend on one."""

    randomizers: tuple
    answers_seen: int = 0

    def add(self, randomizer) -> Frozen:
        if self.answers_seen:
            raise ValueError("interactive: a randomizer after the first answer")
        return Frozen((*self.randomizers, randomizer))

    def answer(self) -> Frozen:
        return Frozen(self.randomizers, self.answers_seen + 1)

    def budget(self) -> float:
        return sum(r.eps for r in self.randomizers)


def generalization(steps: list[tuple[float, float]], bad: float) -> list[tuple[float, float, float]]:
    """(total max-information, total beta, bound on a bad event of chance ``bad``) after each step of an analysis.

    steps: (k, beta) of each step in the order taken; max-information adds up in any order.
    """
    out, k, beta = [], 0.0, 0.0
    for x, b in steps:
        k, beta = k + x, beta + b
        out.append((k, beta, min(1.0, math.exp(k) * bad + beta)))
    return out
