"""From approximate to pure privacy: a user reports the place of one accepted public sample."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.functions.dialect import SPARK, Dialect

from .randomizers import Randomizer


@dataclass(frozen=True)
class RejectionPurifier:
    """``t`` public samples of the randomizer at the default input, each accepted by half its likelihood ratio.

    Samples are derived from seed, user and place; they are never stored. All steps are row-local array functions.
    """

    inner: Randomizer
    t: int
    seed: int = 1
    default: int = 0
    role: str = "purify"

    def sample(self, d: Dialect, user: str, place: str) -> str:
        """The public sample at a place, by the inverse of the default input's distribution."""
        g = d.digits(d.digest(self.role + "-pub", self.seed, user, place), 1, 13)
        law = [(y, p) for x, y, p in self.inner.channel() if x == self.default and p > 0]
        total, steps = 0.0, []
        for y, p in law[:-1]:
            total += p
            steps.append(f"WHEN {g} < {math.floor(total * (1 << 52))} THEN {y}")
        return f"CASE {' '.join(steps)} ELSE {law[-1][0]} END"

    def accept_probability(self, given: int, output: int) -> float:
        """Half the likelihood ratio, or a half where it leaves e^(+-2 eps)."""
        base = self.inner.likelihood(output, self.default)
        p = math.inf if base == 0 else self.inner.likelihood(output, given) / base / 2
        return p if math.exp(-2 * self.inner.eps) / 2 <= p <= math.exp(2 * self.inner.eps) / 2 else 0.5

    def in_band(self, given: int, output: int) -> bool:
        base = self.inner.likelihood(output, self.default)
        ratio = math.inf if base == 0 else self.inner.likelihood(output, given) / base
        return math.exp(-2 * self.inner.eps) <= ratio <= math.exp(2 * self.inner.eps)

    def accepted(self, d: Dialect, item: str, user: str) -> str:
        """Places (from 0) whose coin accepts; all places, if none does."""
        inputs, outputs = sorted({c[0] for c in self.inner.channel()}), sorted({c[1] for c in self.inner.channel() if c[0] == self.default and c[2] > 0})
        cases = " ".join(f"WHEN {item} = {x} AND y = {y} THEN {math.floor(self.accept_probability(x, y) * (1 << 52))}" for x in inputs for y in outputs)
        coin = d.digits(d.digest(self.role + "-coin", self.seed, user, "t"), 1, 13)
        y = self.sample(d, user, "t")
        limit = f"CASE {cases.replace(' y = ', f' ({y}) = ')} ELSE {1 << 51} END"
        if d.duck:
            every = f"generate_series(0, {self.t - 1})"
            kept = f"list_filter({every}, lambda t: {coin} < {limit})"
            return f"CASE WHEN len({kept}) = 0 THEN {every} ELSE {kept} END"
        every = f"sequence(CAST(0 AS BIGINT), CAST({self.t - 1} AS BIGINT))"
        kept = f"filter({every}, t -> {coin} < {limit})"
        return f"element_at(transform(array({kept}), k -> CASE WHEN size(k) = 0 THEN {every} ELSE k END), 1)"

    def pick(self, d: Dialect, places: str, user: str) -> str:
        g = d.digits(d.digest(self.role + "-pick", self.seed, user), 1, 13)
        return f"list_extract({places}, CAST({g} % len({places}) + 1 AS INTEGER))" if d.duck else f"element_at({places}, CAST({g} % size({places}) + 1 AS INT))"

    def reports(self, users: DataFrame) -> DataFrame:
        """user, g: ceil(log2 t) bits a user."""
        held = users.select("user", F.expr(self.accepted(SPARK, "item", "user")).alias("places"))
        return held.select("user", F.expr(self.pick(SPARK, "places", "user")).alias("g"))

    def reports_sql(self, view: str) -> str:
        from ldpspark.functions.dialect import DUCK

        return f'SELECT "user", {self.pick(DUCK, "places", chr(34) + "user" + chr(34))} AS g FROM (SELECT "user", {self.accepted(DUCK, "item", chr(34) + "user" + chr(34))} AS places FROM ({view}))'

    def reconstruct(self, reports: DataFrame) -> DataFrame:
        """user, report: the public sample at the reported place, from the seed alone."""
        return reports.select("user", F.expr(self.sample(SPARK, "user", "g")).alias("report"))

    def reconstruct_sql(self, view: str) -> str:
        from ldpspark.functions.dialect import DUCK

        return f'SELECT "user", {self.sample(DUCK, chr(34) + "user" + chr(34), "g")} AS report FROM ({self.reports_sql(view)})'

    def samples(self, users: DataFrame) -> DataFrame:
        """user, t, y: all public samples, for tests and audits."""
        long = users.select("user", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(self.t - 1).cast("long"))).alias("t"))
        return long.select("user", "t", F.expr(self.sample(SPARK, "user", "t")).alias("y"))

    def samples_sql(self, view: str) -> str:
        from ldpspark.functions.dialect import DUCK

        q = '"user"'
        return f"SELECT {q}, t, {self.sample(DUCK, q, 't')} AS y FROM (SELECT {q}, unnest(generate_series(0, {self.t - 1})) AS t FROM ({view}))"

    def bits(self) -> int:
        return max(1, math.ceil(math.log2(self.t)))


@dataclass(frozen=True)
class OneBit:
    """Accept or reject a single public sample; the server keeps the samples of users who accept, about half of them."""

    inner: Randomizer
    seed: int = 1
    default: int = 0
    role: str = "onebit"

    @property
    def _one(self) -> RejectionPurifier:
        return RejectionPurifier(self.inner, 1, self.seed, self.default, self.role)

    def texts(self, d: Dialect, item: str, user: str) -> tuple[str, str]:
        y = self._one.sample(d, user, "0")
        coin = d.digits(d.digest(self.role + "-coin", self.seed, user), 1, 13)
        pairs = [(x, o) for x in sorted({c[0] for c in self.inner.channel()}) for o in sorted({c[1] for c in self.inner.channel() if c[2] > 0})]
        cases = " ".join(f"WHEN {item} = {x} AND ({y}) = {o} THEN {math.floor(self._one.accept_probability(x, o) * (1 << 52))}" for x, o in pairs)
        return y, f"CASE WHEN {coin} < CASE {cases} ELSE {1 << 51} END THEN 1 ELSE 0 END"

    def reports(self, users: DataFrame) -> DataFrame:
        """user, y (public, derived), accept (the one bit sent)."""
        y, a = self.texts(SPARK, "item", "user")
        return users.select("user", F.expr(y).alias("y"), F.expr(a).alias("accept"))

    def reports_sql(self, view: str) -> str:
        from ldpspark.functions.dialect import DUCK

        y, a = self.texts(DUCK, "item", '"user"')
        return f'SELECT "user", {y} AS y, {a} AS accept FROM ({view})'
