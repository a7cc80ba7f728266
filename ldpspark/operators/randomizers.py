"""Local randomizers: sampling expressions, likelihoods and channel tables.

``report(d, item, user)`` is the SQL text that draws a user's output; ``channel()`` lists (input, output, probability).
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ldpspark.functions.dialect import Dialect


@dataclass(frozen=True)
class Randomizer:
    eps: float
    seed: int = 1
    role: str = "rnd"

    def channel(self) -> list[tuple[int, int, float]]:
        raise NotImplementedError

    def report(self, d: Dialect, item: str, user: str) -> str:
        raise NotImplementedError

    def likelihood(self, output: int, given: int) -> float:
        return sum(p for x, y, p in self.channel() if x == given and y == output)

    def channel_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(x, y, float(p)) for x, y, p in self.channel()], "input int, output int, prob double")

    def pure_epsilon(self) -> float:
        """Largest log-ratio of the channel; infinite if an output is possible for some inputs only."""
        worst = 0.0
        for y in {c[1] for c in self.channel()}:
            p = [self.likelihood(y, x) for x in {c[0] for c in self.channel()}]
            if max(p) > 0:
                worst = max(worst, math.inf if min(p) == 0 else math.log(max(p) / min(p)))
        return worst


@dataclass(frozen=True)
class BitFlip(Randomizer):
    """The bit with probability e^eps / (e^eps + 1), else its opposite."""

    role: str = "bit"

    @property
    def keep(self) -> float:
        return math.exp(self.eps) / (math.exp(self.eps) + 1)

    def channel(self):
        p = self.keep
        return [(0, 0, p), (0, 1, 1 - p), (1, 0, 1 - p), (1, 1, p)]

    def report(self, d, item, user):
        return f"(CASE WHEN {d.below(d.digest(self.role, self.seed, user), 1, self.keep)} THEN {item} ELSE 1 - {item} END)"


@dataclass(frozen=True)
class VectorFlip(Randomizer):
    """Every one of ``k`` bits of a mask flipped on its own with probability 1 / (e^eps + 1)."""

    k: int = 4
    role: str = "vec"

    @property
    def keep(self) -> float:
        return math.exp(self.eps) / (math.exp(self.eps) + 1)

    def channel(self):
        q, full = 1 - self.keep, range(1 << self.k)
        return [(x, y, q ** (x ^ y).bit_count() * (1 - q) ** (self.k - (x ^ y).bit_count())) for x in full for y in full]

    def flips(self, d: Dialect, user: str) -> list[str]:
        """0/1 texts of the flips: four coins of eight digits from each digest."""
        limit = math.floor((1 - self.keep) * (1 << 32))
        return [f"CASE WHEN {d.digits(d.digest(f'{self.role}{i // 4}', self.seed, user), 1 + 8 * (i % 4), 8)} < {limit} THEN {1 << i} ELSE 0 END" for i in range(self.k)]

    def report(self, d, item, user):
        mask = "CAST(" + " + ".join(self.flips(d, user)) + " AS BIGINT)"
        return f"xor(CAST({item} AS BIGINT), {mask})" if d.duck else f"(CAST({item} AS BIGINT) ^ {mask})"


@dataclass(frozen=True)
class KaryResponse(Randomizer):
    """One of ``k`` values: the true one with probability e^eps / (e^eps + k - 1), else one of the others."""

    k: int = 4
    role: str = "kary"

    @property
    def keep(self) -> float:
        return math.exp(self.eps) / (math.exp(self.eps) + self.k - 1)

    def channel(self):
        other = (1 - self.keep) / (self.k - 1)
        return [(x, y, self.keep if x == y else other) for x in range(self.k) for y in range(self.k)]

    def report(self, d, item, user):
        g = d.digest(self.role, self.seed, user)
        return f"(CASE WHEN {d.below(g, 1, self.keep)} THEN {item} ELSE ({item} + 1 + {d.digits(g, 14, 8)} % {self.k - 1}) % {self.k} END)"


@dataclass(frozen=True)
class LeakyBit(Randomizer):
    """:class:`BitFlip` that with probability ``delta`` tells the bit itself (outputs 2 and 3): not private at any eps."""

    delta: float = 0.01
    role: str = "leak"

    def channel(self):
        p = math.exp(self.eps) / (math.exp(self.eps) + 1)
        out = []
        for x in (0, 1):
            out += [(x, y, (1 - self.delta) * (p if x == y else 1 - p)) for y in (0, 1)]
            out += [(x, 2 + y, self.delta if x == y else 0.0) for y in (0, 1)]
        return out

    def report(self, d, item, user):
        g, p = d.digest(self.role, self.seed, user), math.exp(self.eps) / (math.exp(self.eps) + 1)
        return f"(CASE WHEN {d.below(g, 1, self.delta)} THEN 2 + {item} WHEN {d.below(g, 14, p)} THEN {item} ELSE 1 - {item} END)"


@dataclass(frozen=True)
class GridGaussianBit(Randomizer):
    """Bit plus Gaussian noise of ``sigma``, held to a grid of ``2 * reach + 2`` whole points: private with a delta only."""

    sigma: float = 2.0
    reach: int = 6
    role: str = "grid"

    def channel(self):
        out = []
        for x in (0, 1):
            w = [math.exp(-((y - x) ** 2) / (2 * self.sigma**2)) for y in range(-self.reach, self.reach + 2)]
            out += [(x, y, v / sum(w)) for y, v in zip(range(-self.reach, self.reach + 2), w, strict=True)]
        return out

    def report(self, d, item, user):
        g = d.digits(d.digest(self.role, self.seed, user), 1, 13)
        cases = []
        for x in (0, 1):
            total, steps = 0.0, []
            for _, y, p in [c for c in self.channel() if c[0] == x]:
                total += p
                steps.append(f"WHEN {g} < {math.floor(total * (1 << 52))} THEN {y}")
            cases.append(f"WHEN {item} = {x} THEN CASE {' '.join(steps)} ELSE {self.reach + 1} END")
        return f"(CASE {' '.join(cases)} END)"


def unbias(eps: float) -> float:
    """Factor of a one-bit report's sign: (e^eps + 1) / (e^eps - 1)."""
    return (math.exp(eps) + 1) / (math.exp(eps) - 1)
