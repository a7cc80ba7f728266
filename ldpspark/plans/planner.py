"""Parameters of the main algorithm: from the theory's shapes, with calibrated constants."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession

from ldpspark.functions.dialect import FIELD, Dialect, coefficients, polynomial
from ldpspark.operators.code import ExpanderCode
from ldpspark.operators.randomizers import unbias

#: name: item bits, symbol bits, coordinates, hash bits, degree.
PRESETS = {"tiny": (16, 4, 7, 4, 2), "small": (24, 8, 7, 4, 2), "medium": (32, 4, 15, 3, 4), "wide": (62, 8, 15, 4, 2)}


#: Independence of the bucket hash in natural logarithms of the domain.
C_G = 0.5


def bucket_independence(bits: int) -> int:
    return max(4, math.ceil(C_G * bits * math.log(2)))


@dataclass(frozen=True)
class ExpanderPlan:
    """All that is fixed before the first report: the protocol takes one message of each user."""

    n: int
    eps: float
    beta: float
    code: ExpanderCode
    buckets: int = 1
    #: coefficients of the bucket hash; 0: C_G times the logarithm of the domain, see ``bucket_independence``
    independence: int = 0
    #: standard deviations of a cell's noise that a listed cell must exceed
    sigmas: float = 5.0
    cap: int = 24
    agree: int = 4
    oracle_rows: int = 5
    oracle_bits: int = 10
    seed: int = 7
    share: float = 0.5

    @property
    def bucket_independence(self) -> int:
        """As many-wise independent as limited-independence tails ask for: in proportion to the domain's logarithm."""
        return self.independence or bucket_independence(self.code.bits)

    @property
    def eps_coordinate(self) -> float:
        return self.eps * self.share

    @property
    def eps_final(self) -> float:
        return self.eps * (1 - self.share)

    @property
    def bucket_bits(self) -> int:
        return max(0, (self.buckets - 1).bit_length())

    @property
    def cell_bits(self) -> int:
        return self.bucket_bits + self.code.y_bits + self.code.z_bits

    @property
    def threshold(self) -> float:
        """Least estimate of a listed cell within one coordinate's users."""
        return self.sigmas * unbias(self.eps_coordinate) * math.sqrt(self.n / self.code.m)

    @property
    def detectable(self) -> float:
        """Count from which an item passes a coordinate more often than not."""
        return self.threshold * self.code.m

    def group_text(self, d: Dialect, digest: str) -> str:
        """Coordinate group of a user."""
        return f"({d.digits(digest, 1, 8)} % {self.code.m})"

    def bucket_text(self, d: Dialect, item: str) -> str:
        """Bucket of an item: a polynomial hash of ``bucket_independence`` coefficients."""
        return "CAST(0 AS BIGINT)" if self.buckets == 1 else f"({polynomial(d, item, coefficients('bucket', self.seed, self.bucket_independence, FIELD))} % {self.buckets})"

    def cell_text(self, d: Dialect, item: str, m: str) -> str:
        return f"(({self.bucket_text(d, item)} * {1 << self.code.y_bits} + {self.code.y_text(d, item, m)}) * {1 << self.code.z_bits} + {self.code.z_text(d, item, m)})"

    def check(self) -> list[tuple[str, bool, float, float]]:
        """(condition, holds, value, limit) of the theorem's range; small tables and eps over 1 leave it."""
        w = self.code.bits
        return [
            ("eps <= 1", self.eps <= 1, self.eps, 1.0), ("beta <= 1", self.beta <= 1, self.beta, 1.0), ("n >= w / eps^2", self.n >= w / self.eps**2, float(self.n), w / self.eps**2),
            ("n >= 8 M^2 w", self.n >= 8 * self.code.m**2 * w, float(self.n), 8.0 * self.code.m**2 * w), ("n <= domain", self.n <= 2.0**w, float(self.n), 2.0**w),
            ("bucket hash >= C_g w-wise independent", self.bucket_independence >= C_G * w * math.log(2), float(self.bucket_independence), C_G * w * math.log(2)), ("items below 2^62", w <= 62, float(w), 62.0),
            ("one message of at most eps", abs(self.eps_coordinate + self.eps_final - self.eps) < 1e-12, self.eps_coordinate + self.eps_final, self.eps),
            ("list holds eps sqrt(n/w) heavy items", self.cap * self.buckets >= min(self.eps * math.sqrt(self.n / w), 1 / (self.detectable / self.n)), float(self.cap * self.buckets), 1 / (self.detectable / self.n)),
        ]

    def constants(self) -> dict[str, float]:
        """The theory's constants that the calibrated values amount to."""
        w = self.code.bits * math.log(2)
        return {"c_m": self.code.m * math.log(w) / w, "c_y": self.code.y_bits * math.log(2) / math.log(w), "c_l": self.cap / w, "c_f": self.threshold * self.eps / (math.log(w) * math.sqrt(self.n / w)), "c_h": self.detectable * self.eps / math.sqrt(self.n * w)}

    def frame(self, spark: SparkSession) -> DataFrame:
        c = self.constants()
        row = (self.n, self.eps, self.code.bits, self.code.m, self.buckets, 1 << self.code.y_bits, self.cell_bits, self.cap, float(self.threshold), float(self.detectable), *(float(c[k]) for k in ("c_m", "c_y", "c_l", "c_f", "c_h")))
        return spark.createDataFrame([row], "n long, eps double, item_bits int, m int, buckets int, y int, cell_bits int, cap int, threshold double, detectable double, c_m double, c_y double, c_l double, c_f double, c_h double")


def plan(n: int, eps: float, beta: float = 0.1, preset: str = "small", strict: bool = False, c_h: float = 1.0, **changes) -> ExpanderPlan:
    """Plan for ``n`` users: buckets grow as eps sqrt(n) / (10 c_h w^1.5); oracle width as sqrt(n)."""
    bits, s, m, y_bits, d = PRESETS[preset]
    w = bits * math.log(2)
    buckets = max(1, math.ceil(eps * math.sqrt(n) / (10 * c_h * w**1.5)))
    out = ExpanderPlan(n, eps, beta, ExpanderCode(bits, s, m, y_bits, d), buckets=buckets, oracle_bits=max(6, round(math.log2(max(2, n)) / 2) + 2))
    code = {k: changes.pop(k) for k in list(changes) if k in ("bits", "s", "m", "y_bits", "d")}
    out = replace(out, **changes, code=replace(out.code, **code)) if code else replace(out, **changes)
    if strict and not all(ok for _, ok, _, _ in out.check()):
        raise ValueError("outside the theorem's range: " + ", ".join(name for name, ok, _, _ in out.check() if not ok))
    return out
