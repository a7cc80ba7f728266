"""Bounds of the theory. Each is one formula text, used as a Column, as SQL and as a number.

``text`` renders names as columns or literals; ``value`` evaluates with Python's math.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Formulas in the functions that Spark, DuckDB and Python's math have in common: ln, sqrt, exp, pow, least, greatest.
FORMULAS = {
    # error of a fixed number of oracle queries, for domains larger than or as small as one likes
    "oracle_error_general": "sqrt(n * ln(w * least(n, x) / beta)) / eps",
    "oracle_error_small": "sqrt(n * ln(w / beta)) / eps",
    # worst-case error of the main algorithm, of the repeated single hash, of the oldest private one
    "main_error": "sqrt(n * ln(x / beta)) / eps",
    "single_hash_error": "sqrt(n * ln(x / beta) * ln(1 / beta)) / eps",
    "oldest_error": "pow(ln(1 / beta), 1.5) * sqrt(n * ln(x)) / eps",
    "listed_error": "sqrt(n * ln(least(n, x) / beta)) / eps",
    # lower bounds: with the failure probability, with a constant one, without an eps
    "lower_beta": "sqrt(n * ln(x / beta)) / eps",
    "lower_constant": "sqrt(n * ln(x)) / eps",
    "lower_count": "sqrt(n)",
    # groups of k users
    "group_pure": "k * eps * eps / 2 + eps * sqrt(2 * k * ln(1 / delta))",
    "group_central": "k * eps",
    "group_delta_printed": "delta + k * delta2",
    "group_delta_safe": "k * delta + delta2",
    # max-information
    "max_info_local": "n * eps * eps / 2 + eps * sqrt(2 * n * ln(1 / beta))",
    "max_info_central": "eps * n",
    "max_info_central_product": "eps * eps * n + eps * sqrt(n * ln(1 / beta))",
    "generalization": "exp(k) * p + beta",
    # k randomized responses
    "shell_eps": "6 * eps * sqrt(k * ln(1 / beta))",
    "shell_eps_safe": "6 * eps * sqrt(k * ln(2 / beta))",
    "shell_beta_limit": "pow(eps * sqrt(k) / (2 * (k + 1)), 2e0 / 3)",
    "compose_basic": "k * eps",
    "compose_advanced": "eps * sqrt(2 * k * ln(1 / delta)) + k * eps * (exp(eps) - 1)",
    # approximate to pure
    "purify_eps": "10 * eps",
    "purify_tv": "n * (pow(0.5 + eps, t) + 6 * t * delta * exp(eps) / (1 - exp(-eps)))",
    "purify_least_t": "5 * ln(1 / eps)",
    "purify_most_t": "(1 - exp(-eps)) / (4 * delta * exp(eps) * n)",
    "bad_mass": "2 * delta * exp(eps) / (1 - exp(-eps))",
    # concentration; the upper Poisson and Chernoff tails in the form that holds for all alpha up to 1
    "poisson_tail_upper": "exp(-alpha * alpha * mu / 3)",
    "poisson_tail_upper_printed": "exp(-alpha * alpha * mu / 2)",
    "poisson_tail_lower": "exp(-alpha * alpha * mu / 2)",
    "poissonize": "exp(1) * sqrt(n) * p",
    "chernoff_upper": "exp(-alpha * alpha * mu / 3)",
    "chernoff_lower": "exp(-alpha * alpha * mu / 2)",
    "independence_needed": "alpha * alpha * mu",
    "hoeffding": "2 * exp(-2 * t * t / n)",
    "bernstein_kwise": "pow(c * (sigma * sqrt(k) + t * k) / lam, k)",
    "binomial_tail_lower": "exp(-9 * t * t / (n * p))",
    "mutual_info": "eps * eps",
}


def text(name: str, **values: float | str) -> str:
    """The formula with some names replaced by numbers or other columns."""
    import re

    def put(m: re.Match) -> str:
        v = values.get(m[0])
        return m[0] if v is None else v if isinstance(v, str) else f"({v!r})"

    return re.sub(r"(?<![\w.])[a-z]\w*\b", put, FORMULAS[name])


def column(name: str, **values: float | str) -> Column:
    return F.expr(text(name, **values))


def value(name: str, **values: float) -> float:
    names = {"ln": math.log, "sqrt": math.sqrt, "exp": math.exp, "pow": math.pow, "least": min, "greatest": max}
    return float(eval(FORMULAS[name], {"__builtins__": {}}, names | values))


def poisson_binomial(ps: list[float]) -> list[float]:
    """Law of the number of successes of independent trials."""
    law = [1.0]
    for p in ps:
        law = [(law[i] if i < len(law) else 0.0) * (1 - p) + (law[i - 1] * p if i else 0.0) for i in range(len(law) + 1)]
    return law


def binomial(n: int, p: float) -> list[float]:
    if p in (0.0, 1.0):
        return [float(k == n * p) for k in range(n + 1)]
    lp, lq = math.log(p), math.log1p(-p)
    return [math.exp(math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) + k * lp + (n - k) * lq) for k in range(n + 1)]


def poisson_tail(mu: float, least: int) -> float:
    """Chance of ``least`` or more."""
    if least <= 0:
        return 1.0
    below = math.fsum(math.exp(-mu + k * math.log(mu) - math.lgamma(k + 1)) for k in range(least))
    if below < 0.5:
        return 1 - below
    return math.fsum(math.exp(-mu + k * math.log(mu) - math.lgamma(k + 1)) for k in range(least, least + 400))


def group_crossover(eps: float, delta: float) -> int:
    """Least k from which the square-root group bound is below k * eps."""
    lo, hi = 1, 1
    while value("group_pure", eps=eps, k=hi, delta=delta) >= hi * eps and hi < 1 << 60:
        hi *= 2
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if value("group_pure", eps=eps, k=mid, delta=delta) < mid * eps else (mid + 1, hi)
    return lo


def choose_t(n: int, eps: float, beta: float) -> int:
    """Samples a user needs so that the empty-set term of the purified protocol is at most beta / 2."""
    return math.ceil(max(value("purify_least_t", eps=eps), math.log(2 * n / beta) / math.log(1 / (0.5 + eps))))


def escape_exact(ps: list[float], length: int) -> float:
    """Chance that a sum of independent bits misses the best interval of ``length`` + 1 consecutive values."""
    law = poisson_binomial(ps)
    return 1 - max(math.fsum(law[i : i + length + 1]) for i in range(len(law)))


def uniform_tail(k: int, t: float) -> float:
    """Chance that a uniform k-bit string has at most k / 2 - t ones."""
    return math.fsum(math.comb(k, i) for i in range(k + 1) if i <= k / 2 - t) / 2**k


def uniform_tail_lower(k: int, t: float) -> float:
    """Anti-concentration of uniform strings in the shape exp(-9 t^2 / (n p)) of the binomial bound, p = 1/2."""
    return value("binomial_tail_lower", t=t, n=k, p=0.5)
