"""SQL text for the few functions whose names differ between Spark and DuckDB, and keyed randomness.

Expressions of the client side are rendered once for each engine, so that a result can be checked bit by bit. All coins
are keyed: digits of md5 over role, seed and user. A retried task gives the same report again, which is also what
privacy needs; no expression uses a generator with hidden state.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

#: Limbs of items below 2^62, and the field of the linear hash: the largest prime below 2^32. Limbs are members of it, so
#: no two items fall together, and the product of a member and a limb stays below 2^63.
LIMB, PRIME = 1 << 31, (1 << 32) - 5
#: Field of the polynomial hash: the least prime above 2^62. All items are members; products have at most 38 digits.
FIELD = (1 << 62) + 135


@dataclass(frozen=True)
class Dialect:
    duck: bool

    def digest(self, role: str, seed: int, *keys: str) -> str:
        """md5 digits over the colon-joined role, seed and keys (SQL texts)."""
        return f"md5(concat_ws(':', '{role}', '{seed}', {', '.join(self.text(k) for k in keys)}))"

    def text(self, x: str) -> str:
        return f"CAST({x} AS {'VARCHAR' if self.duck else 'STRING'})"

    def digits(self, digest: str, first: int, n: int) -> str:
        """Digits ``first`` (from 1) and on of a digest, ``n`` of them (at most 15), as a number."""
        return f"CAST('0x' || substr({digest}, {first}, {n}) AS BIGINT)" if self.duck else f"CAST(conv(substr({digest}, {first}, {n}), 16, 10) AS BIGINT)"

    def below(self, digest: str, first: int, probability: float) -> str:
        """A coin: 13 digits from ``first`` on are below ``probability``; whole numbers only, so both engines agree."""
        return f"({self.digits(digest, first, 13)} < {math.floor(probability * (1 << 52))})"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) // ({b}))" if self.duck else f"(({a}) div ({b}))"

    def at(self, values: list, place: str) -> str:
        """Member of a literal list at a place from 0."""
        inner = ", ".join(f"CAST({v} AS BIGINT)" for v in values) if values and isinstance(values[0], int) else ", ".join(map(str, values))
        return f"list_extract([{inner}], CAST(({place}) + 1 AS INTEGER))" if self.duck else f"element_at(array({inner}), CAST(({place}) + 1 AS INT))"

    def sign(self, row: str, value: str) -> str:
        """Entry (row, value) of the Hadamard matrix: +1 or -1."""
        return f"(1 - 2 * CAST(bit_count(CAST({row} AS BIGINT) & CAST({value} AS BIGINT)) % 2 AS BIGINT))"

    def parity(self, a: str, b: str) -> str:
        return f"CAST(bit_count(CAST({a} AS BIGINT) & CAST({b} AS BIGINT)) % 2 AS BIGINT)"

    def explode(self, lo: str, hi: str) -> str:
        return f"unnest(generate_series({lo}, {hi}))" if self.duck else f"explode(sequence({lo}, {hi}))"


SPARK, DUCK = Dialect(False), Dialect(True)


def coefficients(role: str, seed: int, n: int, field: int = PRIME) -> list[int]:
    """``n`` field members from md5 of role, seed and place."""
    import hashlib

    return [int(hashlib.md5(f"{role}:{seed}:{i}".encode()).hexdigest(), 16) % field for i in range(n)]


def linear(d: Dialect, item: str, a0: str, a1: str, b: str) -> str:
    """Pairwise independent hash of a 62-bit item to the field: a0 * low limb + a1 * high limb + b."""
    return f"((({a0}) * (({item}) % {LIMB})) % {PRIME} + (({a1}) * {d.div(item, str(LIMB))}) % {PRIME} + ({b})) % {PRIME}"


def polynomial(d: Dialect, item: str, coefs: list[int]) -> str:
    """Horner's rule in ``FIELD``: as many-wise independent over all items below 2^62 as there are coefficients.

    Decimals hold the products exactly and, unlike limbs, name each step once, so the text grows with the coefficients.
    """
    if d.duck:
        out = f"CAST({coefs[0]} AS HUGEINT)"
        for c in coefs[1:]:
            out = f"(({out} * CAST({item} AS HUGEINT) + CAST({c} AS HUGEINT)) % CAST({FIELD} AS HUGEINT))"
    else:
        whole = lambda x: f"CAST({x} AS DECIMAL(19,0))"
        out = whole(coefs[0])
        for c in coefs[1:]:
            out = whole(f"(({out} * {whole(item)} + {whole(c)}) % {whole(FIELD)})")
    return f"CAST({out} AS BIGINT)"


def linear_value(item: int, a0: int, a1: int, b: int) -> int:
    return ((a0 * (item % LIMB)) % PRIME + (a1 * (item // LIMB)) % PRIME + b) % PRIME


def polynomial_value(item: int, coefs: list[int]) -> int:
    out = coefs[0]
    for c in coefs[1:]:
        out = (out * item + c) % FIELD
    return out
