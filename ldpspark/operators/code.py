"""Unique-list-recoverable code: Reed-Solomon symbols, public hashes and an expander that stitches coordinates."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np

from ldpspark.functions.dialect import Dialect, coefficients, linear, linear_value

#: Irreducible polynomials of GF(2^s).
FIELDS = {2: 0b111, 3: 0b1011, 4: 0b10011, 5: 0b100101, 6: 0b1000011, 7: 0b10001001, 8: 0b100011101}


class Field:
    """GF(2^s) by logarithms."""

    def __init__(self, s: int):
        self.s, self.size = s, 1 << s
        self.exp, self.log = [0] * (2 * self.size), [0] * self.size
        x = 1
        for i in range(self.size - 1):
            self.exp[i], self.log[x] = x, i
            x <<= 1
            if x & self.size:
                x ^= FIELDS[s]
        for i in range(self.size - 1, 2 * self.size):
            self.exp[i] = self.exp[i - (self.size - 1)]

    def mul(self, a: int, b: int) -> int:
        return self.exp[self.log[a] + self.log[b]] if a and b else 0

    def inv(self, a: int) -> int:
        return self.exp[self.size - 1 - self.log[a]]

    def pow(self, a: int, n: int) -> int:
        return 1 if n == 0 else 0 if a == 0 else self.exp[self.log[a] * n % (self.size - 1)]

    def solve(self, rows: list[list[int]], rhs: list[int]) -> list[int] | None:
        """A solution of a linear system (free unknowns 0), or None."""
        m = [r[:] + [b] for r, b in zip(rows, rhs, strict=True)]
        n, pivots, at = len(rows[0]), [], 0
        for col in range(n):
            k = next((i for i in range(at, len(m)) if m[i][col]), None)
            if k is None:
                continue
            m[at], m[k] = m[k], m[at]
            f = self.inv(m[at][col])
            m[at] = [self.mul(f, x) for x in m[at]]
            for i in range(len(m)):
                if i != at and m[i][col]:
                    f = m[i][col]
                    m[i] = [x ^ self.mul(f, y) for x, y in zip(m[i], m[at], strict=True)]
            pivots.append(col)
            at += 1
        if any(r[-1] and not any(r[:-1]) for r in m):
            return None
        out = [0] * n
        for i, col in enumerate(pivots):
            out[col] = m[i][-1]
        return out


@dataclass(frozen=True)
class ReedSolomon:
    """Length ``m``, ``dim`` symbols of ``s`` bits: the item's symbols are a polynomial's coefficients."""

    s: int
    m: int
    dim: int

    @cached_property
    def field(self) -> Field:
        return Field(self.s)

    def point(self, m: int) -> int:
        return self.field.exp[m]

    def encode(self, item: int) -> list[int]:
        f, mask = self.field, (1 << self.s) - 1
        parts = [item >> self.s * i & mask for i in range(self.dim)]
        out = []
        for m in range(self.m):
            x, y = self.point(m), 0
            for c in reversed(parts):
                y = f.mul(y, x) ^ c
            out.append(y)
        return out

    def masks(self) -> list[list[int]]:
        """masks[bit][m]: the item bits whose parity is that bit of the symbol at m (the code is linear over bits)."""
        ones = [self.encode(1 << b) for b in range(self.s * self.dim)]
        return [[sum(1 << b for b, word in enumerate(ones) if word[m] >> bit & 1) for m in range(self.m)] for bit in range(self.s)]

    def decode(self, word: list[int | None]) -> int | None:
        """Item of a word with erasures (None): as many errors e as 2e + erasures <= m - dim, by a linear system."""
        f, known = self.field, [(m, y) for m, y in enumerate(word) if y is not None]
        for e in range(max(0, (len(known) - self.dim) // 2), -1, -1):
            if len(known) < self.dim + 2 * e:
                continue
            # q(x) = y * (x^e + sum of e_i x^i) at all known points
            rows = [[f.pow(self.point(m), i) for i in range(self.dim + e)] + [f.mul(y, f.pow(self.point(m), i)) for i in range(e)] for m, y in known]
            got = f.solve(rows, [f.mul(y, f.pow(self.point(m), e)) for m, y in known])
            if got is None:
                continue
            q, locator = got[: self.dim + e], got[self.dim + e :] + [1]
            parts = self._divide(q, locator)
            if parts is None:
                continue
            item = sum(c << self.s * i for i, c in enumerate(parts))
            if sum(a != b for a, (_, b) in zip([self.encode(item)[m] for m, _ in known], known, strict=True)) <= e:
                return item
        return None

    def _divide(self, q: list[int], locator: list[int]) -> list[int] | None:
        f, q, out = self.field, q[:], [0] * max(1, len(q) - len(locator) + 1)
        for i in range(len(q) - len(locator), -1, -1):
            out[i] = q[i + len(locator) - 1]
            for j, c in enumerate(locator):
                q[i + j] ^= f.mul(out[i], c)
        return None if any(q) else (out + [0] * self.dim)[: self.dim]


def second_eigenvalue(neighbours: list[list[int]]) -> float:
    n = len(neighbours)
    a = np.zeros((n, n))
    for m, near in enumerate(neighbours):
        for k in near:
            a[m, k] += 1
    return float(sorted(np.abs(np.linalg.eigvalsh((a + a.T) / 2)))[-2])


def gap_limit(m: int, d: int) -> float:
    """Second eigenvalue that a d-regular graph on m nodes is asked to stay within.

    From degree 3 on a tenth above 2 sqrt(d - 1), which random graphs meet; below, that of one cycle through all nodes, the
    best there is, which also rules out graphs in several pieces.
    """
    if d == 2:
        return max(abs(2 * math.cos(2 * math.pi * k / m)) for k in range(1, m)) + 1e-9
    return min(2.2 * math.sqrt(d - 1), d - 1e-6)


def expander(m: int, d: int, seed: int = 1, tries: int = 300, lam_max: float | None = None) -> list[list[int]]:
    """``d``-regular graph on ``m`` nodes without loops and double edges whose second eigenvalue is at most ``lam_max``.

    Random perfect matchings of stubs, drawn again until simple; of the first ``tries`` the best spectral gap is taken, and
    where that misses the limit drawing goes on, up to a hundred times as many. Circulant offsets are tried where no
    matching exists. A graph that misses the limit is never returned.
    """
    rng, best, gap, limit = np.random.default_rng(seed), None, float("inf"), gap_limit(m, d) if lam_max is None else lam_max
    for k in range(100 * tries if m * d % 2 == 0 else 0):
        if k >= tries and gap <= limit:
            break
        stubs = rng.permutation(np.repeat(np.arange(m), d)).reshape(-1, 2)
        edges = {(min(a, b), max(a, b)) for a, b in stubs.tolist()}
        if len(edges) < m * d // 2 or any(a == b for a, b in edges):
            continue
        near = [sorted({b for a, b in edges if a == k} | {a for a, b in edges if b == k}) for k in range(m)]
        value = second_eigenvalue(near)
        if value < gap - 1e-9:
            best, gap = near, value
    if best is None and d < m:
        best = [sorted({(k + o) % m for o in range(1, d // 2 + 1)} | {(k - o) % m for o in range(1, d // 2 + 1)}) for k in range(m)]
        gap = second_eigenvalue(best) if all(len(x) == d for x in best) else float("inf")
    if best is None or gap > limit:
        raise ValueError(f"no {d}-regular graph on {m} nodes with a second eigenvalue of at most {limit:.3f} found")
    return best


@dataclass(frozen=True)
class ExpanderCode:
    """Coordinates m of an item: (y, z), y a public hash, z its Reed-Solomon symbol with the hashes at m's neighbours."""

    bits: int = 24
    s: int = 8
    m: int = 7
    y_bits: int = 4
    d: int = 2
    seed: int = 3
    graph: tuple[tuple[int, ...], ...] = field(default=())

    @property
    def dim(self) -> int:
        return -(-self.bits // self.s)

    @cached_property
    def rs(self) -> ReedSolomon:
        return ReedSolomon(self.s, self.m, self.dim)

    @cached_property
    def near(self) -> list[list[int]]:
        return [list(x) for x in self.graph] or expander(self.m, self.d, self.seed)

    @cached_property
    def hashes(self) -> list[list[int]]:
        return [coefficients(f"h{k}", self.seed, self.m) for k in range(3)]

    @property
    def z_bits(self) -> int:
        return self.s + self.d * self.y_bits

    def y(self, item: int, m: int) -> int:
        return linear_value(item, *(c[m] for c in self.hashes)) % (1 << self.y_bits)

    def encode(self, item: int) -> list[tuple[int, int]]:
        ys, word = [self.y(item, m) for m in range(self.m)], self.rs.encode(item)
        out = []
        for m in range(self.m):
            z = word[m]
            for k in self.near[m]:
                z = z << self.y_bits | ys[k]
            out.append((ys[m], z))
        return out

    def split(self, z: int) -> tuple[int, list[int]]:
        """Symbol and neighbour hashes of a z."""
        mask, near = (1 << self.y_bits) - 1, []
        for _ in range(self.d):
            near.append(z & mask)
            z >>= self.y_bits
        return z, near[::-1]

    def y_text(self, d: Dialect, item: str, m: str, places: list[int] | None = None) -> str:
        """SQL text of the hash at coordinate ``m``, or at ``places[m]``."""
        a0, a1, b = (d.at([c[k] for k in (places or range(self.m))], m) for c in self.hashes)
        return f"(({linear(d, item, a0, a1, b)}) % {1 << self.y_bits})"

    def z_text(self, d: Dialect, item: str, m: str) -> str:
        """SQL text of z: one parity of masked item bits for each bit of the symbol, then the neighbours' hashes."""
        symbol = " + ".join(f"{1 << bit} * {d.parity(d.at(masks, m), item)}" for bit, masks in enumerate(self.rs.masks()))
        out = f"({symbol})"
        for k in range(self.d):
            out = f"({out} * {1 << self.y_bits} + {self.y_text(d, item, m, [self.near[i][k] for i in range(self.m)])})"
        return out


def boundary(near: list[list[int]], inside: set[int]) -> int:
    """Edges that leave a set of nodes."""
    return sum(k not in inside for m in inside for k in near[m])


def boundary_bound(near: list[list[int]], inside: set[int]) -> float:
    """Most edges that a d-regular graph with this second eigenvalue keeps within a set: (d/n + lambda/|S|) |S|^2 / 2."""
    n, d, s = len(near), len(near[0]), len(inside)
    return (d * s / n + second_eigenvalue(near) * (1 - s / n)) * s


def cluster_eta(edges: list[tuple[int, int]], inside: list[int]) -> tuple[float, float]:
    """(leaving, cut): the least eta for which a vertex set meets each condition of a spectral cluster; their larger is its eta.

    leaving: share of its volume that leaves it. cut: over all its subsets A with volume share r, the most that
    r (1 - r) is above the share of the volume between A and the rest. All subsets are tried, so at most 20 vertices.
    """
    if len(inside) > 20:
        raise ValueError("at most 20 vertices")
    place = {v: k for k, v in enumerate(inside)}
    volume, out, within = np.zeros(len(inside)), 0, []
    for a, b in edges:
        for v in (a, b):
            if v in place:
                volume[place[v]] += 1
        out += (a in place) != (b in place)
        if a in place and b in place:
            within.append((place[a], place[b]))
    total = volume.sum()
    if not total:
        return 1.0, 0.0
    subsets = np.arange(1 << len(inside))
    bits = (subsets[:, None] >> np.arange(len(inside))) & 1
    r = bits @ volume / total
    between = sum(((bits[:, a] != bits[:, b]).astype(np.int64) for a, b in within), np.zeros(len(subsets), np.int64))
    return float(out / total), float((r * (1 - r) - between / total).max())


def is_cluster(edges: list[tuple[int, int]], inside: list[int], eta: float) -> bool:
    """Whether the vertex set is an eta-spectral cluster of the graph."""
    return max(cluster_eta(edges, inside)) <= eta + 1e-12
