"""Decoding the lists (b, m, y, z, est) of a bucket into items."""

from __future__ import annotations

from collections import defaultdict

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.functions.dialect import SPARK

from .code import ExpanderCode

Vertex = tuple[int, int]


def cap_lists(winners: DataFrame, cap: int) -> DataFrame:
    """The ``cap`` best of each (b, m) by estimate, ties to the smaller y: free of order, and never cap + 1."""
    rank = F.row_number().over(Window.partitionBy("b", "m").orderBy(F.desc("est"), "y"))
    return winners.withColumn("rank", rank).filter(F.col("rank") <= cap).drop("rank")


def unique_y(lists: DataFrame) -> DataFrame:
    """(b, m, y) that a list holds more than once: none in valid lists."""
    return lists.groupBy("b", "m", "y").agg(F.count("*").alias("held")).filter("held > 1")


def requests(lists: DataFrame, code: ExpanderCode) -> DataFrame:
    """(b, m, y, to_m, to_y): what each list entry asks of its neighbours."""
    near = F.array(*[F.array(*[F.lit(int(k)) for k in x]) for x in code.near])
    asked = lists.select("b", "m", "y", "z", F.posexplode(near[F.col("m").cast("int")]).alias("k", "to_m"))
    shift = (F.lit(code.d - 1) - F.col("k")) * code.y_bits
    to_y = F.expr(f"shiftright(z, cast(({code.d - 1} - k) * {code.y_bits} as int)) & {(1 << code.y_bits) - 1}")
    return asked.withColumn("s", shift).select("b", "m", "y", F.col("to_m").cast("long").alias("to_m"), to_y.alias("to_y"))


def layered_edges(lists: DataFrame, code: ExpanderCode) -> DataFrame:
    """(b, m1, y1, m2, y2) with m1 < m2: edges that both of their ends ask for."""
    asked = requests(lists, code)
    back = asked.select("b", F.col("to_m").alias("m"), F.col("to_y").alias("y"), F.col("m").alias("to_m"), F.col("y").alias("to_y"))
    both = asked.join(back, ["b", "m", "y", "to_m", "to_y"]).filter("m < to_m").distinct()
    return both.select("b", F.col("m").alias("m1"), F.col("y").alias("y1"), F.col("to_m").alias("m2"), F.col("to_y").alias("y2"))


def ghost_edges(lists: DataFrame, code: ExpanderCode) -> DataFrame:
    """Pairs of entries that ask for the same entry, which is missing from its list."""
    asked, held = requests(lists, code), lists.select("b", F.col("m").alias("to_m"), F.col("y").alias("to_y"))
    ghost = asked.join(held, ["b", "to_m", "to_y"], "left_anti")
    a, b = ghost.alias("p"), ghost.alias("q")
    met = a.join(b, (F.col("p.b") == F.col("q.b")) & (F.col("p.to_m") == F.col("q.to_m")) & (F.col("p.to_y") == F.col("q.to_y")) & (F.col("p.m") < F.col("q.m")))
    return met.select(F.col("p.b").alias("b"), F.col("p.m").alias("m1"), F.col("p.y").alias("y1"), F.col("q.m").alias("m2"), F.col("q.y").alias("y2")).distinct()


def components(lists: DataFrame, edges: DataFrame, code: ExpanderCode) -> DataFrame:
    """(b, m, y, label): least vertex number m * Y + y of the component of each list entry, bucket by bucket.

    A bucket holds at most m * cap entries, so one task finds its components.
    """
    import pandas as pd

    def bucket(nodes: pd.DataFrame, links: pd.DataFrame) -> pd.DataFrame:
        v = (nodes["m"] * (1 << code.y_bits) + nodes["y"]).tolist()
        root = {x: x for x in v}

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = x = root[root[x]]
            return x

        for a, c in zip((links["m1"] * (1 << code.y_bits) + links["y1"]).tolist(), (links["m2"] * (1 << code.y_bits) + links["y2"]).tolist(), strict=True):
            p, q = find(a), find(c)
            root[max(p, q)] = min(p, q)
        return nodes[["b", "m", "y"]].assign(label=[find(x) for x in v])

    return lists.select("b", "m", "y").groupBy("b").cogroup(edges.select(F.col("b").alias("eb"), "m1", "y1", "m2", "y2").groupBy("eb")).applyInPandas(bucket, "b bigint, m bigint, y bigint, label bigint")


def components_by_rounds(lists: DataFrame, edges: DataFrame, code: ExpanderCode, store) -> DataFrame:
    """The same by rounds of joins, for graphs beyond one task's memory; ``store`` cuts the lineage of each round."""
    number = lambda m, y: F.col(m) * (1 << code.y_bits) + F.col(y)
    nodes = store(lists.select("b", "m", "y", number("m", "y").alias("v")).withColumn("label", F.col("v")))
    pairs = edges.select("b", number("m1", "y1").alias("u"), number("m2", "y2").alias("v"))
    pairs = store(pairs.union(pairs.select("b", F.col("v").alias("u"), F.col("u").alias("v"))))
    while True:
        best = pairs.join(nodes.select("b", F.col("v").alias("u"), "label"), ["b", "u"]).groupBy("b", "v").agg(F.min("label").alias("best"))
        new = nodes.join(best, ["b", "v"], "left").select("b", "m", "y", "v", F.least("label", F.coalesce("best", "label")).alias("label"), (F.col("best") < F.col("label")).alias("moved"))
        new = store(new)
        nodes = new.drop("moved")
        if not new.filter("moved").limit(1).count():
            return nodes.select("b", "m", "y", "label")


def prune_low_degree(lists: DataFrame, edges: DataFrame, d: int) -> DataFrame:
    """List entries with more than d / 2 edges."""
    ends = edges.select("b", F.col("m1").alias("m"), F.col("y1").alias("y")).union(edges.select("b", "m2", "y2"))
    enough = ends.groupBy("b", "m", "y").agg(F.count("*").alias("degree")).filter(F.col("degree") * 2 > d)
    return lists.join(enough.select("b", "m", "y"), ["b", "m", "y"], "left_semi")


def verify(candidates: DataFrame, lists: DataFrame, code: ExpanderCode, agree: int) -> DataFrame:
    """(b, item, agree): candidates whose own code words stand in at least ``agree`` lists of their bucket."""
    words = candidates.withColumn("m", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(code.m - 1).cast("long"))))
    words = words.select("b", "item", "m", F.expr(code.y_text(SPARK, "item", "m")).alias("y"), F.expr(code.z_text(SPARK, "item", "m")).alias("z"))
    met = words.join(lists.select("b", "m", "y", "z"), ["b", "m", "y", "z"])
    return met.groupBy("b", "item").agg(F.count("*").alias("agree")).filter(F.col("agree") >= agree)


def brute_force(lists: DataFrame, domain: DataFrame, code: ExpanderCode, agree: int) -> DataFrame:
    """Every item of a small domain tried in every bucket."""
    return verify(lists.select("b").distinct().crossJoin(F.broadcast(domain.select("item"))), lists, code, agree)


class Bucket:
    """Decoder of one bucket's lists, in memory: at most m * cap entries."""

    def __init__(self, code: ExpanderCode, entries: list[tuple[int, int, int]], ghosts: bool = True):
        self.code, self.z = code, {(m, y): z for m, y, z in entries}
        self.symbol: dict[Vertex, int] = {}
        asks: dict[Vertex, list[Vertex]] = {}
        for v, z in self.z.items():
            self.symbol[v], ys = code.split(z)
            asks[v] = list(zip(code.near[v[0]], ys, strict=True))
        self.near: dict[Vertex, set[Vertex]] = {v: set() for v in self.z}
        missing = defaultdict(list)
        for v, out in asks.items():
            for u in out:
                if u not in self.z:
                    missing[u].append(v)
                elif v in asks[u]:
                    self.near[v].add(u)
                    self.near[u].add(v)
        if ghosts:
            for members in missing.values():
                for v in members:
                    for u in members:
                        if u[0] != v[0]:
                            self.near[v].add(u)

    def components(self) -> list[set[Vertex]]:
        seen: set[Vertex] = set()
        out = []
        for v in sorted(self.z):
            if v in seen:
                continue
            part, todo = {v}, [v]
            while todo:
                for u in self.near[todo.pop()] - part:
                    part.add(u)
                    todo.append(u)
            seen |= part
            out.append(part)
        return out

    def sweep(self, part: set[Vertex], most: float = 0.35) -> list[set[Vertex]]:
        """Parts of a component along its second eigenvector, while a cut of conductance up to ``most`` splits it."""
        nodes = sorted(part)
        if len(nodes) < 4:
            return [part]
        place = {v: i for i, v in enumerate(nodes)}
        a = np.zeros((len(nodes), len(nodes)))
        for v in nodes:
            for u in self.near[v] & part:
                a[place[v], place[u]] = 1
        degree = np.maximum(a.sum(axis=1), 1e-9)
        _, vectors = np.linalg.eigh(np.eye(len(nodes)) - a / np.sqrt(degree[:, None] * degree[None, :]))
        order = np.argsort(vectors[:, 1] / np.sqrt(degree), kind="stable")
        best, at, inside = np.inf, 0, np.zeros(len(nodes), bool)
        for k, i in enumerate(order[:-1], 1):
            inside[i] = True
            cut = a[inside][:, ~inside].sum()
            value = cut / min(degree[inside].sum(), degree[~inside].sum())
            if value < best:
                best, at = value, k
        if best > most:
            return [part]
        left = {nodes[i] for i in order[:at]}
        return self.sweep(left, most) + self.sweep(part - left, most)

    def conflicts(self, part: set[Vertex]) -> bool:
        return len({m for m, _ in part}) < len(part)

    def one_a_layer(self, part: set[Vertex]) -> list[set[Vertex]]:
        """Where layers hold several vertices: grown from each vertex of the fullest layer, taking the best joined ones."""
        layers = defaultdict(list)
        for v in part:
            layers[v[0]].append(v)
        start = max(layers.values(), key=len)
        out = []
        for v in start:
            own = {v}
            while True:
                free = [u for u in part if u[0] not in {m for m, _ in own} and self.near[u] & own]
                if not free:
                    break
                own.add(max(free, key=lambda u: (len(self.near[u] & own), -len(self.near[u]), (-u[0], -u[1]))))
            out.append(own)
        return out

    def prune(self, part: set[Vertex]) -> set[Vertex]:
        return {v for v in part if 2 * len(self.near[v] & part) > self.code.d}

    def attempts(self, spectral: bool = True) -> list[set[Vertex]]:
        out = []
        for part in self.components():
            pieces = [part]
            if self.conflicts(part):
                pieces = (self.sweep(part) if spectral else []) + self.one_a_layer(part)
            for p in pieces:
                for q in [p] if not self.conflicts(p) else self.one_a_layer(p):
                    out += [q, self.prune(q)]
        return out

    def decode(self, agree: int, spectral: bool = True) -> dict[int, int]:
        """item: number of agreeing lists, of all attempts that pass."""
        found: dict[int, int] = {}
        for part in self.attempts(spectral):
            if len(part) < self.code.dim:
                continue
            word: list[int | None] = [None] * self.code.m
            for v in part:
                word[v[0]] = self.symbol[v]
            item = self.code.rs.decode(word)
            if item is None or item in found or item >> self.code.bits:
                continue
            n = sum(self.z.get((m, y)) == z for m, (y, z) in enumerate(self.code.encode(item)))
            if n >= agree:
                found[item] = n
        return found


def decode(lists: DataFrame, code: ExpanderCode, agree: int, ghosts: bool = True, spectral: bool = True) -> DataFrame:
    """(b, item, agree), one task a bucket."""
    import pandas as pd

    def bucket(g: pd.DataFrame) -> pd.DataFrame:
        rows = list(zip(g["m"].tolist(), g["y"].tolist(), g["z"].tolist(), strict=True))
        found = Bucket(code, rows, ghosts).decode(agree, spectral)
        return pd.DataFrame({"b": pd.Series([int(g["b"].iloc[0])] * len(found), dtype="int64"), "item": pd.Series(list(found), dtype="int64"), "agree": pd.Series(list(found.values()), dtype="int64")})

    return lists.select("b", "m", "y", "z").groupBy("b").applyInPandas(bucket, "b bigint, item bigint, agree bigint")
