"""Blocks, shards, lengths and repeats of the exact search against brute force."""

import math
import random

import pytest
from pyspark.sql import functions as F

from ldpspark.llm import topk


def brute(rows, k, queries):
    good = [(i, tuple(math.floor(64 * x) for x in v)) for i, v in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    raw = {}
    for i, v in rows:
        if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v) and queries(i):
            raw[i] = min(raw.get(i, v), v)
    out = []
    for q, v in raw.items():
        own = [math.floor(64 * x) for x in v]
        found = sorted((-sum(a * b for a, b in zip(own, c, strict=True)), i) for i, c in good if i != q and len(c) == len(own))[:k]
        out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(found)]
    return sorted(out)


@pytest.mark.parametrize("block,shard", [(1 << 20, 1 << 26), (200, 300), (64, 100_000)])
def test_blocks_and_shards_against_brute_force(spark, block, shard):
    rng = random.Random(block)
    rows = [(i, [rng.uniform(-1, 1) for _ in range(3)]) for i in range(120)] + [(i, [0.5, 0.5, 0.25]) for i in (7, 7, 7, 300, 301, 301)] + [(20, [0.25, 0.5, -1.0])]
    rows += [(500 + i, [rng.uniform(-1, 1) for _ in range(5)]) for i in range(30)] + [(None, [1.0, 1.0, 1.0]), (40, None), (600, [None, 1.0, 0.0]), (620, [float("nan")] * 3), (640, [float("inf"), 0.0, 0.0]), (660, [])]
    rows += [(9, [0.9, 0.9, 0.9])] * 40
    df = spark.createDataFrame([(i, v, 1, 2, [0.0]) for i, v in rows], "vec_id long, embedding array<double>, shard int, n int, v array<double>")
    got = topk.search(df, F.col("vec_id") % 20 == 0, k=6, block_bytes=block, shard_bytes=shard, least_bytes=50, fan_in=2)
    assert sorted(tuple(r) for r in got.collect()) == brute(rows, 6, lambda i: i % 20 == 0)
