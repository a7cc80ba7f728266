"""Hashes over the whole domain, the split transform, verified expanders and spectral clusters."""

import random
from collections import Counter
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from ldpspark.functions import hadamard
from ldpspark.functions.dialect import DUCK, FIELD, PRIME, SPARK, coefficients, linear, linear_value, polynomial, polynomial_value
from ldpspark.operators import code
from ldpspark.operators.heavy import ExpanderHeavyHitters, SingleHash
from ldpspark.plans import planner

#: Items that fall together when limbs are folded into a field of 31 bits.
FOLDED = [0, 2**31 - 1, 2**31, 1000003, 2**31 * 5 + 7, 1000003 * 5 + 7, (2**31 - 1) * 2**31, 2**61 - 1, 2**62 - 1, 2**62 - 2]


def test_no_two_items_collide_under_every_seed(duck):
    seen = {"linear": Counter(), "polynomial": Counter()}
    for seed in range(30):
        a0, a1, b = coefficients("l", seed, 3)
        poly = coefficients("p", seed, 9, FIELD)
        for name, value in (("linear", lambda x: linear_value(x, a0, a1, b)), ("polynomial", lambda x: polynomial_value(x, poly))):
            values = [value(x) for x in FOLDED]
            seen[name].update((i, j) for i in range(len(FOLDED)) for j in range(i) if values[i] == values[j])
    assert not seen["linear"] and not seen["polynomial"]
    values = ", ".join(f"({x}::BIGINT)" for x in FOLDED)
    rows = duck.sql(f"SELECT item, {polynomial(DUCK, 'item', poly)}, {linear(DUCK, 'item', str(a0), str(a1), str(b))} FROM (VALUES {values}) AS t(item)").fetchall()
    assert all((p, v) == (polynomial_value(x, poly), linear_value(x, a0, a1, b)) for x, p, v in rows)
    assert max(FOLDED) < FIELD and 2**31 < PRIME


def test_polynomial_in_spark_stays_exact(spark):
    poly = coefficients("p", 3, planner.bucket_independence(62), FIELD)
    df = spark.createDataFrame([(x,) for x in FOLDED], "item long").select("item", F.expr(polynomial(SPARK, "item", poly)).alias("p"))
    assert all(r["p"] == polynomial_value(r["item"], poly) for r in df.collect())
    assert "Python" not in df._jdf.queryExecution().executedPlan().toString()


def test_independence_grows_with_the_domain():
    k = [planner.bucket_independence(bits) for bits in (16, 24, 32, 62)]
    assert k == sorted(set(k)) and all(x >= planner.C_G * b * np.log(2) for x, b in zip(k, (16, 24, 32, 62), strict=True))


def test_pairs_of_items_fall_evenly():
    """Pairwise independence by counting: cells of two items over many seeds."""
    for x, y in ((0, 2**31 - 1), (1000003, 2**31), (5, 2**61)):
        cells = Counter()
        for seed in range(4000):
            a0, a1, b = coefficients("even", seed, 3)
            cells[linear_value(x, a0, a1, b) % 4, linear_value(y, a0, a1, b) % 4] += 1
        assert len(cells) == 16 and max(cells.values()) < 330 and min(cells.values()) > 180


@pytest.mark.parametrize("local", [6, 11])
def test_split_winners_equal_whole_ones(spark, monkeypatch, local):
    rng = random.Random(1)
    plan = planner.plan(4000, 4.0, preset="tiny", buckets=5)
    sums = spark.createDataFrame([(m, rng.randrange(1 << plan.cell_bits), rng.choice([-60, 45, 80])) for m in range(plan.code.m) for _ in range(400)], "m long, r long, s long").groupBy("m", "r").agg(F.sum("s").alias("s"))
    h = ExpanderHeavyHitters(plan)
    whole = sorted(map(tuple, h.winners(sums, 1500.0).collect()))
    single = SingleHash(4.0, 2000, reps=2, y_bits=4, s=6, bits=18, sigmas=0.2)
    s_sums = sums.filter("m < 3").select(F.explode(F.array(F.lit(0).cast("long"), F.lit(1).cast("long"))).alias("rep"), "m", (F.col("r") % 1024).alias("r"), "s").groupBy("rep", "m", "r").agg(F.sum("s").alias("s"))
    s_whole = sorted(r[0] for r in single.candidates(s_sums).collect())
    monkeypatch.setattr(hadamard, "LOCAL_BITS", local)
    assert sorted(map(tuple, h.winners(sums, 1500.0).collect())) == whole and len(whole) > 10
    assert sorted(r[0] for r in single.candidates(s_sums).collect()) == s_whole


def test_tables_beyond_one_task_are_split(spark):
    """2^23 cells a coordinate are split, and a planted cell is found."""
    plan = replace(planner.plan(10**6, 4.0, preset="tiny"), buckets=1 << 7)
    bits = plan.cell_bits
    assert bits > hadamard.LOCAL_BITS
    cell = 123_456 % (1 << bits)
    rows = spark.range(1 << 12).select(F.lit(0).cast("long").alias("m"), ((F.col("id") * 7919 + 13) % (1 << bits)).alias("r"))
    sums = rows.select("m", "r", F.expr(f"{SPARK.sign('r', str(cell))} * 10").alias("s"))
    won = ExpanderHeavyHitters(plan).winners(sums, 10 * (1 << 12) * 0.99).collect()
    y, z = cell >> plan.code.z_bits, cell & (1 << plan.code.z_bits) - 1
    assert (y >> plan.code.y_bits, 0, y & (1 << plan.code.y_bits) - 1, z) in {(r["b"], r["m"], r["y"], r["z"]) for r in won}


def test_expander_meets_its_gap_or_is_refused():
    for m, d in ((7, 2), (7, 4), (15, 2), (15, 4), (31, 4)):
        assert code.second_eigenvalue(code.expander(m, d)) <= code.gap_limit(m, d)
    with pytest.raises(ValueError):
        code.expander(15, 4, tries=3, lam_max=0.5)
    with pytest.raises(ValueError):
        code.expander(40, 2, tries=1, lam_max=0.1)


def test_cluster_eta_of_graphs():
    full = [(a, b) for a in range(6) for b in range(a)]
    leaving, cut = code.cluster_eta(full, list(range(6)))
    assert leaving == 0 and cut <= 0.02 and code.is_cluster(full, list(range(6)), 0.05)
    two = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5)]
    assert code.cluster_eta(two, list(range(6))) == (0.0, pytest.approx(0.25)) and not code.is_cluster(two, list(range(6)), 0.1)
    assert code.cluster_eta([(0, 1), (0, 9)], [0, 1])[0] == pytest.approx(1 / 3)
    near = code.expander(15, 4)
    edges = [(a, b) for a in range(15) for b in near[a] if a < b]
    lam = code.second_eigenvalue(near)
    assert code.is_cluster(edges, list(range(15)), lam / 16)
    for bad in range(3):  # the theory's eta for lists that miss some coordinates
        left = [(a, b) for a, b in edges if min(a, b) >= bad]
        alpha = bad / 15
        assert max(code.cluster_eta(left, list(range(bad, 15)))) <= (alpha + lam / 16) / (1 - alpha)


def test_exchange_never_rises_and_ends_in_a_binomial():
    from ldpspark.operators.hard import exchange, outside, sum_law

    assert sum_law([0.5, 0.5]) == [0.25, 0.5, 0.25] and outside([0.3], 0, 0) == pytest.approx(0.3)
    rng = random.Random(8)
    for n in (1, 2, 7, 12):
        ps = [0.5 + rng.uniform(-0.2, 0.2) for _ in range(n)]
        steps = exchange(ps, 0.2, n / 2 - 1, n / 2 + 1)
        assert all(b[4] <= a[4] + 1e-12 for a, b in zip(steps, steps[1:], strict=False)) and steps[0][4] == outside(ps, n / 2 - 1, n / 2 + 1)
        left, (_, _, lo, hi, last) = (n + 1) // 2, steps[-1]
        assert hi - lo == pytest.approx(2) and min(abs(last - outside([p] * left, lo, hi)) for p in (0.3, 0.7)) < 1e-12
