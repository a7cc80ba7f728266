"""Exact checks on finite channels, codes and laws; no Spark."""

import itertools
import math
import random

import numpy as np
import pytest

from ldpspark.functions.hadamard import butterfly
from ldpspark.operators import audit, shell
from ldpspark.operators.code import ExpanderCode, ReedSolomon, boundary, boundary_bound, expander, second_eigenvalue
from ldpspark.operators.decode import Bucket
from ldpspark.operators.purify import OneBit, RejectionPurifier
from ldpspark.operators.randomizers import BitFlip, GridGaussianBit, KaryResponse, LeakyBit, VectorFlip, unbias
from ldpspark.plans import bounds, planner


def test_channels_sum_to_one_and_have_their_eps():
    for r, eps in [(BitFlip(math.log(3)), math.log(3)), (KaryResponse(1.0, k=5), 1.0), (VectorFlip(0.4, k=3), 1.2), (LeakyBit(0.5), math.inf), (GridGaussianBit(0.5), None)]:
        for x in {c[0] for c in r.channel()}:
            assert math.isclose(sum(p for a, _, p in r.channel() if a == x), 1)
        if eps is not None:
            assert r.pure_epsilon() == pytest.approx(eps)
    assert BitFlip(math.log(3)).keep == pytest.approx(0.75)


def test_butterfly_is_the_hadamard_matrix():
    x = np.random.default_rng(1).normal(size=16)
    h = np.array([[1 - 2 * ((r & v).bit_count() % 2) for r in range(16)] for v in range(16)])
    assert np.allclose(butterfly(x), h @ x)


def test_oracle_is_unbiased_over_coins():
    eps, item, other = 1.0, 3, 5
    total = {v: 0.0 for v in (item, other)}
    p = BitFlip(eps).keep
    for r in range(8):
        sign = 1 - 2 * ((r & item).bit_count() % 2)
        expected = sign * (2 * p - 1)
        for v in total:
            total[v] += unbias(eps) * (1 - 2 * ((r & v).bit_count() % 2)) * expected / 8
    assert total[item] == pytest.approx(1) and total[other] == pytest.approx(0)


@pytest.mark.parametrize("s,m,dim", [(8, 7, 3), (4, 15, 8), (4, 7, 4)])
def test_reed_solomon_errors_and_erasures(s, m, dim):
    rs, rng = ReedSolomon(s, m, dim), random.Random(1)
    for _ in range(60):
        item = rng.getrandbits(s * dim)
        word = rs.encode(item)
        errors = rng.randrange((m - dim) // 2 + 1)
        lost = rng.randrange(m - dim - 2 * errors + 1)
        places = rng.sample(range(m), errors + lost)
        for p in places[:errors]:
            word[p] ^= rng.randrange(1, 1 << s)
        for p in places[errors:]:
            word[p] = None
        assert rs.decode(word) == item
    for bit, masks in enumerate(rs.masks()):
        x = rng.getrandbits(s * dim)
        assert all(((x & masks[k]).bit_count() & 1) == rs.encode(x)[k] >> bit & 1 for k in range(m))


def test_expander_is_regular_and_mixes():
    near = expander(15, 4)
    assert all(len(set(x)) == 4 and m not in x for m, x in enumerate(near))
    assert second_eigenvalue(near) < 3.2
    for inside in map(set, itertools.combinations(range(7), 3)):
        g = expander(7, 4)
        assert sum(len(g[m]) for m in inside) - boundary(g, inside) <= boundary_bound(g, inside) + 1e-9


def test_every_loss_of_up_to_four_coordinates_is_recovered():
    code = ExpanderCode(m=7, d=4)
    item = 0xABCDE
    word = code.encode(item)
    for n in range(5):
        for lost in itertools.combinations(range(7), n):
            lists = [(m, y, z) for m, (y, z) in enumerate(word) if m not in lost]
            assert item in Bucket(code, lists).decode(7 - n)
    for bad in itertools.combinations(range(7), 2):
        lists = [(m, y, z ^ (5 << code.d * code.y_bits) if m in bad else z) for m, (y, z) in enumerate(word)]
        assert item in Bucket(code, lists).decode(5)


def test_decoder_against_brute_force():
    code, rng = ExpanderCode(bits=8, s=4, m=7, y_bits=4, d=2), random.Random(3)
    missed = extra = 0
    for _ in range(40):
        items = [rng.randrange(256) for _ in range(3)]
        held = {}
        for x in items:
            for m, (y, z) in enumerate(code.encode(x)):
                held.setdefault((m, y), z)
        lists = [(m, y, z) for (m, y), z in held.items()]
        brute = {x for x in range(256) if sum(held.get((m, y)) == z for m, (y, z) in enumerate(code.encode(x))) >= 6}
        found = set(Bucket(code, lists).decode(6))
        missed += len(brute - found)
        extra += len(found - brute)
    assert extra == 0 and missed <= 2


def test_group_bound_and_crossover():
    for eps, k, d, bound, exact in [(0.1, 100, 1e-6, 5.757, 5.2), (0.5, 100, 1e-6, 38.783, 34), (0.1, 1000, 1e-6, 21.623, 20)]:
        assert bounds.value("group_pure", eps=eps, k=k, delta=d) == pytest.approx(bound, abs=1e-3)
        assert audit.group_quantile(eps, k, d) == pytest.approx(exact)
        assert exact <= bound
    k = bounds.group_crossover(0.1, 1e-6)
    assert bounds.value("group_pure", eps=0.1, k=k, delta=1e-6) < 0.1 * k
    assert bounds.value("group_pure", eps=0.1, k=k - 1, delta=1e-6) >= 0.1 * (k - 1)


def test_printed_group_delta_fails_where_the_safe_one_holds():
    k, delta, delta2 = 10, 0.01, 1e-6
    event = 1 - (1 - delta) ** k
    assert event > bounds.value("group_delta_printed", k=k, delta=delta, delta2=delta2)
    assert event <= bounds.value("group_delta_safe", k=k, delta=delta, delta2=delta2)


def test_poisson_tail_printed_slip():
    exact = bounds.poisson_tail(50.0, 100)
    assert bounds.value("poisson_tail_upper_printed", mu=50.0, alpha=1.0) < exact <= bounds.value("poisson_tail_upper", mu=50.0, alpha=1.0)


def test_shell_laws():
    assert shell.bounds(16, 0.02, 0.017) == (2, 14) and shell.feasible(16, 0.02, 0.017)
    assert shell.exact_epsilon(16, 0.02, 0.017) == pytest.approx(0.24)
    assert shell.tv_exact(16, 0.02, 0.017) == pytest.approx(3.67e-5, rel=1e-2)
    assert shell.exact_epsilon(8, 0.02, 0.02) == pytest.approx(0.16) and shell.tv_exact(8, 0.02, 0.02) == 0
    for k in (16, 64, 256):
        for eps in (0.005, 0.01, 0.02):
            for beta in (0.001, 0.004, 0.017):
                if shell.feasible(k, eps, beta):
                    assert shell.exact_epsilon(k, eps, beta) <= bounds.value("shell_eps_safe", k=k, eps=eps, beta=beta)
                    assert shell.tv_exact(k, eps, beta) <= beta
    assert math.isclose(sum(n * p for _, n, _, p, _ in shell.law(16, 0.3, 0.2)), 1)


def test_purifier_law_and_budget():
    assert audit.purify_epsilon(0.1, 12) == pytest.approx(0.799, abs=1e-3) and audit.purify_epsilon(0.25, 7) == pytest.approx(1.925, abs=1e-3)
    law = audit.purify_law([0.3, 0.5, 0.6])
    exact = [0.0] * 3
    for coins in itertools.product((0, 1), repeat=3):
        p = math.prod(q if c else 1 - q for q, c in zip([0.3, 0.5, 0.6], coins, strict=True))
        on = [i for i, c in enumerate(coins) if c] or [0, 1, 2]
        for i in on:
            exact[i] += p / len(on)
    assert law == pytest.approx(exact)
    assert bounds.value("purify_eps", eps=0.1) >= audit.purify_epsilon(0.1, 12)
    t = bounds.choose_t(60_000, 0.25, 0.01)
    assert t == 57 and 60_000 * 0.75**t <= 0.005
    p = RejectionPurifier(LeakyBit(0.1, delta=0.01), 12)
    assert p.accept_probability(1, 2) == 0.5 and not p.in_band(1, 3) and p.bits() == 4
    assert OneBit(BitFlip(0.5))._one.accept_probability(0, 0) == pytest.approx(0.5)


def test_accepted_sample_follows_the_target():
    inner = BitFlip(0.4)
    p = RejectionPurifier(inner, 1)
    weight = {y: inner.likelihood(y, 0) * p.accept_probability(1, y) for y in (0, 1)}
    total = sum(weight.values())
    assert total == pytest.approx(0.5)
    assert weight[1] / total == pytest.approx(inner.likelihood(1, 1))


def test_expected_share_falls_as_others_rise():
    assert sum(q / (w + 1) for w, q in enumerate(bounds.poisson_binomial([0.5, 0.5]))) > sum(q / (w + 1) for w, q in enumerate(bounds.poisson_binomial([0.6, 0.5])))


def test_escape_and_tails():
    law = bounds.poisson_binomial([0.3] * 12)
    assert law == pytest.approx(bounds.binomial(12, 0.3))
    assert bounds.escape_exact([0.5] * 4, 4) == 0 and bounds.escape_exact([0.5] * 4, 0) == pytest.approx(1 - 6 / 16)
    for n, p, t in [(100, 0.5, 10), (400, 0.25, 15)]:
        assert math.fsum(bounds.binomial(n, p)[: int(n * p - t) + 1]) >= bounds.value("binomial_tail_lower", t=t, n=n, p=p)
    assert bounds.uniform_tail(40, 5) >= bounds.uniform_tail_lower(40, 5)
    assert min(bounds.escape_exact([q] * 30, 3) for q in (0.1, 0.2, 0.4)) >= bounds.escape_exact([0.05] * 30, 3)


def test_plan_splits_the_budget_and_strict_refuses():
    p = planner.plan(60_000, 4.0)
    assert p.eps_coordinate + p.eps_final == p.eps and p.code.d == 2
    with pytest.raises(ValueError):
        planner.plan(60_000, 4.0, strict=True)
    assert planner.plan(10**12, 1.0, preset="wide").buckets > 100


def test_table_of_errors_orders_the_methods():
    for beta in (1e-1, 1e-3, 1e-6):
        v = {k: bounds.value(k, n=6e5, x=2.0**32, eps=1.0, beta=beta) for k in ("main_error", "single_hash_error", "oldest_error")}
        assert v["main_error"] < v["single_hash_error"] < v["oldest_error"]
    assert bounds.value("main_error", n=6e4, x=2.0**32, eps=1.0, beta=0.1) == pytest.approx(1212, abs=1)
    assert bounds.value("oldest_error", n=6e5, x=2.0**32, eps=1.0, beta=1e-6) == pytest.approx(187332, rel=1e-3)


def test_ledger_refuses_and_frozen_protocols_stay_frozen():
    from ldpspark.operators.privacy import Frozen, Ledger, generalization

    ledger = Ledger(1.0)
    ledger.spend("round 1", 0.5)
    ledger.spend("round 1", 0.5)
    with pytest.raises(ValueError):
        ledger.spend("round 1", 0.1)
    p = Frozen(()).add(BitFlip(0.5)).add(BitFlip(0.5))
    assert p.budget() == 1.0
    with pytest.raises(ValueError):
        p.answer().add(BitFlip(0.5))
    assert generalization([(0.5, 0.01), (1.0, 0.0)], 1e-3)[-1] == pytest.approx((1.5, 0.01, math.exp(1.5) * 1e-3 + 0.01))


def test_joint_report_of_the_main_method_is_private():
    """Both halves' signs for two items, all public coins fixed: the law's worst ratio is e^eps."""
    eps = 1.0
    p = BitFlip(eps / 2).keep
    worst = 0.0
    for s1, s2 in itertools.product((1, -1), repeat=2):
        law = []
        for a, b in itertools.product((1, -1), repeat=2):
            law.append((p if s1 == a else 1 - p) * (p if s2 == b else 1 - p))
        worst = max(worst, math.log(max(law) / min(law)))
    assert worst == pytest.approx(eps)


def test_source_bits_stay_independent_given_their_reports():
    p = BitFlip(0.5).keep
    for report in itertools.product((0, 1), repeat=4):
        joint = {}
        for bits in itertools.product((0, 1), repeat=2):
            users = [bits[0], bits[0], bits[1], bits[1]]
            joint[bits] = math.prod(p if u == r else 1 - p for u, r in zip(users, report, strict=True)) / 4
        total = sum(joint.values())
        for x, y in joint:
            px = sum(v for k, v in joint.items() if k[0] == x) / total
            py = sum(v for k, v in joint.items() if k[1] == y) / total
            assert joint[x, y] / total == pytest.approx(px * py)
