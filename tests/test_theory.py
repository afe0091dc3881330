import math

import pytest
from pyspark.sql import functions as F

from stagewise.functions import theory as T


@pytest.mark.parametrize(
    ("lam", "bound", "whole", "smooth", "alternating"),
    [(2, 2.7549, 3.0, 2.9139, 5.771), (4, 3.6096, 4.0, 3.9139, 7.214), (16, 5.4869, 6.0, 5.9139, 10.099), (1000, 11.4092, 11.9531, 11.8797, 18.706)],
)
def test_reference_values(lam, bound, whole, smooth, alternating):
    assert T.lb_exact(lam) == pytest.approx(bound, abs=1e-4)
    assert T.cost_staged_int(lam) == pytest.approx(whole, abs=1e-4)
    assert T.cost_staged(lam) == pytest.approx(smooth, abs=1e-4)
    assert T.cost_alternating(lam) == pytest.approx(alternating, abs=1e-3)


def test_splitting_costs_nothing():
    assert T.lb(0.002, 30) == pytest.approx(6.040726011718576)
    assert T.split_gap(0.01, 0.2, 30) == pytest.approx(0, abs=1e-12)
    assert T.split_many([0.5, 0.5, 0.25, 0.0], 20) == pytest.approx(T.lb_exact(20))


def test_limits_and_overhead():
    assert T.lb(0.01, 1e9) == pytest.approx(math.log2(100), abs=1e-6)
    assert T.staged_overhead(4) == pytest.approx(T.MAX_OVERHEAD)
    assert max(T.staged_overhead(x / 10) for x in range(10, 2000)) <= T.MAX_OVERHEAD + 1e-9
    assert T.class_bits(3) == pytest.approx(3 * T.class_bits(1 / 3))
    assert T.lb_exact(T.swap_roles(80, 100)) == pytest.approx(T.lb_exact(4))


def test_toy_universe():
    sets, bits = T.toy_bound(4, 2)
    assert sets == 6 and bits == pytest.approx(math.log2(6))
    assert bits <= 2 * T.lb_exact(1) + 1e-9


def test_chain_matches_two_stages():
    for lam in (2, 5, 16, 100):
        assert T.plan_chain(0.0, lam)[1] == pytest.approx(T.cost_staged_int(lam))


def test_envelope_is_no_worse_than_one_filter():
    one = lambda e, lam: T.cost_single(e, lam)
    assert T.and_envelope(one, 0.0, 16, 16) <= T.cost_single(0.0, 16)


def test_general_plans_beat_single_tables():
    for eps in (0.001, 0.01):
        for lam in (4, 16):
            assert T.cost_general(eps, lam) <= T.cost_single(eps, lam) + 1e-9
            assert T.cost_general(eps, lam) >= T.lb(eps, lam) - 1e-9


def test_predictor_table():
    want = {0.10: 0.10, 0.15: 0.20, 0.20: 0.32, 0.25: 0.45, 0.30: 0.60, 0.35: 0.76, 0.40: 0.93}
    for r, mb in want.items():
        assert T.predictor_space(r) == pytest.approx(mb, abs=0.006)
    assert T.predictor_lambda(0.4) == pytest.approx(2.209, abs=1e-3)
    assert 1 - T.predictor_space(0.4) / T.locking_space() == pytest.approx(0.767, abs=0.003)


def test_thresholds():
    assert 1.21 < T.peel_threshold(3) < 1.24
    assert T.coupled_threshold(4) < T.coupled_threshold(3) < T.peel_threshold(3)


def test_layers_shrink():
    plan = T.layer_plan(50_000, 4)
    assert sum(bits for *_, bits in plan) / 50_000 == pytest.approx(T.cost_alternating(4), rel=0.02)


def test_columns_agree_with_numbers(spark):
    lams = [0.5, 1.0, 2.0, 4.0, 16.0, 64.0]
    df = spark.createDataFrame([(x,) for x in lams], "lam double")
    lam = F.col("lam")
    got = df.select("lam", T.lb_exact(lam), T.cost_staged(lam), T.cost_staged_int(lam), T.lb(F.lit(0.01), lam), T.general_a(F.lit(0.01), lam), T.general_b(F.lit(0.01), lam)).collect()
    for x, *cols in got:
        want = [T.lb_exact(x), T.cost_staged(x), T.cost_staged_int(x), T.lb(0.01, x), T.general_a(0.01, x), T.general_b(0.01, x)]
        assert cols == pytest.approx(want)


def test_planner():
    assert T.plan(1000, 17_000).kind == "staged"
    assert T.plan(1000, 2000).kind == "single"
    assert T.plan(9000, 10_000).negate
    assert T.plan(100, 10_000, dynamic=True).steps[0].kind == "bloom"
    assert T.classify(0.0, 4) == "exact" and T.classify(0.1, math.inf) == "approximate" and T.classify(0.1, 4) == "general"


def test_a_budget_buys_what_it_pays_for():
    exact = T.plan(1000, 17_000)
    assert T.plan(1000, 17_000, budget=exact.bits_per_positive * 1000 + 1) == exact
    less = T.plan(1000, 17_000, budget=4000)
    assert less.kind == "single" and less.steps[0].eps == 2.0**-3 and less.bits_per_positive * 1000 <= 4000
    with pytest.raises(ValueError, match="bits"):
        T.plan(1000, 17_000, budget=500)
