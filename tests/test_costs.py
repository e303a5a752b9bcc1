"""Formulas, the planner and the simulator against the published numbers and brute force."""

import math
import random

import pytest

from semjoin.functions import costs
from semjoin.plans import optimize, simulate
from semjoin.types import BudgetTooSmall, TableProfile

EX = dict(width_left=10, width_right=2, width_match=1, budget=100)


def test_worked_example():
    a = costs.left_size(10, 2, 1, 1, 100)
    b = costs.right_size_for(a, 10, 2, 1, 1, 100)
    assert (a, b) == pytest.approx((2.898979, 14.494897), abs=1e-6)
    assert costs.call_tokens(3, 14, 0, 10, 2, 1, 1) == 100
    p = optimize.optimal_batches(TableProfile(50, 10.0, 10), TableProfile(10, 2.0, 2), 1.0, 100, 1, 1, 1.0, clamp=False)
    assert (p.batch_left, p.batch_right) == (3, 14)
    p = optimize.optimal_batches(TableProfile(50, 10.0, 10), TableProfile(10, 2.0, 2), 1.0, 100, 1, 1, 1.0)
    assert (p.batch_left, p.batch_right, p.expected_cost) == (4, 10, 1273)


def test_curve_ends():
    for sigma, want in ((0, (5, 25)), (0.25, (4, 20)), (1, (2.899, 14.495))):
        a = costs.left_size(10, 2, 1, sigma, 100)
        assert (a, costs.right_size_for(a, 10, 2, 1, sigma, 100)) == pytest.approx(want, abs=1e-3)


def test_slope():
    f = lambda x: costs.cost_on_curve(x, 50, 10, 1, 10, 2, 1, 1, 1, 100)
    assert costs.slope_on_curve(2.2, 50, 10, 1, 10, 2, 1, 1, 100) == pytest.approx((f(2.2 + 1e-5) - f(2.2 - 1e-5)) / 2e-5, rel=1e-5)
    assert costs.slope_on_curve(2.2, 50, 10, 1, 10, 2, 1, 1, 100) == pytest.approx(-109.0722, abs=1e-3)
    assert costs.slope_on_curve(costs.left_size(10, 2, 1, 1, 100), 50, 10, 1, 10, 2, 1, 1, 100) == pytest.approx(0, abs=1e-9)


def test_statements_hold_on_random_settings():
    r = random.Random(5)
    for _ in range(3000):
        w1, w2, w3, t = r.uniform(1, 200), r.uniform(1, 200), r.uniform(1, 8), r.uniform(500, 9000)
        p, g, growth = r.uniform(1, 200), r.uniform(1, 5), r.uniform(1.1, 10)
        sigma = 10 ** r.uniform(-5, 0)
        e = min(1.0, sigma * r.uniform(1, growth))
        a, b = costs.left_size(w1, w2, w3, sigma, t), costs.right_size_for(costs.left_size(w1, w2, w3, sigma, t), w1, w2, w3, sigma, t)
        assert a * w1 == pytest.approx(b * w2, rel=1e-9)  # equal shares
        assert costs.call_tokens(a, b, 0, w1, w2, w3, sigma) == pytest.approx(t, rel=1e-9)  # the budget is used up
        c, d = costs.left_size(w1, w2, w3, e, t), costs.right_size_for(costs.left_size(w1, w2, w3, e, t), w1, w2, w3, e, t)
        assert c <= a * (1 + 1e-12) and a <= growth * c * (1 + 1e-9) and a * b <= growth * c * d * (1 + 1e-9)
        assert costs.regret(e, sigma, 1000, 1000, p, w1, w2, w3, g, t) <= costs.regret_bound(growth, g) * (1 + 1e-9)
        best = costs.cost_on_curve(a, 100, 100, p, w1, w2, w3, sigma, g, t)
        for f in (0.5, 0.9, 1.1, 1.5):
            if a * f * w1 < t:
                assert best <= costs.cost_on_curve(a * f, 100, 100, p, w1, w2, w3, sigma, g, t) * (1 + 1e-12)
        assert costs.block_cost(100, 100, a * 0.7, b, p, w1, w2, w3, sigma, g) >= costs.block_cost(100, 100, a, b, p, w1, w2, w3, sigma, g) * (1 - 1e-12)


def test_planner_equals_exhaustive_search():
    r = random.Random(3)
    for _ in range(200):
        n, m, w1, w2, w3, s, t, p, g = r.randint(1, 40), r.randint(1, 40), r.uniform(1, 20), r.uniform(1, 20), r.choice([1, 2, 4]), r.choice([0, 0.01, 0.3, 1]), r.uniform(60, 300), r.uniform(1, 50), r.choice([1, 2])
        plan = optimize.optimal_batches(TableProfile(n, w1, 0), TableProfile(m, w2, 0), s, t, p, w3, g)
        least = min(costs.ragged_cost(n, m, x, y, p, w1, w2, w3, s, g) for x in range(1, n + 1) for y in range(1, m + 1) if costs.fits(x, y, w1, w2, w3, s, t + 1e-9))
        assert plan.expected_cost == pytest.approx(least)
        assert costs.fits(plan.batch_left, plan.batch_right, w1, w2, w3, s, t + 1e-6)


def test_planner_refuses():
    with pytest.raises(BudgetTooSmall):
        optimize.optimal_batches(TableProfile(5, 50.0, 50), TableProfile(5, 60.0, 60), 1.0, 100, 1)
    with pytest.raises(ValueError):
        optimize.optimal_batches(TableProfile(5, 5.0, 5), TableProfile(5, 6.0, 6), -0.1, 100, 1)


def test_rounds_and_bound():
    assert costs.expected_rounds(0.01, 1.0, 4) == 4 and costs.expected_rounds(0.5, 0.1, 4) == 0
    assert costs.regret_bound(4, 2) == 8 and costs.regret_bound(4, 0.5) == 4


PUBLISHED = [  # rows_left, width_left, selectivity, pairwise, conservative, informed, adaptive, void rounds
    (1000, 30, 0.001, 16800, 182.67, 71.26, 71.99, 3), (5000, 30, 0.001, 84000, 913.35, 347.17, 347.90, 3), (10000, 30, 0.001, 168000, 1826.70, 689.77, 690.51, 3),
    (5000, 10, 0.001, 69000, 489.48, 119.24, 121.75, 4), (5000, 100, 0.001, 136500, 1995.58, 1127.44, 1128.17, 3), (5000, 30, 0.0001, 84000, 910.65, 339.91, 339.91, 0),
    (5000, 30, 0.01, 84000, 940.35, 383.28, 402.52, 4), (5000, 30, 0.1, 84000, 1210.35, 753.75, 874.01, 4), (5000, 30, 1.0, 84000, 3910.35, 3910.35, 3911.59, 4),
]


def test_simulated_fees(spark):
    for n, w, s, *want, void in PUBLISHED:
        x = simulate.Setting(rows_left=n, width_left=w, selectivity=s)
        fee = {r["method"]: r["fee"] for r in simulate.simulate(spark, [(0.0, x)]).collect()}
        assert [fee[m] for m in simulate.METHODS] == pytest.approx(want, abs=0.02), (n, w, s)
        assert abs(len(simulate.void_calls(x)[0]) - void) <= (1 if s == 0.0001 else 0)


def test_overhead_falls_as_tables_grow(spark):
    over = []
    for n in (500, 1000, 2000, 5000, 10000):
        fee = {r["method"]: r["fee"] for r in simulate.simulate(spark, [(0.0, simulate.Setting(rows_left=n))], ("informed", "adaptive")).collect()}
        over.append(fee["adaptive"] / fee["informed"] - 1)
    assert over == sorted(over, reverse=True) and over[-1] < 0.0012


def test_price_example():
    assert costs.fee_cents(costs.pairwise_cost(10_000, 10_000, 0, 100, 100, 0), 0) == 60_000_000
    assert math.isclose(costs.pair_cost(50, 30, 30, 2), 112)
