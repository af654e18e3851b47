"""Closed forms against worked numbers and brute force."""

import math

import numpy as np
import pytest

from privgrove.functions import closed
from privgrove.functions.noise import laplace_of, race_keys, uniform_of
from privgrove.operators import leaves, sketch
from privgrove.operators.proposals import cuts_of, joint_quantiles
from privgrove.plans.ledger import BudgetPlan, Charge, Ledger, plan_ensemble

WORKED = {1: (0.41390, 0.13797, 0.02299), 2: (0.71867, 0.23956, 0.03993), 4: (1.16752, 0.38917, 0.06486), 6: (1.50376, 0.50125, 0.08354), 8: (1.77804, 0.59268, 0.09878), 10: (2.01320, 0.67107, 0.11184)}


@pytest.mark.parametrize("eps", WORKED)
def test_budget_table(eps):
    plan = plan_ensemble(eps, 20, 0.1, 8, 6)[0]
    assert (round(plan.eps_tree, 5), round(plan.leaf(), 5), round(plan.level, 5)) == WORKED[eps]
    assert math.isclose(math.fsum(c.epsilon for c in plan.charges(0)), plan.eps_tree)


@pytest.mark.parametrize("lam", [0.1, 1.0, 10.0])
def test_gain_and_leaf_sensitivities_hold(lam):
    n = np.arange(0, 400)
    worst = 0.0
    for share in np.linspace(-1, 1, 21):
        g = share * n
        for add in (-1.0, 1.0):
            worst = max(worst, np.abs((g + add) ** 2 / (n + 1 + lam) - g**2 / (n + lam)).max())
            change = np.abs(-(g + add) / (n + 1 + lam) + g / (n + lam))
            assert (change <= closed.sensitivity("leaf_worst_case", lam=lam) + 1e-12).all()
            for least in (1, 10, 50):
                assert (change[least:] <= closed.sensitivity("leaf_min_child", lam=lam, min_child=least) + 1e-12).all()
    assert worst <= closed.sensitivity("gain")


def test_ledger_composes_and_refuses():
    book = Ledger(1.0, 0.1)
    plans = plan_ensemble(1.0, 4, 0.1, 3, 2)
    for t, p in enumerate(plans):
        book.charge(p.charges(t))
    assert math.isclose(book.total(), 1.0)
    with pytest.raises(ValueError):
        book.charge([Charge(9, "leaf", 0, "x", 0.1)])
    assert Ledger(charges=[Charge(0, "a", 0, "s", 0.2), Charge(0, "a", 0, "s", 0.3), Charge(0, "b", 0, "s", 0.1)]).total() == pytest.approx(0.4)
    assert BudgetPlan(0.9, 3, 3, early_leaf_bonus=True).leaf(1) == pytest.approx(0.5)


def test_laplace_quantiles_and_race_frequencies():
    x = np.array([laplace_of(uniform_of("t", k), 2.0) for k in range(20000)])
    assert abs(np.median(x)) < 0.06 and abs(np.quantile(np.abs(x), 0.5) - 2 * math.log(2)) < 0.06
    log = np.log(np.array([1.0, 2.0, 3.0, 4.0]))
    wins = np.bincount([race_keys(log, np.array([uniform_of("r", i, k) for k in range(4)])).argmin() for i in range(20000)], minlength=4) / 20000
    assert np.abs(wins - np.array([0.1, 0.2, 0.3, 0.4])).max() < 0.012


def test_cuts_follow_weight():
    assert cuts_of(np.array([5.0, 0, 0, 1, 10, 0]), 2).tolist() == [3, 4]
    assert cuts_of(np.zeros(8), 3).tolist() == [1, 3, 5]


def test_noisy_average_clips():
    assert leaves.leaf_value("noisy_average", 10.0, 10, float("inf"), 1.0, 0.0, 1, 0.5) == -1.0
    assert leaves.leaf_value("noisy_average", 1e6, 10, 1.0, 1.0, 0.1, 1, 0.9) == -1.0


def test_sketch_bounds_hold_after_merge_and_prune():
    rng = np.random.default_rng(1)
    x, w = rng.normal(size=4000).round(2), rng.integers(1, 5, 4000).astype(float)
    parts = [sketch.prune(sketch.build(x[i::4], w[i::4]), 100) for i in range(4)]
    s = parts[0]
    for p in parts[1:]:
        s = sketch.merge(s, p)
    before = np.array([w[x < v].sum() for v in s.value])
    assert (s.low <= before + 1e-9).all() and (before + np.array([w[x == v].sum() for v in s.value]) <= s.high + 1e-9).all()
    cut = sketch.query(s, np.array([0.25, 0.5, 0.75]) * s.total)
    assert all(abs(w[x <= c].sum() / w.sum() - q) < 0.03 for c, q in zip(cut, (0.25, 0.5, 0.75)))


def test_joint_quantiles_are_near_the_quantiles():
    w = np.full(32, 500.0)
    assert np.abs(np.array(joint_quantiles(w, 3, 5.0, "k")) - np.array([7, 15, 23])).max() <= 1
