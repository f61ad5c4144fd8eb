"""Golden values of the accountant, and the budget of whole runs."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from dpsynth.privacy import accountant as a
from dpsynth.privacy.mechanisms import NoiseSource, exp_select

GOLDEN = [(0.01, 2.09543e-6, 7977, 8.358e-5), (0.1, 1.77138e-4, 867.6, 7.684e-4), (1, 1.49731e-2, 94.37, 7.065e-3), (10, 1.09079, 11.06, 6.03e-2), (100, 42.3802, 1.774, 0.3759)]


@pytest.mark.parametrize(("eps", "rho", "sigma", "select"), GOLDEN)
def test_rho_and_start_rates(eps, rho, sigma, select):
    found = a.rho_of(eps, 1e-9)
    assert found == pytest.approx(rho, rel=1e-5)
    assert a.initial_rates(found, 15) == pytest.approx((sigma, select), rel=1e-3)
    assert a.delta_of(found, eps) == pytest.approx(1e-9, rel=1e-6)


def rounds(rho, d, alpha, anneal):
    """Costs of all rounds if annealing fires as told, without data."""
    ledger = a.Ledger(rho)
    sigma, eps = a.initial_rates(rho, d, alpha)
    ledger.charge(d * a.rho_gauss(sigma))
    costs, last = [], False
    while not last:
        if ledger.left <= 2 * a.round_cost(sigma, eps) * (1 + 1e-12):
            sigma, eps = a.last_rates(ledger.left, alpha)
            last = True
        costs.append(a.round_cost(sigma, eps))
        ledger.charge(min(costs[-1], ledger.left))
        if next(anneal, False):
            sigma, eps = sigma / 2, eps * 2
    return ledger, costs


@pytest.mark.parametrize(("d", "n", "last"), [(15, 226, 1.5), (9, 135, 1.9), (16, 241, 1.6)])
def test_rounds_without_annealing(d, n, last):
    ledger, costs = rounds(1.0, d, 0.9, iter(()))
    assert len(costs) == n
    assert costs[-1] * 16 * d == pytest.approx(last)
    assert ledger.used == pytest.approx(1.0, rel=1e-12)


def test_rounds_with_annealing():
    _, costs = rounds(1.0, 15, 0.9, iter([True] * 9))
    assert [c * 240 for c in costs] == pytest.approx([1, 4, 16, 64, 141.5])


@settings(max_examples=60, deadline=None)
@given(st.floats(1e-6, 50), st.integers(2, 20), st.floats(0.05, 0.95), st.lists(st.booleans(), max_size=40))
def test_budget_is_spent_and_never_passed(rho, d, alpha, pattern):
    ledger, _ = rounds(rho, d, alpha, iter(pattern))
    assert ledger.used == pytest.approx(rho, rel=1e-9)
    assert ledger.used <= rho * (1 + 1e-12)


def test_overspending_is_refused():
    ledger = a.Ledger(1.0)
    ledger.charge(0.8)
    with pytest.raises(a.BudgetExceeded):
        ledger.charge(0.3)
    assert ledger.used == 0.8


def test_choice_follows_the_softmax():
    noise, scores = NoiseSource(1), [0.0, 1.0, 2.0]
    hits = np.bincount([exp_select(scores, 2.0, 1.0, noise) for _ in range(20000)], minlength=3) / 20000
    want = np.exp(scores) / np.exp(scores).sum()
    assert np.abs(hits - want).max() < 0.015


def test_noise_sources():
    z = NoiseSource(3).gaussian(2.0, 50000)
    assert z.std() == pytest.approx(2.0, rel=0.02)
    k = NoiseSource(3, discrete=True).gaussian(3.0, 50000)
    assert (k == np.round(k)).all() and k.std() == pytest.approx(3.0, rel=0.02) and abs(k.mean()) < 0.05
    with pytest.raises(ValueError):
        NoiseSource(3).check(release=True)
    NoiseSource().check(release=True)


def test_sensitivity_of_marginals_by_one_row_edits():
    rng = np.random.default_rng(0)
    for _ in range(50):
        t = rng.integers(0, 4, 30)
        m = np.bincount(t, minlength=4)
        added = np.bincount(np.append(t, rng.integers(4)), minlength=4)
        assert np.linalg.norm(added - m) <= a.l2_sensitivity()
        t2 = t.copy()
        t2[0] = rng.integers(4)
        assert np.linalg.norm(np.bincount(t2, minlength=4) - m) <= a.l2_sensitivity(a.Neighbor.BOUNDED) + 1e-12
    assert a.l2_sensitivity(a.Neighbor.BOUNDED) == math.sqrt(2)
