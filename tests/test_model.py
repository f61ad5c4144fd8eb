"""The estimator against brute force over small domains, trees, generation."""

import itertools

import numpy as np
import pytest

from dpsynth.domain import DomainSpec
from dpsynth.model import generate as gen
from dpsynth.model import graphical as g
from dpsynth.model import junction as j
from dpsynth.model.mixture import MixtureModel, fit_relaxed, logit_gradient, mixture_marginal, softmax_blocks

SPEC = DomainSpec.from_sizes([2, 3, 4, 2, 3])
ALL = (0, 1, 2, 3, 4)


def down(p, r):
    return p.sum(tuple(i for i in ALL if i not in r)).ravel()


@pytest.fixture(scope="module")
def measured():
    rng = np.random.default_rng(0)
    p = rng.random(SPEC.sizes) ** 4
    p *= 1000 / p.sum()
    return [g.Measurement(r, down(p, r) + rng.normal(0, s, SPEC.size(r)), s) for r, s in (((0, 1), 1.0), ((1, 2), 2.0), ((2, 3), 1.0), ((3, 4), 0.5), ((0,), 1.0), ((1, 2), 1.0))]


def test_fit_reaches_the_dense_optimum(measured):
    model = g.fit(measured, SPEC, 500)
    merged, total = g.merged(measured), g.estimate_total(measured)
    top, theta = max(1 / m.sigma for m in merged), np.zeros(SPEC.sizes)
    for _ in range(8000):
        q = np.exp(theta - theta.max())
        q *= total / q.sum()
        loss, grad = 0.0, np.zeros_like(theta)
        for m in merged:
            gap, w = down(q, m.subset) - m.values, 1 / m.sigma / top
            loss += w * gap @ gap
            grad += 2 * w * g._spread(gap.reshape(SPEC.shape(m.subset)), m.subset, ALL)
        theta -= 2e-4 * grad
    assert model.loss == pytest.approx(loss, rel=1e-3)


def test_marginals_equal_dense_sums(measured):
    model = g.fit(measured, SPEC, 50)
    q = np.exp(sum(g._spread(v, r, ALL) for r, v in model.potentials.items()) + np.zeros(SPEC.sizes))
    q *= model.total / q.sum()
    for n in range(1, 6):
        for r in itertools.combinations(ALL, n):
            assert np.allclose(model.marginal(r), down(q, r))


def test_disconnected_attributes_are_independent():
    spec = DomainSpec.from_sizes([2, 3, 4])
    model = g.GraphicalModel(spec, 12, {(0, 1): np.log(np.arange(1.0, 7).reshape(2, 3))})
    assert np.allclose(model.marginal((1, 2)).reshape(3, 4), model.marginal((1,))[:, None] / 4)


def test_tree_sizes():
    assert j.size_mb([(0, 1), (1, 2), (0, 2)], (10, 20, 30)) == pytest.approx(0.0457764, abs=1e-7)
    rng = np.random.default_rng(1)
    for _ in range(15):  # against the best elimination order
        sizes = [int(x) for x in rng.integers(2, 5, 6)]
        sets = [tuple(sorted(rng.choice(6, 2, replace=False).tolist())) for _ in range(6)]

        def cost(order, sets=sets, sizes=sizes):
            near, cliques = j._neighbours(sets, 6), []
            for i in order:
                c = near[i] | {i}
                if not any(c <= x for x in cliques):
                    cliques.append(set(c))
                for k in near[i]:
                    near[k] |= near[i]
                    near[k] -= {i, k}
            return sum(np.prod([sizes[i] for i in c]) for c in cliques) * 8 / 2**20

        best = min(cost(o) for o in itertools.permutations(range(6)))
        assert j.size_mb(sets, sizes) <= 1.5 * best + 1e-9


def test_total_is_an_inverse_variance_mean():
    ms = [g.Measurement((0,), np.array([3.0, 4.0]), 1.0), g.Measurement((1,), np.array([1.0, 2.0, 3.0]), 2.0)]
    assert g.estimate_total(ms) == pytest.approx((7 / 2 + 6 / 12) / (1 / 2 + 1 / 12))
    assert g.estimate_total([g.Measurement((0,), np.array([-5.0]), 1.0)]) == 1.0


def test_rounding_stays_within_one_per_parent_group(measured):
    model = g.fit(measured, SPEC, 100)
    data = gen.make_slice(gen.plan_columns(model), SPEC, 1000, np.random.default_rng(0))
    for i, parents, table in gen.plan_columns(model):
        key = np.zeros(1000, int)
        for p in parents:
            key = key * SPEC.attrs[p].size + data[:, p]
        for k in np.unique(key):
            rows = data[key == k, i]
            want = table[k] / table[k].sum() * len(rows)
            assert np.abs(np.bincount(rows, minlength=len(want)) - want).max() < 1 + 1e-6


def test_generation_is_repeatable(spark, measured):
    model = g.fit(measured, SPEC, 30)
    a, b = (sorted(map(tuple, gen.generate(spark, model, 500, seed=4, slice_rows=100).collect())) for _ in range(2))
    assert a == b and len(a) == 500
    assert gen.generate(spark, model, 300, method="sample").count() == 300


def test_mixture_gradient():
    rng, spec = np.random.default_rng(0), DomainSpec.from_sizes([2, 3, 4])
    logits, want = rng.normal(size=(5, 9)), rng.random((2, 3, 4))

    def loss(x):
        return float(((mixture_marginal(softmax_blocks(x, spec), (0, 1, 2), 10.0) - want) ** 2).sum())

    blocks = softmax_blocks(logits, spec)
    grad = logit_gradient(blocks, [((0, 1, 2), 2 * (mixture_marginal(blocks, (0, 1, 2), 10.0) - want))], 10.0, spec)
    for at in ((0, 0), (3, 4), (4, 8)):
        step = np.zeros_like(logits)
        step[at] = 1e-6
        assert (loss(logits + step) - loss(logits - step)) / 2e-6 == pytest.approx(grad[at], rel=1e-4, abs=1e-6)


def test_relaxed_fit_falls(measured):
    few, many = (fit_relaxed(measured, SPEC, 50, n) for n in (1, 200))
    assert isinstance(many, MixtureModel) and many.loss < 0.1 * few.loss


def test_marginals_share_sums_and_meet_brute_force():
    """Calibration and marginals within and across cliques against the whole table, in few large sums."""
    spec, rng = DomainSpec.from_sizes([3, 4, 2, 5, 3, 2]), np.random.default_rng(3)
    sets = [(0, 1), (1, 2, 3), (0, 3), (3, 4), (1,), (5,)]
    logs = {r: rng.normal(0, 30, spec.shape(r)) for r in sets}
    whole = sum(v.reshape([n if i in r else 1 for i, n in enumerate(spec.sizes)]) for r, v in logs.items())
    whole = np.exp(whole - whole.max())
    whole *= 100 / whole.sum()
    model = g.GraphicalModel(spec, 100.0, logs)
    for k in (1, 2, 3, 4):
        for r in itertools.combinations(range(6), k):
            want = whole.sum(tuple(i for i in range(6) if i not in r)).ravel()
            assert np.allclose(model.marginal(r), want, atol=1e-9)
    assert 0 < len(model._sums)
    model.forget()
    assert not model._sums
