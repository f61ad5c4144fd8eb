"""Mixtures of product distributions: the relaxed table and the generator network.

Both hold a row of softmax blocks per component.  A marginal is the mean over components of
products of blocks; gradients of any loss on marginals flow back through the blocks.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

from dpsynth.domain import DomainSpec
from dpsynth.model.graphical import Measurement, estimate_total, merged

Subset = tuple[int, ...]
_LETTERS = "abcdefghijkl"


def softmax_blocks(logits: np.ndarray, spec: DomainSpec) -> list[np.ndarray]:
    out, at = [], 0
    for n in spec.sizes:
        x = logits[:, at : at + n]
        e = np.exp(x - x.max(1, keepdims=True))
        out.append(e / e.sum(1, keepdims=True))
        at += n
    return out


def mixture_marginal(blocks: list[np.ndarray], subset: Subset, total: float) -> np.ndarray:
    names = _LETTERS[: len(subset)]
    args = ",".join(f"m{c}" for c in names)
    return np.einsum(f"{args}->{names}", *[blocks[i] for i in subset], optimize=True) * (total / len(blocks[0]))


def logit_gradient(blocks: list[np.ndarray], grads: list[tuple[Subset, np.ndarray]], total: float, spec: DomainSpec) -> np.ndarray:
    """Gradient on the logits of a loss whose gradients on some marginals are given."""
    on = [np.zeros_like(b) for b in blocks]
    scale = total / len(blocks[0])
    for subset, g in grads:
        names = _LETTERS[: len(subset)]
        if len(subset) == 1:
            on[subset[0]] += scale * g
            continue
        for k, i in enumerate(subset):
            others = [n for n in range(len(subset)) if n != k]
            args = ",".join([*(f"m{names[n]}" for n in others), names])
            on[i] += scale * np.einsum(f"{args}->m{names[k]}", *[blocks[subset[n]] for n in others], g, optimize=True)
    return np.concatenate([b * (g - (b * g).sum(1, keepdims=True)) for b, g in zip(blocks, on, strict=True)], 1)


class MixtureModel:
    """Components of equal weight; each attribute is independent within one."""

    size_mb = 0.0

    def __init__(self, spec: DomainSpec, total: float, blocks: list[np.ndarray], state=None):
        self.spec, self.total, self.blocks, self.state = spec, float(total), blocks, state

    def marginal(self, subset: Sequence[int]) -> np.ndarray:
        return mixture_marginal(self.blocks, tuple(subset), self.total).ravel()

    def make_rows(self, n: int, rng: np.random.Generator) -> np.ndarray:
        part = rng.integers(0, len(self.blocks[0]), n)
        out = np.empty((n, self.spec.d), np.int32)
        for i, b in enumerate(self.blocks):
            out[:, i] = np.minimum((rng.random(n)[:, None] > np.cumsum(b, 1)[part]).sum(1), b.shape[1] - 1)
        return out


class Adam:
    def __init__(self, rate: float):
        self.rate, self.t, self.m, self.v = rate, 0, 0.0, 0.0

    def step(self, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m, self.v = 0.9 * self.m + 0.1 * g, 0.999 * self.v + 0.001 * g * g
        return self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-10)


def fit_relaxed(measured: Sequence[Measurement], spec: DomainSpec, rows: int = 200, steps: int = 200, rate: float = 0.1, total: float | None = None, warm: MixtureModel | None = None, seed: int = 0) -> MixtureModel:
    """A continuous table of ``rows`` rows whose marginals match the measurements in squares."""
    measured = merged(measured)
    total = estimate_total(measured) if total is None else total
    logits = warm.state.copy() if isinstance(warm, MixtureModel) and warm.state is not None else np.random.default_rng(seed).normal(0, 0.5, (rows, sum(spec.sizes)))
    top, adam = max(1 / m.sigma for m in measured), Adam(rate)
    for _ in range(steps):
        blocks = softmax_blocks(logits, spec)
        grads = []
        for m in measured:
            gap = mixture_marginal(blocks, m.subset, total) - m.values.reshape(spec.shape(m.subset))
            grads.append((m.subset, 2 * gap / (m.sigma * top * total)))
        logits -= adam.step(logit_gradient(blocks, grads, total, spec))
    model = MixtureModel(spec, total, softmax_blocks(logits, spec), logits)
    model.loss = sum(float(((model.marginal(m.subset) - m.values) ** 2).sum()) / m.sigma for m in measured)
    return model


class Generator:
    """Two layers on fixed Gaussian inputs; the output layer gives the logits of the components."""

    def __init__(self, spec: DomainSpec, components: int = 128, width: int = 64, inputs: int = 16, seed: int = 0):
        rng = np.random.default_rng(seed)
        self.spec, self.z = spec, rng.normal(size=(components, inputs))
        self.p = [rng.normal(0, inputs**-0.5, (inputs, width)), np.zeros(width), rng.normal(0, width**-0.5, (width, sum(spec.sizes))), np.zeros(sum(spec.sizes))]
        self.opt = [Adam(5e-3) for _ in self.p]

    def forward(self, p: list[np.ndarray] | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
        w1, b1, w2, b2 = p or self.p
        h = np.tanh(self.z @ w1 + b1)
        return h, softmax_blocks(h @ w2 + b2, self.spec)

    def fit(self, measured: Sequence[Measurement], total: float, steps: int = 100, average_from: float = 0.5) -> MixtureModel:
        """Adam on the L1 gap to the measurements; the later half of the weights is averaged."""
        mean, n = [np.zeros_like(x) for x in self.p], 0
        for k in range(steps):
            h, blocks = self.forward()
            grads = [(m.subset, np.sign(mixture_marginal(blocks, m.subset, total) - m.values.reshape(self.spec.shape(m.subset))) / total) for m in measured]
            g = logit_gradient(blocks, grads, total, self.spec)
            back = (g @ self.p[2].T) * (1 - h * h)
            for x, o, d in zip(self.p, self.opt, [self.z.T @ back, back.sum(0), h.T @ g, g.sum(0)], strict=True):
                x -= o.step(d)
            if k >= average_from * steps:
                mean, n = [a + x for a, x in zip(mean, self.p, strict=True)], n + 1
        _, blocks = self.forward([a / max(1, n) for a in mean] if n else None)
        return MixtureModel(self.spec, total, blocks)
