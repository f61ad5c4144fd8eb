"""Records from a fitted model, column by column in tree order, without access to data.

Rounding: in each group of records that agree on the parents, every value gets the floor of its
expected count, and a lottery hands out the rest without replacement.  Slices of records are
made independently from (seed, slice), so a retried task makes the same records again and
nothing is shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from dpsynth.domain import DomainSpec
from dpsynth.model.graphical import GraphicalModel, _collapse
from dpsynth.model.mixture import MixtureModel

SLICE = 1 << 18


def plan_columns(model: GraphicalModel) -> list[tuple[int, tuple[int, ...], np.ndarray]]:
    """(attribute, parents, table of parents' cells x values) in the order of generation."""
    out, made = [], set()
    for clique, table in zip(model.tree.cliques, model.cliques, strict=True):
        parents = tuple(i for i in clique if i in made)
        for i in (i for i in clique if i not in made):
            order = tuple(sorted((*parents, i)))
            shown = np.moveaxis(_collapse(table, clique, order), order.index(i), -1).reshape(-1, model.spec.attrs[i].size)
            out.append((i, parents, shown))
            parents = tuple(sorted((*parents, i)))
            made.add(i)
    return out


def round_counts(expected: np.ndarray, rows: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Integer counts per group (a row each) with the given sums: floors, then a lottery in
    proportion to the fractions, by the largest Gumbel sums."""
    base = np.floor(expected + 1e-9).astype(np.int64)
    rest = rows - base.sum(1)
    key = np.log(np.maximum(expected - base, 1e-12)) + rng.gumbel(size=expected.shape)
    place = np.argsort(np.argsort(-key, axis=1), axis=1)
    return base + (place < rest[:, None])


def make_slice(columns: list[tuple[int, tuple[int, ...], np.ndarray]], spec: DomainSpec, n: int, rng: np.random.Generator, method: str = "round") -> np.ndarray:
    """n records as an array of codes, a column per attribute."""
    data = np.zeros((n, spec.d), np.int32)
    for i, parents, table in columns:
        group = np.zeros(n, np.int64)
        for p in parents:
            group = group * spec.attrs[p].size + data[:, p]
        met, at, rows = np.unique(group, return_inverse=True, return_counts=True)
        share = table[met]
        mass = share.sum(1, keepdims=True)
        share = np.where(mass > 0, share / np.where(mass > 0, mass, 1), 1 / share.shape[1])
        if method == "sample":
            data[:, i] = np.minimum((rng.random(n)[:, None] > np.cumsum(share, 1)[at]).sum(1), share.shape[1] - 1)
            continue
        counts = round_counts(share * rows[:, None], rows, rng)
        values = np.repeat(np.tile(np.arange(share.shape[1]), len(met)), counts.ravel())
        # the values of a group go to its records in random order
        order = np.lexsort((rng.random(n), at))
        data[order, i] = values
    return data


def generate_rows(model: GraphicalModel, n: int | None = None, seed: int = 0, method: str = "round") -> np.ndarray:
    """The first slice of what ``generate`` makes, here and now: at most SLICE records."""
    n = min(SLICE, max(1, round(model.total)) if n is None else n)
    rng = np.random.default_rng([seed, 0])
    return model.make_rows(n, rng) if isinstance(model, MixtureModel) else make_slice(plan_columns(model), model.spec, n, rng, method)


def generate(spark: SparkSession, model: GraphicalModel, n: int | None = None, seed: int = 0, method: str = "round", slice_rows: int = SLICE) -> DataFrame:
    """``n`` records (the model's mass, rounded, by default) in the encoded schema."""
    n = max(1, round(model.total)) if n is None else n
    mixture = model if isinstance(model, MixtureModel) else None
    columns, spec = mixture or plan_columns(model), model.spec
    slices, mixed = -(-n // slice_rows), mixture is not None
    shared = spark.sparkContext.broadcast(columns)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for k in f["id"]:
                rows = min(slice_rows, n - int(k) * slice_rows)
                rng = np.random.default_rng([seed, int(k)])
                made = shared.value.make_rows(rows, rng) if mixed else make_slice(shared.value, spec, rows, rng, method)
                yield pd.DataFrame(made, columns=spec.names)

    return spark.range(0, slices, 1, min(slices, 10_000)).mapInPandas(run, ", ".join(f"{x} int" for x in spec.names))
