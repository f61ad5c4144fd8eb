"""Encoding to codes and back, as SQL expressions that stay inside code generation.

The rule builders give text that both Spark SQL and DuckDB read, so one declaration serves the
engine and its checks.  Every rule clamps, so a code is in its domain whatever the data are.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.domain import AttrSpec, DomainSpec


def _clamped(expr: str, size: int) -> str:
    return f"cast(least(greatest(coalesce({expr}, 0), 0), {size - 1}) as int)"


def vocab(name: str, source: str, words: Sequence[str], other: bool = False) -> AttrSpec:
    """A declared vocabulary; what is not in it (or null) gets the last code."""
    cases = " ".join(f"when '{w}' then {i}" for i, w in enumerate(words))
    labels = (*words, "other") if other else tuple(words)
    return AttrSpec(name, len(labels), f"case {source} {cases} else {len(labels) - 1} end", "vocab", labels)


def code(name: str, expr: str, size: int) -> AttrSpec:
    """An integer expression, clamped to 0..size-1."""
    return AttrSpec(name, size, _clamped(expr, size), "code")


def bins(name: str, source: str, lo: float, hi: float, k: int) -> AttrSpec:
    """k bins of equal width between declared bounds."""
    return AttrSpec(name, k, _clamped(f"floor(({source} - ({lo})) / {(hi - lo) / k!r})", k), "bins", tuple(f"{lo + (hi - lo) * (i + 0.5) / k:g}" for i in range(k)))


def log_bins(name: str, source: str, k: int, shift: int = 0) -> AttrSpec:
    """Bins by powers of two."""
    return AttrSpec(name, k, _clamped(f"floor(log2(greatest({source} + {shift}, 1)))", k), "log_bins")


def flag(name: str, condition: str) -> AttrSpec:
    return AttrSpec(name, 2, f"case when {condition} then 1 else 0 end", "flag", ("no", "yes"))


def nullable(name: str, source: str, size: int) -> AttrSpec:
    """0..size-1, and null as a code of its own."""
    return AttrSpec(name, size + 1, f"case when {source} is null then {size} else {_clamped(source, size)} end", "nullable")


def encode(df: DataFrame, spec: DomainSpec) -> DataFrame:
    """The codes of every record: one projection, no shuffle, no Python."""
    return df.select(*[F.expr(a.rule).cast("int").alias(a.name) for a in spec.attrs])


def validate(codes: DataFrame, spec: DomainSpec) -> DataFrame:
    """One row: records, and those with a code outside its domain (0 for anything from encode)."""
    bad = " or ".join(f"{a.name} is null or {a.name} not between 0 and {a.size - 1}" for a in spec.attrs)
    return codes.agg(F.count("*").alias("n"), F.count_if(F.expr(bad)).alias("n_bad"))


def decode(codes: DataFrame, spec: DomainSpec) -> DataFrame:
    """Labels in place of codes (the codes of attributes without labels stay)."""
    label = lambda a: F.element_at(F.array(*[F.lit(x) for x in a.labels]), F.col(a.name) + 1) if a.labels else F.col(a.name)
    return codes.select(*[label(a).alias(a.name) for a in spec.attrs])


def recode(labelled: DataFrame, spec: DomainSpec) -> DataFrame:
    """Inverse of decode."""
    place = lambda a: (F.array_position(F.array(*[F.lit(x) for x in a.labels]), F.col(a.name)) - 1).cast("int") if a.labels else F.col(a.name)
    return labelled.select(*[place(a).alias(a.name) for a in spec.attrs])
