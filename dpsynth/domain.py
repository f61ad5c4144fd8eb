"""Declared finite domains.  Sizes are part of the declaration and never learned from data."""

from __future__ import annotations

import math
from collections.abc import Iterable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class AttrSpec:
    """One attribute: codes 0..size-1, the SQL rule that makes the code, what a code stands for."""

    name: str
    size: int
    rule: str
    kind: str = "code"
    labels: tuple[str, ...] = field(default=())

    def __post_init__(self):
        if self.size < 1:
            raise ValueError(f"{self.name}: a domain has at least one value")
        if self.labels and len(self.labels) != self.size:
            raise ValueError(f"{self.name}: {len(self.labels)} labels for {self.size} values")

    def label(self, code: int) -> str:
        return self.labels[code] if self.labels else str(code)


@dataclass(frozen=True)
class DomainSpec:
    """An ordered list of attributes."""

    attrs: tuple[AttrSpec, ...]

    @classmethod
    def of(cls, *attrs: AttrSpec) -> DomainSpec:
        if len({a.name for a in attrs}) < len(attrs):
            raise ValueError("two attributes have the same name")
        return cls(tuple(attrs))

    @classmethod
    def from_sizes(cls, sizes: Sequence[int]) -> DomainSpec:
        """A domain of columns a0, a1, ... that hold codes already."""
        return cls.of(*(AttrSpec(f"a{i}", n, f"a{i}") for i, n in enumerate(sizes)))

    @property
    def d(self) -> int:
        return len(self.attrs)

    @property
    def names(self) -> list[str]:
        return [a.name for a in self.attrs]

    @property
    def sizes(self) -> tuple[int, ...]:
        return tuple(a.size for a in self.attrs)

    def index(self, name: str) -> int:
        return self.names.index(name)

    def size(self, subset: Iterable[int] | None = None) -> int:
        """Number of cells over a subset (of all attributes by default); exact, may exceed 64 bits."""
        return math.prod(self.sizes if subset is None else (self.attrs[i].size for i in subset))

    def shape(self, subset: Iterable[int]) -> tuple[int, ...]:
        return tuple(self.attrs[i].size for i in subset)

    def strides(self, subset: Sequence[int]) -> list[int]:
        """Mixed-radix weights of a subset's codes in a cell number, last attribute fastest."""
        out, weight = [], 1
        for i in reversed(subset):
            out.append(weight)
            weight *= self.attrs[i].size
        return out[::-1]

    def to_df(self, spark: SparkSession) -> DataFrame:
        """The domain as a small table, one row per code."""
        rows = [(i, a.name, a.size, c, a.label(c)) for i, a in enumerate(self.attrs) for c in range(a.size)]
        return spark.createDataFrame(rows, "attr_id int, attr string, size int, code int, label string")


def marginal_id(subset: Iterable[int]) -> int:
    """Bit mask of an attribute subset; up to 62 attributes fit a BIGINT."""
    out = 0
    for i in subset:
        if i > 61:
            raise ValueError("bit masks hold 62 attributes; use surrogate ids beyond")
        out |= 1 << i
    return out


def attrs_of(mask: int) -> tuple[int, ...]:
    return tuple(i for i in range(mask.bit_length()) if mask >> i & 1)
