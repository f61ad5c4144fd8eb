"""Marginals: contingency tables over attribute subsets, many of them in one scan."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec, attrs_of, marginal_id
from dpsynth.functions import cell
from dpsynth.plans import cover_plan

Subset = tuple[int, ...]
STORE = "marginal_id long, cell long, cnt long"
#: Cells that a task may count densely, 8 bytes each.
TASK_CELLS = 4_000_000
#: Cells of a wide set that a task counts in place of the sets inside it, and records that it counts at a time.
WIDE_CELLS, TASK_ROWS = 32_768, 65_536
#: So many rows a record are cheaper as additions in numpy than as rows of a partial aggregate.
ARROW_SETS = 8


def marginal(codes: DataFrame, spec: DomainSpec, subset: Sequence[int], dense: bool = False, weight: str | None = None) -> DataFrame:
    """cell, cnt of one subset; dense: every cell of the domain, zeros included."""
    count = F.sum(weight) if weight else F.count("*")
    counted = codes.groupBy(cell(spec, subset).alias("cell")).agg(count.cast("long").alias("cnt"))
    if not dense:
        return counted
    every = codes.sparkSession.range(spec.size(subset)).withColumnRenamed("id", "cell")
    return every.join(counted, "cell", "left").select("cell", F.coalesce("cnt", F.lit(0).cast("long")).alias("cnt"))


def marginals(codes: DataFrame, spec: DomainSpec, subsets: Iterable[Subset], plan: str = "auto") -> DataFrame:
    """marginal_id, cell, cnt of all subsets in one scan of the records.

    auto: arrow from ARROW_SETS sets on, where all cells together fit a task (TASK_CELLS), else
    inline.  inline: each record gives a row per subset to a partial aggregate.  grouping_sets: the same
    by Expand.  arrow: dense counts per task in numpy (8 bytes a cell) of
    wide sets that hold the subsets, summed over tasks.
    """
    subsets = list(dict.fromkeys(tuple(r) for r in subsets))
    if plan == "auto":
        plan = "arrow" if len(subsets) >= ARROW_SETS and sum(map(spec.size, subsets)) <= TASK_CELLS else "inline"
    if plan == "grouping_sets":
        return _by_grouping_sets(codes, spec, subsets)
    if plan == "arrow":
        return _by_arrow(codes, spec, subsets)
    rows = codes.select(F.inline(F.array(*[F.struct(F.lit(marginal_id(r)).cast("long").alias("marginal_id"), cell(spec, r).alias("cell")) for r in subsets])))
    return rows.groupBy("marginal_id", "cell").agg(F.count("*").alias("cnt"))


def _by_grouping_sets(codes: DataFrame, spec: DomainSpec, subsets: list[Subset]) -> DataFrame:
    used = sorted({i for r in subsets for i in r})
    names = [spec.attrs[i].name for i in used]
    grouped = codes.groupingSets([[spec.attrs[i].name for i in r] for r in subsets], *names).agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid"))
    out = None
    for r in subsets:  # grouping_id has a bit, first name highest, for each name that is summed over
        gid = sum(1 << (len(used) - 1 - k) for k, i in enumerate(used) if i not in r)
        case = F.when(F.col("gid") == gid, F.struct(F.lit(marginal_id(r)).cast("long").alias("marginal_id"), cell(spec, r).alias("cell")))
        out = case if out is None else F.coalesce(out, case)
    return grouped.select(out.alias("x"), "cnt").select("x.marginal_id", "x.cell", "cnt")


def _wide_sets(subsets: list[Subset], spec: DomainSpec) -> dict[Subset, list[Subset]]:
    """Sets that a task counts, each with those of ``subsets`` that are sums over it."""
    below: dict[Subset, list[Subset]] = {}
    for r, wide in cover_plan(subsets, spec, WIDE_CELLS).items():
        below.setdefault(wide, []).append(r)
    return below if sum(map(spec.size, below)) <= TASK_CELLS else {r: [r] for r in subsets}


def _by_arrow(codes: DataFrame, spec: DomainSpec, subsets: list[Subset]) -> DataFrame:
    """A record is added to a few wide tables; the subsets are summed from these once a task."""
    used, sizes = sorted({i for r in subsets for i in r}), spec.sizes
    # per wide set: its attributes, and (marginal_id, axes to sum over) of the subsets below it
    plan = [(wide, [(marginal_id(r), tuple(k for k, i in enumerate(wide) if i not in r)) for r in below]) for wide, below in _wide_sets(subsets, spec).items()]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [np.zeros([sizes[i] for i in wide], np.int64) for wide, _ in plan]

        def add(held: list[pa.RecordBatch]) -> None:
            columns = {i: np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in held]).astype(np.int64) for k, i in enumerate(used)}
            for table, (wide, _) in zip(tables, plan, strict=True):
                at = columns[wide[0]]
                for i in wide[1:]:
                    at = at * sizes[i] + columns[i]
                table += np.bincount(at, minlength=table.size).reshape(table.shape)

        held, n = [], 0
        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= TASK_ROWS:
                add(held)
                held, n = [], 0
        if held:
            add(held)
        for table, (_, below) in zip(tables, plan, strict=True):
            for i, axes in below:
                total = table.sum(axes).ravel()
                at = np.flatnonzero(total)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), i)), pa.array(at), pa.array(total[at])], ["marginal_id", "cell", "cnt"])

    return codes.select(*[spec.names[i] for i in used]).mapInArrow(count, STORE).groupBy("marginal_id", "cell").agg(F.sum("cnt").alias("cnt"))


def rollup(store: DataFrame, spec: DomainSpec, wide_to_narrow: dict[Subset, list[Subset]]) -> DataFrame:
    """Marginals that are sums over wider ones in ``store``: one aggregation for all of them.

    What to sum over what is a small table (a row per narrow set, broadcast), so the plan's size
    does not grow with the number of sets, and its code stays within what can be compiled.
    """
    plan = []
    for wide, narrow in wide_to_narrow.items():
        weight = dict(zip(wide, spec.strides(wide), strict=True))
        plan += [(marginal_id(wide), marginal_id(r), [(weight[i], spec.attrs[i].size, w) for i, w in zip(r, spec.strides(r), strict=True)]) for r in narrow]
    table = store.sparkSession.createDataFrame(plan, "wide long, narrow long, digits array<struct<stride:long,size:long,weight:long>>")
    digit = lambda at, x: at + F.floor(F.col("cell") / x["stride"]) % x["size"] * x["weight"]  # noqa: E731  counts of cells are far below 2^53
    each = store.join(F.broadcast(table), F.col("marginal_id") == F.col("wide")).select(F.col("narrow").alias("marginal_id"), F.aggregate("digits", F.lit(0).cast("long"), digit).alias("cell"), "cnt")
    return each.groupBy("marginal_id", "cell").agg(F.sum("cnt").cast("long").alias("cnt"))


def merge_store(a: DataFrame, b: DataFrame) -> DataFrame:
    """Counts of two disjoint sets of records added up."""
    return a.unionByName(b).groupBy("marginal_id", "cell").agg(F.sum("cnt").cast("long").alias("cnt"))


def normalize(store: DataFrame) -> DataFrame:
    """Adds freq, the share of a cell in its marginal."""
    return store.withColumn("freq", F.col("cnt") / F.sum("cnt").over(Window.partitionBy("marginal_id")))


def densify(store: DataFrame, spec: DomainSpec, subsets: Iterable[Subset]) -> DataFrame:
    """Every cell of the subsets, zeros included: what a noisy release has to cover."""
    sizes = [(marginal_id(r), spec.size(r)) for r in dict.fromkeys(subsets)]
    every = store.sparkSession.createDataFrame(sizes, "marginal_id long, n long").select("marginal_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("cell"))
    return every.join(store, ["marginal_id", "cell"], "left").select("marginal_id", "cell", F.coalesce("cnt", F.lit(0).cast("long")).alias("cnt"))


class MarginalStore:
    """Exact marginals of a closure.  Trusted side: nothing of it leaves without noise.

    Built with one scan.  Where all cells together fit a task (TASK_CELLS) each task counts all
    sets densely in numpy; beyond, the wide sets of a cover plan are counted and all others are
    sums over them.
    """

    #: Cells that the driver may hold; beyond, scores are computed on executors.
    DRIVER_CELLS = 20_000_000

    def __init__(self, table: DataFrame, spec: DomainSpec, subsets: list[Subset], n: int):
        self.table, self.spec, self.subsets, self.n = table, spec, subsets, n
        self._dense: dict[Subset, np.ndarray] = {}

    @classmethod
    def build(cls, codes: DataFrame, spec: DomainSpec, subsets: Iterable[Subset], cap: int = 1_000_000, plan: str = "auto") -> MarginalStore:
        """plan: auto, direct (dense counts of every set) or cover (wide sets and roll-up)."""
        from pyspark import StorageLevel

        subsets = sorted({tuple(r) for r in subsets}, key=lambda r: (len(r), r))
        if plan == "direct" or plan == "auto" and sum(map(spec.size, subsets)) <= TASK_CELLS:
            table = marginals(codes, spec, subsets, "arrow")
        else:
            below: dict[Subset, list[Subset]] = {}
            for r, wide in cover_plan(subsets, spec, cap).items():
                below.setdefault(wide, []).append(r)
            table = rollup(marginals(codes, spec, below), spec, below)
        table = table.persist(StorageLevel.MEMORY_AND_DISK)
        first = marginal_id(subsets[0])
        n = table.where(F.col("marginal_id") == first).agg(F.sum("cnt")).first()[0] or 0
        return cls(table, spec, subsets, int(n))

    @property
    def cells(self) -> int:
        return sum(self.spec.size(r) for r in self.subsets)

    @property
    def on_driver(self) -> bool:
        """Whether all of the store may be brought to the driver."""
        return self.cells <= self.DRIVER_CELLS

    def dense(self, subset: Subset) -> np.ndarray:
        """One marginal as a vector; all of the store is fetched once where its size allows it.  Else
        each is fetched alone, and the last ones of DRIVER_CELLS cells in all are kept."""
        if subset not in self._dense:
            if not self.on_driver:
                rows = self.table.where(F.col("marginal_id") == marginal_id(subset)).select("cell", "cnt").toPandas()
                while self._dense and sum(map(len, self._dense.values())) + self.spec.size(subset) > self.DRIVER_CELLS:
                    del self._dense[next(iter(self._dense))]
                self._dense[subset] = self._vector(rows, subset)
            else:
                frame = self.table.toPandas()
                for i, rows in frame.groupby("marginal_id"):
                    self._dense[attrs_of(int(i))] = self._vector(rows, attrs_of(int(i)))
                for r in self.subsets:
                    self._dense.setdefault(r, np.zeros(self.spec.size(r)))
        return self._dense[subset]

    def _vector(self, rows: pd.DataFrame, subset: Subset) -> np.ndarray:
        out = np.zeros(self.spec.size(subset))
        out[rows["cell"].to_numpy(np.int64)] = rows["cnt"].to_numpy(float)
        return out

    def close(self) -> None:
        self.table.unpersist()
