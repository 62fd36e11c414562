"""Baselines: dense tiles, prefix-sum tiles, aggregation outside Spark, a hand-written cube."""

from __future__ import annotations

from dataclasses import dataclass
from math import prod

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..model.clause import Clause
from ..model.pred import TRUE, Pred
from ..views.spec import ViewSpec


class OverBudget(MemoryError):
    """A dense representation would hold more values than allowed."""


@dataclass(frozen=True)
class Axis:
    """A bin dimension with its first bin and number of bins."""

    name: str
    sql: str
    first: int
    count: int


def axes_of(clause: Clause) -> list[Axis]:
    out = []
    for i, (sql, s) in enumerate(zip(clause.bins(), clause.meta.scales, strict=True)):
        ends = sorted(s.bin_value(d, clause.meta.step, clause.meta.rule) for d in s.domain)
        out.append(Axis(f"a_{i}", sql, ends[0], ends[1] - ends[0] + 1))
    return out


def _cells(base: DataFrame, axes: list[Axis], weight: str | None) -> DataFrame:
    rows = base.select(*[F.expr(a.sql).alias(a.name) for a in axes], *([F.expr(weight).alias("w")] if weight else []))
    for a in axes:
        rows = rows.where(F.col(a.name).between(a.first, a.first + a.count - 1))
    return rows.groupBy(*[a.name for a in axes]).agg((F.sum("w") if weight else F.count("*")).cast("double").alias("v"))


class DenseTile:
    """All bin combinations of keys and active dimensions in one array. COUNT and SUM only; refuses above ``budget`` values."""

    def __init__(self, keys: list[Axis], active: list[Axis], values: np.ndarray):
        self.keys, self.active, self.values = keys, active, values

    @classmethod
    def build(cls, base: DataFrame, keys: list[Axis], clause: Clause, weight: str | None = None, budget: int = 50_000_000) -> DenseTile:
        active = axes_of(clause)
        size = prod(a.count for a in [*keys, *active])
        if size > budget:
            raise OverBudget(f"{size} values exceed {budget}")
        values = np.zeros([a.count for a in [*keys, *active]])
        axes = [*keys, *active]
        got = _cells(base, axes, weight).toPandas()  # at most ``budget`` cells
        values[tuple(got[a.name].to_numpy() - a.first for a in axes)] = got["v"].to_numpy()
        return cls(keys, active, values)

    def answer(self, *ranges: tuple[int, int]) -> np.ndarray:
        """Sums per key for inclusive bin ranges."""
        cut = tuple(slice(max(0, lo - a.first), max(0, hi - a.first + 1)) for a, (lo, hi) in zip(self.active, ranges, strict=True))
        return self.values[(..., *cut)].sum(axis=tuple(range(len(self.keys), self.values.ndim)))


class PrefixTile(DenseTile):
    """A dense tile summed up along its active axes: an answer is 2^m corner values per key."""

    def __init__(self, keys: list[Axis], active: list[Axis], values: np.ndarray):
        for d in range(len(keys), values.ndim):
            values = values.cumsum(axis=d)
        super().__init__(keys, active, values)

    def answer(self, *ranges: tuple[int, int]) -> np.ndarray:
        out = 0.0
        for corner in range(1 << len(ranges)):
            at, sign, zero = [], 1, False
            for i, (a, (lo, hi)) in enumerate(zip(self.active, ranges, strict=True)):
                k = (lo - 1 if corner >> i & 1 else hi) - a.first
                sign = -sign if corner >> i & 1 else sign
                zero |= k < 0
                at.append(min(k, a.count - 1))
            if not zero:
                out = out + sign * self.values[(..., *at)]
        return out if not np.isscalar(out) else np.zeros([a.count for a in self.keys])


def dense_frame(base: DataFrame, keys: list[Axis], clause: Clause, weight: str | None = None, budget: int = 50_000_000) -> DataFrame:
    """The dense tile as a DataFrame: the grid of all bins, left-joined with the cells."""
    axes = [*keys, *axes_of(clause)]
    size = prod(a.count for a in axes)
    if size > budget:
        raise OverBudget(f"{size} values exceed {budget}")
    grid = base.sparkSession.range(size)
    stride = size
    for a in axes:  # the grid comes from one range, so no cross join is needed
        stride //= a.count
        grid = grid.withColumn(a.name, F.lit(a.first) + F.floor(F.col("id") / stride) % a.count)
    cells = _cells(base, axes, weight)
    return grid.drop("id").join(cells, [a.name for a in axes], "left").fillna(0.0, ["v"])


def prefix_frame(dense: DataFrame, keys: list[str], active: list[str]) -> DataFrame:
    """Running sums along every active axis in turn."""
    for a in active:
        others = [c for c in (*keys, *active) if c != a]
        dense = dense.withColumn("v", F.sum("v").over(W.partitionBy(*others).orderBy(a).rowsBetween(W.unboundedPreceding, 0)))
    return dense


def runtime_frame(view: ViewSpec, base: DataFrame, pred: Pred = TRUE) -> DataFrame:
    """Proxy for systems that aggregate in the interface's own runtime: Spark filters, all rows cross over as Arrow, Python counts batch by batch
    (one count per key and batch comes back). Of one count per key; keys are the view's."""
    keys = view.steps(base).where(pred.column()).select(*[F.expr(sql).alias(a) for a, sql in view.group])
    names, count = [a for a, _ in view.group], view.aggs[0].alias

    def counts(batches):
        for b in batches:
            yield b.groupby(names, dropna=False).size().rename(count).reset_index()

    schema = ", ".join([f"`{a}` {k}" for a, k in keys.dtypes] + [f"`{count}` bigint"])
    return keys.mapInPandas(counts, schema).groupBy(*names).agg(F.sum(count).alias(count))


def cube_baseline(base: DataFrame, dims: dict[str, str], measure: str) -> DataFrame:
    """A hand-written data cube over binned dimensions."""
    rows = base.select(*[F.expr(s).alias(a) for a, s in dims.items()], F.expr(measure).alias("m"))
    return rows.cube(*dims).agg(F.count("*").alias("n"), F.sum("m").alias("s"))
