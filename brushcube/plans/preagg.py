"""Pre-aggregates: create once per (view, shape of the active clause, other clauses), answer every drag by merging cells."""

from __future__ import annotations

import threading
from collections import OrderedDict
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.clause import Clause
from ..model.pred import TRUE, Pred
from ..sources.store import Relations, Store
from ..views.spec import ViewSpec
from . import local, measures
from .measures import MeasurePlan, Options

#: Up to so many cells, an answer reads one cached partition: no exchange in the update query.
ONE_PARTITION = 1_000_000
#: Pre-aggregates that a session holds open (the least recently used close), and centres that it remembers.
OPEN, CENTRES = 64, 1000


@dataclass
class Cells:
    """A stored pre-aggregate and how to merge it."""

    name: str
    df: DataFrame
    keys: list[str]
    active: list[str]
    plan: MeasurePlan
    rows: int
    warm: bool = False
    bytes: int = 0
    near: local.LocalCells | None = None  # the cells in this process, once an update has asked for them
    far: bool = False  # they can't be merged here
    facts: dict = field(default_factory=dict)


def dimensions(view: ViewSpec, clause: Clause) -> list[tuple[str, str]]:
    """(alias, SQL) of the group keys, then of the active clause: raw columns of points, bins of intervals."""
    active = list(clause.meta.columns) if clause.meta.kind == "point" else clause.bins()
    return [*view.group, *((f"a_{i}", sql) for i, sql in enumerate(active))]


class PreAggregator:
    def __init__(self, spark: SparkSession, relations: Relations, store: Store, options: Options = Options(), gate: float | None = None):
        self.spark, self.relations, self.store, self.options, self.gate = spark, relations, store, options, gate
        self._open: OrderedDict[str, Cells] = OrderedDict()
        self._centres: dict[tuple, dict[str, float]] = {}
        self._guard = threading.Lock()
        self._names: OrderedDict[tuple, str] = OrderedDict()

    # -- definition -------------------------------------------------------------------------------------------------
    def centres(self, view: ViewSpec, residual: Pred) -> dict[str, float]:
        """Constants near the means. Any constant is right; a near one keeps sums of squares from cancelling."""
        inputs, mode = measures.centred_inputs(view.aggs), self.options.centre
        if not inputs or mode == "none":
            return {}
        if mode == "constant":
            return {k: v for k, v in self.options.constants if k in inputs}
        r = self.relations.get(view.source)
        key = (r.name, r.snapshot, residual.sql(), view.derive, tuple(inputs), mode)
        if key not in self._centres:
            if len(self._centres) >= CENTRES:
                self._centres.clear()
            rows = view.steps(r.df).where(residual.column())
            if mode == "sample":
                rows = rows.sample(0.01, 42)
            means = rows.agg(*[F.avg(F.expr(f"CAST({x} AS DOUBLE)")).alias(f"c{i}") for i, x in enumerate(inputs)]).first()
            self._centres[key] = {x: means[i] if means[i] is not None and means[i] == means[i] and abs(means[i]) < 1e300 else 0.0 for i, x in enumerate(inputs)}
        return self._centres[key]

    def definition(self, view: ViewSpec, clause: Clause, residual: Pred, centres: dict[str, float], plan: MeasurePlan) -> dict:
        r = self.relations.get(view.source)
        return {"source": r.name, "snapshot": r.snapshot, "derive": view.derive, "explode": view.explode, "inner": view.inner_keys, "residual": residual.sql(),
                "dims": dimensions(view, clause), "stats": sorted(plan.text.items()), "centres": sorted(centres.items())}

    # -- creation ---------------------------------------------------------------------------------------------------
    def create(self, view: ViewSpec, clause: Clause, residual: Pred, plan: MeasurePlan) -> DataFrame:
        """Filter, bin, group: one scan of the columns that dims and statistics need."""
        rows = view.steps(self.relations.get(view.source).df.where(residual.column()) if not view.derive else self.relations.get(view.source).df)
        if view.derive:
            rows = rows.where(residual.column())
        dims = [F.expr(sql).alias(a) for a, sql in dimensions(view, clause)]
        stats = list(plan.create.values()) or [F.count(F.lit(1)).alias("m_rows")]
        return rows.groupBy(*dims).agg(*stats)

    def ensure(self, view: ViewSpec, clause: Clause, residual: Pred = TRUE) -> Cells:
        """The cells, found by name in this session, in the store, or built. Concurrent callers share one build."""
        r = self.relations.get(view.source)
        asked = (view, clause.meta, residual.sql(), r.name, r.snapshot)
        with self._guard:
            if (found := self._open.get(self._names.get(asked, ""))) is not None:
                self._open.move_to_end(found.name)
                self.store.hits += 1
                return found
        centres = self.centres(view, residual)
        plan = measures.plan(view.aggs, centres, self.options)
        name = self.store.fingerprint(self.definition(view, clause, residual, centres, plan))
        with self.store.lock(name):
            if (found := self._open.get(name)) is not None:
                self.store.hits += 1
                with self._guard:
                    if name in self._open:
                        self._open.move_to_end(name)
                        self._names[asked] = name
                return found
            if self.store.exists(name):
                self.store.hits += 1
                df = self.store.read(name)
            else:
                df = self.store.publish(name, self.create(view, clause, residual, plan), {"view": view.id, "source": view.source})
            rows = df.count()  # Parquet footers
            if rows <= ONE_PARTITION:
                df = df.coalesce(1).cache()
            dims = [a for a, _ in dimensions(view, clause)]
            cells = Cells(name, df, dims[: len(view.group)], dims[len(view.group):], plan, rows, rows <= ONE_PARTITION, self.store.size_bytes(name), facts=self.store.facts(name))
            with self._guard:
                self._open[name], self._names[asked] = cells, name
                while len(self._names) > 16 * OPEN:
                    self._names.popitem(last=False)
                while len(self._open) > OPEN:
                    self._open.popitem(last=False)[1].df.unpersist()
            return cells

    def worth(self, view: ViewSpec, clause: Clause, residual: Pred = TRUE) -> float:
        """Estimated cells per row: near 1 where a pre-aggregate doesn't shrink anything. A distinct count by sketch over all rows, since the distinct share
        of a sample says little about that of the table (rows rarely meet in a sample)."""
        rows = view.steps(self.relations.get(view.source).df).where(residual.column())
        got = rows.agg(F.approx_count_distinct(F.struct(*[F.expr(s).alias(a) for a, s in dimensions(view, clause)])).alias("d"), F.count("*").alias("n")).first()
        return got["d"] / got["n"] if got["n"] else 1.0

    # -- answers ----------------------------------------------------------------------------------------------------
    def answer(self, cells: Cells, view: ViewSpec, clause: Clause) -> DataFrame:
        """Filter bins, merge statistics, read the aggregates off. A cleared clause merges all cells."""
        df = cells.df
        if not clause.cleared:
            df = df.where(clause.bin_predicate(cells.active).column())
        merged = df.groupBy(*cells.keys).agg(*(cells.plan.merge.values() or [F.count(F.lit(1)).alias("m_rows")]))
        return view.after(merged.select(*cells.keys, *cells.plan.read.values()))

    def merged(self, cells: Cells, view: ViewSpec, clause: Clause) -> tuple[pa.Table, str]:
        """(answer, where it was merged): in this process if the cells are within ``local``'s bounds and its terms, else by Spark."""
        if not cells.far and cells.rows <= local.LOCAL_ROWS and cells.bytes <= local.LOCAL_BYTES and local.fits(view, clause):
            with self.store.lock(f"{cells.name}|{view}"):
                if cells.near is None:
                    cells.near = local.fetch(cells.df, cells.keys, cells.active, cells.plan, view)
                    cells.far = cells.near is None
            if cells.near is not None:
                return local.answer(cells.near, view, clause), "process"
        return self.answer(cells, view, clause).toArrow(), "spark"

    def forget(self) -> None:
        for c in self._open.values():
            c.df.unpersist()
        self._open.clear()


# -- the direct path: fallback and baseline -------------------------------------------------------------------------------
_BUILTIN = {"count": F.count, "sum": F.sum, "max": F.max, "min": F.min, "product": F.product, "bit_and": F.bit_and, "bit_or": F.bit_or, "bit_xor": F.bit_xor, "bool_and": F.bool_and,
            "bool_or": F.bool_or, "avg": F.avg, "var_samp": F.var_samp, "var_pop": F.var_pop, "stddev_samp": F.stddev_samp, "stddev_pop": F.stddev_pop, "arg_max": F.max_by, "arg_min": F.min_by,
            "covar_samp": F.covar_samp, "covar_pop": F.covar_pop, "regr_count": F.regr_count, "regr_avgx": F.regr_avgx, "regr_avgy": F.regr_avgy, "regr_sxx": F.regr_sxx, "regr_syy": F.regr_syy,
            "regr_sxy": F.regr_sxy, "regr_intercept": F.regr_intercept, "regr_slope": F.regr_slope, "regr_r2": F.regr_r2, "median": F.median}


def _direct_agg(a) -> Column:
    args = [F.lit(1) if x == "*" else F.expr(x) for x in ((a.args[0], a.ordering()) if a.first else a.args)]
    if a.where:
        args = [F.when(F.expr(a.where), x) for x in args]
    if a.distinct:
        return F.count_distinct(*args).alias(a.alias)
    if a.fn in measures.EXTRA:
        create, _, read = measures.EXTRA[a.fn]
        return read(create(*args)).alias(a.alias)
    if a.fn == "corr":  # the builtin raises on zero variance in ANSI mode
        sd = F.stddev_pop(F.when(args[1].isNotNull(), args[0])) * F.stddev_pop(F.when(args[0].isNotNull(), args[1]))
        return F.when(sd != 0, F.try_divide(F.covar_pop(*args), sd)).alias(a.alias)
    if a.fn == "geomean":
        v = args[0].cast("double")
        return F.when(F.min(v) < 0, None).when(F.min(v) == 0, 0.0).otherwise(F.exp(F.avg(F.when(v > 0, F.log(v))))).alias(a.alias)
    return _BUILTIN[a.fn](*args).alias(a.alias)


def direct(view: ViewSpec, base: DataFrame, pred: Pred = TRUE) -> DataFrame:
    """The filtered view query over the base relation, with Spark's own aggregates."""
    rows = view.steps(base).where(pred.column()) if view.derive else view.steps(base.where(pred.column()))
    if view.raw:
        return view.after(rows.select(*[F.expr(s).alias(a) for a, s in view.group]))
    group = [F.expr(s).alias(a) for a, s in view.group]
    if not view.aggs:
        return view.after(rows.select(*group).distinct())
    return view.after(rows.groupBy(*group).agg(*[_direct_agg(a) for a in view.aggs]))
