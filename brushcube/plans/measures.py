"""Aggregates as sufficient statistics: what a pre-aggregate stores, how cells merge, how the answer is read off.

Every statistic is itself mergeable. Statistics are shared between aggregates (the bivariate family of one (y, x) needs
six sums and four extremes in all). Sums of squares are taken about a constant centre, since sums about zero cancel.
"No variance" is decided by min = max, not by a rounded difference.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.safe import clamp, count_or_zero, ratio
from ..views.spec import FUNCTIONS, Agg
from .local import Local

#: Values that a sketch of heavy hitters keeps.
TRACKED = 10_000
#: Registered by users: name -> (statistics per cell, merge of each, result). See ``register_measure``.
EXTRA: dict[str, tuple[Callable, Callable, Callable]] = {}


@dataclass(frozen=True)
class Options:
    """``avg``: weighted (averages and counts) or sum; ``centre``: global, sample, constant or none."""

    avg: str = "weighted"
    centre: str = "global"
    constants: tuple[tuple[str, float], ...] = ()


class Spark:
    """What reads of answers are made of, here over columns; ``local.Local`` has the same names over numpy arrays."""

    col, lit, when, sqrt, exp = (staticmethod(f) for f in (F.col, F.lit, F.when, F.sqrt, F.exp))
    ratio, clamp, count_or_zero = (staticmethod(f) for f in (ratio, clamp, count_or_zero))


@dataclass
class MeasurePlan:
    """create: name -> statistic over rows; merge: name -> merge over cells; read: alias -> answer over merged statistics. ``kinds`` and ``local``:
    the same merges and reads for cells that are merged in this process (no kind: by Spark only)."""

    create: dict[str, Column] = field(default_factory=dict)
    merge: dict[str, Column] = field(default_factory=dict)
    read: dict[str, Column] = field(default_factory=dict)
    text: dict[str, str] = field(default_factory=dict)
    kinds: dict[str, str | None] = field(default_factory=dict)
    local: dict = field(default_factory=dict)

    def stat(self, text: str, column: Column, merge: Callable[[Column], Column], kind: str | None = None) -> str:
        for name, t in self.text.items():
            if t == text:
                return name
        name = f"m_{len(self.text)}"
        self.text[name], self.create[name], self.merge[name] = text, column.alias(name), merge(F.col(name)).alias(name)
        self.kinds[name] = kind or {F.sum: "sum", F.min: "min", F.max: "max"}.get(merge)
        return name


def centred_inputs(aggs: tuple[Agg, ...]) -> list[str]:
    """Inputs whose squares or products are summed."""
    out = []
    for a in aggs:
        if a.fn.startswith(("var_", "stddev_", "covar_", "corr", "regr_")) and a.fn != "regr_count":
            out += [x for x in a.args if x not in out]
    return out


def plan(aggs: tuple[Agg, ...], centres: dict[str, float] | None = None, options: Options = Options()) -> MeasurePlan:
    p, centres = MeasurePlan(), centres or {}
    for a in aggs:
        if a.fn not in FUNCTIONS and a.fn not in EXTRA:
            raise ValueError(f"unsupported aggregate {a.fn}")
        p.read[a.alias] = _one(p, a, centres, options).alias(a.alias)
        if a.fn not in EXTRA:
            p.local[a.alias] = _one(p, a, centres, options, Local)
    return p


def _one(p: MeasurePlan, a: Agg, centres: dict[str, float], options: Options, on=Spark):
    """The answer over merged statistics (which the plan gets, if it hasn't them), in columns or in the terms of ``on``."""
    ratio, clamp, count_or_zero = on.ratio, on.clamp, on.count_or_zero
    mark = f" where {a.where}" if a.where else ""
    within = (lambda c: F.when(F.expr(a.where), c)) if a.where else (lambda c: c)
    col = lambda sql: within(F.expr(sql))
    add = lambda text, column, merge: on.col(p.stat(text + mark, column, merge))
    if a.fn in EXTRA:
        create, merge, read = EXTRA[a.fn]
        return read(add(f"{a.fn}({', '.join(a.args)})", create(*[col(x) for x in a.args]), merge))
    x = a.args[0]
    n = lambda x: add(f"count({x})", F.count(within(F.lit(1)) if x == "*" else col(x)), F.sum)
    if a.fn == "count":
        return count_or_zero(n(x))
    simple = {"sum": F.sum, "max": F.max, "min": F.min, "product": F.product, "bit_and": F.bit_and, "bit_or": F.bit_or, "bit_xor": F.bit_xor, "bool_and": F.bool_and, "bool_or": F.bool_or}
    if a.fn in simple:
        return add(f"{a.fn}({x})", simple[a.fn](col(x)), simple[a.fn])
    if a.fn == "avg":
        if options.avg == "sum":
            return ratio(add(f"sum({x})", F.sum(col(x)), F.sum).cast("double"), n(x))
        count = p.stat(f"count({x}){mark}", F.count(col(x)), F.sum)
        cells = F.col(count)
        name = p.stat(f"avg({x}){mark}", F.avg(col(x)), lambda c: Spark.ratio(F.sum(c * cells), F.sum(F.when(c.isNotNull(), cells))), f"avg:{count}")
        return on.col(name)
    if a.fn == "geomean":
        v = F.expr(f"CAST({x} AS DOUBLE)")
        logs = add(f"sum(ln {x})", F.sum(within(F.when(v > 0, F.log(v)))), F.sum)
        zero = add(f"zeros {x}", F.count(within(F.when(v == 0, 1))), F.sum)
        below = add(f"negatives {x}", F.count(within(F.when(v < 0, 1))), F.sum)
        return on.when(below > 0, None).when(zero > 0, 0.0).otherwise(on.exp(ratio(logs, n(x))))
    if a.fn in ("arg_max", "arg_min"):
        by = a.ordering()
        pick, ext = (F.max_by, F.max) if a.fn == "arg_max" else (F.min_by, F.min)
        far = p.stat(f"{a.fn} order({by}){mark}", ext(col(by)), ext)
        # the ordering column of the cells, not the merged one: both bear the same name, and inside an aggregate it is the cells'
        return on.col(p.stat(f"{a.fn}({x}, {by}){mark}", pick(col(x), col(by)), lambda c: pick(c, F.col(far))))
    if a.fn.startswith(("var_", "stddev_")):
        k = F.lit(float(centres.get(x, 0.0)))
        d = F.expr(f"CAST({x} AS DOUBLE)") - k
        s, q = add(f"sum({x} - k)", F.sum(within(d)), F.sum), add(f"sum(({x} - k)^2)", F.sum(within(d * d)), F.sum)
        lo, hi = add(f"min({x})", F.min(col(x)), F.min), add(f"max({x})", F.max(col(x)), F.max)
        m = on.when(lo == hi, 0.0).otherwise(clamp(q - ratio(s * s, n(x))))
        out = ratio(m, n(x) - (1 if a.fn.endswith("samp") else 0))
        out = on.when(n(x) > (1 if a.fn.endswith("samp") else 0), out)
        return on.sqrt(out) if a.fn.startswith("stddev") else out
    y, x = a.args
    k, h = float(centres.get(x, 0.0)), float(centres.get(y, 0.0))
    fy, fx = F.expr(f"CAST({y} AS DOUBLE)"), F.expr(f"CAST({x} AS DOUBLE)")
    pair = lambda c: within(F.when(fy.isNotNull() & fx.isNotNull(), c))
    tag = f"[{y}, {x}]"
    n2 = add(f"count {tag}", F.count(pair(F.lit(1))), F.sum)
    if a.fn == "regr_count":
        return count_or_zero(n2)
    dx, dy = fx - k, fy - h
    sx, sy = add(f"sx {tag}", F.sum(pair(dx)), F.sum), add(f"sy {tag}", F.sum(pair(dy)), F.sum)
    if a.fn == "regr_avgx":
        return on.lit(k) + ratio(sx, n2)
    if a.fn == "regr_avgy":
        return on.lit(h) + ratio(sy, n2)
    flat = lambda v, name: add(f"min {name} {tag}", F.min(pair(v)), F.min) == add(f"max {name} {tag}", F.max(pair(v)), F.max)
    sxx = lambda: on.when(flat(fx, "x"), 0.0).otherwise(clamp(add(f"sxx {tag}", F.sum(pair(dx * dx)), F.sum) - ratio(sx * sx, n2)))
    syy = lambda: on.when(flat(fy, "y"), 0.0).otherwise(clamp(add(f"syy {tag}", F.sum(pair(dy * dy)), F.sum) - ratio(sy * sy, n2)))
    sxy = lambda: on.when(flat(fx, "x"), 0.0).when(flat(fy, "y"), 0.0).otherwise(add(f"sxy {tag}", F.sum(pair(dx * dy)), F.sum) - ratio(sx * sy, n2))
    if a.fn == "covar_samp":
        return on.when(n2 > 1, ratio(sxy(), n2 - 1))
    if a.fn == "covar_pop":
        return ratio(sxy(), n2)
    if a.fn == "corr":
        return on.when(~flat(fx, "x") & ~flat(fy, "y"), ratio(sxy(), on.sqrt(sxx() * syy())))
    if a.fn in ("regr_sxx", "regr_syy", "regr_sxy"):
        return {"regr_sxx": sxx, "regr_syy": syy, "regr_sxy": sxy}[a.fn]()
    slope = on.when(~flat(fx, "x"), ratio(sxy(), sxx()))
    if a.fn == "regr_slope":
        return slope
    if a.fn == "regr_intercept":
        return on.lit(h) + ratio(sy, n2) - slope * (on.lit(k) + ratio(sx, n2))
    return on.when(flat(fx, "x"), None).when(flat(fy, "y"), 1.0).otherwise(ratio(sxy() * sxy(), sxx() * syy()))


def register_measure(name: str, create: Callable, merge: Callable, read: Callable = lambda c: c, args: int = 1) -> None:
    """Any mergeable aggregate as a measure: ``create(*columns)`` per cell, ``merge(cell column)``, ``read(merged)``. All of it in Catalyst."""
    EXTRA[name] = (create, merge, read)


def register_sketches() -> None:
    """Approximate distinct counts (HLL, theta), quantiles (KLL), heavy hitters and exact distinct ids (bitmap) as mergeable measures."""
    register_measure("approx_distinct", F.hll_sketch_agg, F.hll_union_agg, F.hll_sketch_estimate)
    register_measure("theta_distinct", F.theta_sketch_agg, F.theta_union_agg, F.theta_sketch_estimate)
    kll = lambda q: lambda c: F.kll_sketch_get_quantile_double(c, F.lit(q))
    for name, q in (("kll_median", 0.5), ("kll_p90", 0.9), ("kll_p99", 0.99)):
        register_measure(name, lambda c: F.kll_sketch_agg_double(c.cast("double")), F.kll_merge_agg_double, kll(q))
    # heavy hitters: counts are exact while a cell and their union have fewer values than are tracked
    call = F.call_function
    register_measure("top_5", lambda c: call("approx_top_k_accumulate", c, F.lit(TRACKED)), lambda c: call("approx_top_k_combine", c, F.lit(TRACKED)), lambda c: call("approx_top_k_estimate", c, F.lit(5)))
    register_measure("bitmap_distinct", lambda c: F.bitmap_construct_agg(F.bitmap_bit_position(c)), F.bitmap_or_agg, F.bitmap_count)
