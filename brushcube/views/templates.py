"""View templates: the queries of charts, tables and widgets, as ViewSpecs."""

from __future__ import annotations

from ..functions.safe import text_number as num
from ..model.scales import Scale
from .spec import Agg, ViewSpec


def histogram(id: str, source: str, col: str, width: float, origin: float = 0.0, weight: str | None = None) -> ViewSpec:
    """1-D histogram of fixed bins in data units."""
    w, o = num(float(width)), num(float(origin))
    return ViewSpec(id, source, (("x", f"{o} + {w} * floor((CAST({col} AS DOUBLE) - {o}) / {w})"),), (Agg("y", "sum", (weight,)) if weight else Agg("y", "count"),), True)


def raster(id: str, source: str, xcol: str, ycol: str, xscale: Scale, yscale: Scale, step: float = 1, weight: str | None = None) -> ViewSpec:
    """2-D density raster at pixel resolution."""
    agg = Agg("n", "sum", (weight,)) if weight else Agg("n", "count")
    return ViewSpec(id, source, (("x", xscale.bin_sql(xcol, step)), ("y", yscale.bin_sql(ycol, step))), (agg,), True)


def mean_ci(id: str, source: str, key: str, col: str, z: float = 1.96) -> ViewSpec:
    """Mean with a confidence interval per category."""
    half = f"{num(z)} * sd / sqrt(CAST(n AS DOUBLE))"
    return ViewSpec(id, source, (("key", key),), (Agg("mean", "avg", (col,)), Agg("sd", "stddev_samp", (col,)), Agg("n", "count", (col,))), True,
                    post=(("lo", f"mean - {half}"), ("hi", f"mean + {half}")))


def regression(id: str, source: str, y: str, x: str, by: tuple[tuple[str, str], ...] = ()) -> ViewSpec:
    """Linear fit, global or per key."""
    names = ("slope", "intercept", "r2", "count", "avgx", "avgy", "sxx", "syy", "sxy")
    return ViewSpec(id, source, tuple(by), tuple(Agg("n" if n == "count" else n, f"regr_{n}", (y, x)) for n in names), True)


def hexbin(id: str, source: str, x: str, y: str, radius: float) -> ViewSpec:
    """Hexagonal bins: of the nearest nodes of two lattices, half a cell apart, the nearer; ties to the first."""
    dx, dy = radius * 3 ** 0.5, radius * 3.0
    a = [f"{num(d)} * floor(CAST({c} AS DOUBLE) / {num(d)} + {num(0.5)})" for c, d in ((x, dx), (y, dy))]
    b = [f"{num(d)} * (floor(CAST({c} AS DOUBLE) / {num(d)}) + {num(0.5)})" for c, d in ((x, dx), (y, dy))]
    gap = lambda n: f"(({x} - {n}x) * ({x} - {n}x) + ({y} - {n}y) * ({y} - {n}y))"
    steps = (("hax", a[0]), ("hay", a[1]), ("hbx", b[0]), ("hby", b[1]))
    near = f"{gap('ha')} <= {gap('hb')}"
    return ViewSpec(id, source, (("cx", f"CASE WHEN {near} THEN hax ELSE hbx END"), ("cy", f"CASE WHEN {near} THEN hay ELSE hby END")), (Agg("n", "count"),), True, derive=steps)


def linear_density(id: str, source: str, x: str, xscale: Scale, y: str | None = None, yscale: Scale | None = None) -> ViewSpec:
    """Linear binning: a point's weight is split over the 2 (4) nearest grid nodes."""
    axes = [("u", xscale.position_sql(x)), *([("v", yscale.position_sql(y))] if y else [])]
    part = lambda u, k: (f"floor({u}) + {k}", f"({u} - floor({u}))" if k else f"(1 - ({u} - floor({u})))")
    stencil = [(part("u", i), part("v", j) if y else None) for i in (0, 1) for j in ((0, 1) if y else (0,))]
    cells = ", ".join(f"named_struct('x', CAST({a[0]} AS BIGINT), 'y', CAST({b[0] if b else 0} AS BIGINT), 'w', {a[1]}{' * ' + b[1] if b else ''})" for a, b in stencil)
    group = (("x", "cell.x"), ("y", "cell.y")) if y else (("x", "cell.x"),)
    return ViewSpec(id, source, group, (Agg("w", "sum", ("cell.w",)),), True, derive=tuple(axes), explode=(("cell", f"array({cells})"),))


def menu(id: str, source: str, col: str) -> ViewSpec:
    """Distinct values, as group keys without measures."""
    return ViewSpec(id, source, (("value", col),), (), True, order=("value",))


def table_window(id: str, source: str, cols: tuple[str, ...], sort: tuple[str, ...], offset: int, limit: int) -> ViewSpec:
    """Rows around the scroll position of a sortable table: never pre-aggregated."""
    return ViewSpec(id, source, tuple((c, c) for c in cols), raw=True, order=sort, offset=offset, limit=limit)


def scatter(id: str, source: str, x: str, y: str, key: str | None = None, limit: int | None = None) -> ViewSpec:
    cols = (("x", x), ("y", y), *((("key", key),) if key else ()))
    return ViewSpec(id, source, cols, raw=True, order=("key",) if key and limit else (), limit=limit)


def summary(id: str, source: str, aggs: tuple[Agg, ...]) -> ViewSpec:
    """Global aggregates: one row."""
    return ViewSpec(id, source, (), aggs, True)


def marginals(id: str, source: str, x: str, y: str, xscale: Scale, yscale: Scale, step: float = 1) -> tuple[ViewSpec, ViewSpec]:
    """Histograms along both axes, at fixed pixel bins."""
    one = lambda tag, c, s: ViewSpec(f"{id}_{tag}", source, (("x", s.bin_sql(c, step)),), (Agg("n", "count"),), True)
    return one("x", x, xscale), one("y", y, yscale)


def pixel_column(id: str, source: str, t: str, v: str, scale: Scale, tie: str | None = None) -> ViewSpec:
    """Per pixel column of a line: first, last, least and greatest points; of equal values the first in time. ``tie`` makes equal times unique."""
    order_t, order_v = (f"struct({t}, {tie})", f"struct({v}, {tie})") if tie else (t, v)
    aggs = (Agg("tmin", "min", (t,)), Agg("tmax", "max", (t,)), Agg("vmin", "min", (v,)), Agg("vmax", "max", (v,)), Agg("v_at_tmin", "arg_min", (v, order_t)), Agg("v_at_tmax", "arg_max", (v, order_t)),
            Agg("t_at_vmin", "arg_min", (t, order_v), first=t), Agg("t_at_vmax", "arg_max", (t, order_v), first=t))
    return ViewSpec(id, source, (("px", scale.bin_sql(t)),), aggs, True)


def rebinned(id: str, source: str, col: str, nbins: int) -> ViewSpec:
    """Bins that follow the filtered extent: not stable, so never pre-aggregated. ``lo`` and ``hi`` are the extent's columns."""
    return ViewSpec(id, source, (("x", f"floor({num(float(nbins))} * ({col} - lo) / (hi - lo))"),), (Agg("y", "count"),), False)
