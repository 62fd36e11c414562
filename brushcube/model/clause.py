"""Clauses: what an interactor says, with the metadata that lets the engine foresee the next ones."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from ..functions.safe import text_number
from .pred import TRUE, Match, PointIn, Pred, Range, Raw, both
from .scales import Scale

SNAPS = ("inclusive", "halfopen")


@dataclass(frozen=True)
class ClauseMeta:
    """Shape of a clause: point, interval or match; columns; scales, pixel step, rounding rule and snapping of intervals."""

    kind: str
    columns: tuple[str, ...] = ()
    scales: tuple[Scale, ...] = ()
    step: float = 1
    rule: str = "floor"
    snap: str = "inclusive"


@dataclass(frozen=True)
class Clause:
    """A predicate of a source, the views it does not filter under cross-filtering, metadata, and the values behind it."""

    source: str
    predicate: Pred
    views: frozenset[str] = frozenset()
    meta: ClauseMeta | None = None
    values: tuple = field(default=(), compare=False)

    @property
    def cleared(self) -> bool:
        return self.predicate == TRUE

    def bins(self) -> list[str]:
        """SQL of the bin of each column (intervals)."""
        m = self.meta
        return [s.bin_sql(c, m.step, m.rule) for c, s in zip(m.columns, m.scales, strict=True)]

    def bin_ends(self) -> list[tuple[str | None, str | None]]:
        """Per dimension the least and the greatest bin that the interval keeps, as SQL on literals (folded by the optimiser)."""
        m, out = self.meta, []
        for (lo, hi), s in zip(self.values, m.scales, strict=True):
            one = lambda v: s.bin_sql(text_number(float(v)), m.step, m.rule)  # noqa: B023, E731
            a, b = (None if v is None else one(v) for v in (lo, hi))
            if m.snap == "halfopen" and m.rule == "floor" and b is not None and s.bins(m.step) > 0:
                b = f"CAST(ceil({s.position_sql(text_number(float(hi)), m.step)}) - 1 AS BIGINT)"
            out.append((b, a) if s.bins(m.step) < 0 else (a, b))
        return out

    def bin_predicate(self, names: list[str] | None = None) -> Pred:
        """The clause at the resolution of its bins: over bin columns ``names``, else over the raw columns."""
        if self.cleared or self.meta.kind == "point":
            return self.predicate if not names else self.point_predicate(names)
        parts = []
        for name, (a, b) in zip(names or self.bins(), self.bin_ends(), strict=True):
            parts += [Raw(f"{name} >= {a}")] if a else []
            parts += [Raw(f"{name} <= {b}")] if b else []
        return both(*parts)

    def point_predicate(self, names: list[str]) -> Pred:
        return TRUE if self.cleared else PointIn(tuple(names), self.values)


def point(source: str, columns, values, views=()) -> Clause:
    """Equality with any of ``values`` (scalars for one column, tuples for several)."""
    cols = (columns,) if isinstance(columns, str) else tuple(columns)
    rows = tuple(v if isinstance(v, tuple) else (v,) for v in values)
    return Clause(source, PointIn(cols, rows), frozenset(views), ClauseMeta("point", cols), rows)


def interval_nd(source: str, columns, boxes, scales=None, step: float = 1, rule: str = "floor", views=(), snap: str = "inclusive") -> Clause:
    """A conjunction of ranges, one per column; without scales it can't be pre-aggregated."""
    cols = tuple(columns)
    boxes = tuple((None if a is None else float(a), None if b is None else float(b)) for a, b in boxes)
    boxes = tuple((min(a, b), max(a, b)) if a is not None and b is not None else (a, b) for a, b in boxes)
    return Clause(source, both(*[Range(c, a, b) for c, (a, b) in zip(cols, boxes, strict=True)]), frozenset(views), ClauseMeta("interval", cols, tuple(scales or ()), step, rule, snap), boxes)


def interval(source: str, column: str, ends, scale: Scale | None = None, step: float = 1, rule: str = "floor", views=(), snap: str = "inclusive") -> Clause:
    return interval_nd(source, (column,), (ends,), (scale,) if scale else (), step, rule, views, snap)


def slider(source: str, column: str, value: float, scale: Scale, step: float = 1, views=()) -> Clause:
    """column <= value, with bins rounded up so that the end is inside."""
    return interval(source, column, (None, value), scale, step, "ceil", views)


def match(source: str, column: str, text: str, kind: str = "contains", views=()) -> Clause:
    return Clause(source, Match(column, text, kind), frozenset(views), ClauseMeta("match", (column,)), (text, kind))


def clear(clause: Clause) -> Clause:
    """The interactor's input withdrawn; its shape stays known, so its pre-aggregates still serve."""
    return replace(clause, predicate=TRUE, values=())
