"""Interactors: input of the interface -> clauses. ``example`` stands for the first input before there is one."""

from __future__ import annotations

from dataclasses import dataclass, field

from .clause import Clause, clear, interval, interval_nd, match, point, slider
from .scales import Scale


@dataclass
class Interactor:
    source: str
    views: frozenset[str] = frozenset()
    last: Clause | None = field(default=None, init=False)

    def make(self, value) -> Clause:
        raise NotImplementedError

    def emit(self, value) -> Clause:
        """The clause of an input; None clears it."""
        self.last = clear(self.last or self.example()) if value is None else self.make(value)
        return self.last


@dataclass
class Menu(Interactor):
    """A list or menu: one value, or several."""

    column: str = ""

    def make(self, value) -> Clause:
        return point(self.source, self.column, value if isinstance(value, (list, tuple, set)) else [value], self.views)

    def example(self) -> Clause:
        return point(self.source, self.column, [None], self.views)


class Legend(Menu):
    """Entries of a legend."""


@dataclass
class Pick(Interactor):
    """Marks of a chart, by the values of their fields."""

    columns: tuple[str, ...] = ()

    def make(self, value) -> Clause:
        return point(self.source, self.columns, [tuple(v) for v in value], self.views)

    def example(self) -> Clause:
        return point(self.source, self.columns, [tuple(None for _ in self.columns)], self.views)


class RowPick(Pick):
    """Rows of a table."""


class Hover(Pick):
    """The mark under the pointer."""

    def make(self, value) -> Clause:
        return super().make([value])


@dataclass
class Brush(Interactor):
    """A drag along one axis, in data units."""

    column: str = ""
    scale: Scale = Scale()
    step: float = 1
    rule: str = "floor"

    def make(self, value) -> Clause:
        return interval(self.source, self.column, value, self.scale, self.step, self.rule, self.views)

    def example(self) -> Clause:
        return self.make(self.scale.domain)


class BrushX(Brush):
    pass


class BrushY(Brush):
    pass


@dataclass
class BrushXY(Interactor):
    """A rectangle."""

    columns: tuple[str, str] = ("", "")
    scales: tuple[Scale, Scale] = (Scale(), Scale())
    step: float = 1

    def make(self, value) -> Clause:
        return interval_nd(self.source, self.columns, value, self.scales, self.step, "floor", self.views)

    def example(self) -> Clause:
        return self.make(tuple(s.domain for s in self.scales))


@dataclass
class Slider(Interactor):
    column: str = ""
    scale: Scale = Scale()
    step: float = 1

    def make(self, value) -> Clause:
        return slider(self.source, self.column, value, self.scale, self.step, self.views)

    def example(self) -> Clause:
        return self.make(self.scale.domain[1])


@dataclass
class Search(Interactor):
    column: str = ""
    kind: str = "contains"

    def make(self, value) -> Clause:
        return match(self.source, self.column, value, self.kind, self.views)

    def example(self) -> Clause:
        return self.make("")
