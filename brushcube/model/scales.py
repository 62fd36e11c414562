"""Scales from data to pixels, and bins of pixels: the resolution at which a drag can differ.

Everything is SQL text over doubles, evaluated by Spark for data and for endpoints alike, so that both fall into bins by
the same arithmetic. A value on the edge of two bins is in the one that this arithmetic names: of a logarithm the last bit decides. ``Scale.forward`` is the Python twin for dense tiles and drawing.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..functions.safe import text_number as num

KINDS = ("linear", "log", "pow", "symlog")
RULES = ("floor", "ceil", "round")


@dataclass(frozen=True)
class Scale:
    """kind, data domain, screen range, and the parameter of the kind (base, exponent or constant)."""

    kind: str = "linear"
    domain: tuple[float, float] = (0.0, 1.0)
    range: tuple[float, float] = (0.0, 1.0)
    base: float = 10.0
    exponent: float = 1.0
    constant: float = 1.0

    def problems(self) -> list[str]:
        """Why a clause with this scale can't be pre-aggregated; empty if it can."""
        d0, d1 = self.domain
        out = []
        if self.kind not in KINDS:
            out.append(f"unknown scale {self.kind}")
        if not all(map(math.isfinite, (d0, d1, *self.range))) or d0 == d1 or self.range[0] == self.range[1]:
            out.append("empty or unbounded domain or range")
        if self.kind == "log" and min(d0, d1) <= 0:
            out.append("log domain touches zero")
        if self.kind == "symlog" and self.constant <= 0:
            out.append("symlog constant not positive")
        return out

    def transform_sql(self, x: str) -> str:
        if self.kind == "log":  # the base cancels in the unit position
            return f"ln(CASE WHEN {x} > 0 THEN {x} END)"
        if self.kind == "pow":
            return f"sign({x}) * pow(abs({x}), {num(self.exponent)})"
        if self.kind == "symlog":
            return f"sign({x}) * ln(1 + abs({x}) / {num(self.constant)})"
        return x

    def position_sql(self, x: str, step: float = 1) -> str:
        """Distance from the range's start in steps, as SQL text."""
        x = f"CAST({x} AS DOUBLE)"
        f0, f1 = (self.transform_sql(num(float(d))) for d in self.domain)
        return f"{num(self.bins(step))} * (({self.transform_sql(x)}) - ({f0})) / (({f1}) - ({f0}))"

    def bins(self, step: float = 1) -> float:
        """Bins along the range; negative for a reversed range."""
        return (self.range[1] - self.range[0]) / step

    def bin_sql(self, x: str, step: float = 1, rule: str = "floor") -> str:
        """Bin number of an expression. Values outside the domain keep their bins, nulls keep none."""
        if rule not in RULES:
            raise ValueError(rule)
        p = self.position_sql(x, step)
        return f"CAST({'ceil' if rule == 'ceil' else 'floor'}({p}{' + ' + num(0.5) if rule == 'round' else ''}) AS BIGINT)"

    def forward(self, x: float) -> float:
        if self.kind == "log":
            return math.log(x)
        if self.kind == "pow":
            return math.copysign(abs(x) ** self.exponent, x) if x else 0.0
        if self.kind == "symlog":
            return math.copysign(math.log(1 + abs(x) / self.constant), x) if x else 0.0
        return float(x)

    def bin_value(self, x: float, step: float = 1, rule: str = "floor") -> int:
        f0, f1 = map(self.forward, self.domain)
        p = self.bins(step) * (self.forward(x) - f0) / (f1 - f0)
        return {"floor": math.floor, "ceil": math.ceil, "round": lambda v: math.floor(v + 0.5)}[rule](p)

    def edge(self, k: int, step: float = 1) -> float:
        """Data value at the start of bin k, to draw cells and to snap endpoints."""
        f0, f1 = map(self.forward, self.domain)
        f = f0 + (f1 - f0) * k / self.bins(step)
        if self.kind == "log":
            return math.exp(f)
        if self.kind == "pow":
            return math.copysign(abs(f) ** (1 / self.exponent), f)
        if self.kind == "symlog":
            return math.copysign((math.exp(abs(f)) - 1) * self.constant, f)
        return f
