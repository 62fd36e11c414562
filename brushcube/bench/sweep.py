"""Simulated input: intervals of 10, 20 and 30 % of the axis swept across it; sliders through their positions."""

from __future__ import annotations

from collections.abc import Iterator

from ..model.clause import Clause
from .workloads import Pair


def sweep(pair: Pair, widths=(0.1, 0.2, 0.3), positions: int = 20) -> Iterator[tuple[float, float, Clause]]:
    """(width, position, clause)."""
    if pair.kind == "slider":
        n = min(positions, round(abs(pair.scales[0].bins(pair.step))))
        for i in range(n):
            yield 0.0, (i + 1) / n, pair.clause(0.0, (i + 1) / n)
        return
    for w in widths:
        for i in range(positions):
            start = (1 - w) * i / max(1, positions - 1)
            yield w, start, pair.clause(start, w)
