"""May this view be answered from a pre-aggregate for this clause? Every failing condition is named."""

from __future__ import annotations

from dataclasses import dataclass

from ..model.clause import Clause
from ..model.selection import Selection
from ..views.spec import FUNCTIONS, ViewSpec
from .measures import EXTRA


@dataclass(frozen=True)
class Verdict:
    reasons: tuple[str, ...] = ()

    @property
    def ok(self) -> bool:
        return not self.reasons


def check(selection: Selection | None, clause: Clause, view: ViewSpec, dynamic: tuple[str, ...] = ()) -> Verdict:
    """``dynamic``: predicate texts of current selections, which no FILTER may hold."""
    out = []
    if selection is not None:
        if selection.resolve == "union":
            out.append("resolver: union can't be folded into bins")
        if selection.empty == "none" and not [c for c in selection.clauses() if c.source != clause.source]:
            out.append("empty: no clause means no rows") if clause.cleared else None
    if clause.meta is None:
        out.append("metadata: none")
    elif clause.meta.kind not in ("point", "interval"):
        out.append(f"clause: {clause.meta.kind} can't be binned")
    elif clause.meta.kind == "interval":
        if len(clause.meta.scales) != len(clause.meta.columns):
            out.append("metadata: an interval needs a scale per column")
        out += [f"scale: {p}" for s in clause.meta.scales for p in s.problems()]
        if clause.meta.step <= 0:
            out.append("metadata: pixel step not positive")
    if not view.filter_stable:
        out.append("view: not declared stable under filters")
    if len(set(view.sources) | {view.source}) != 1:
        out.append("source: more than one base relation")
    if view.raw or not (view.aggs or view.group):
        out.append("query: no aggregation")
    for a in view.aggs:
        if a.distinct:
            out.append(f"aggregate: {a.fn} distinct")
        elif a.fn not in FUNCTIONS and a.fn not in EXTRA:
            out.append(f"aggregate: {a.fn} unsupported")
        if a.where and any(d in a.where for d in dynamic):
            out.append("filter: holds a selection's predicate")
    if view.opaque:
        out.append(f"inner query: {view.opaque}")
    if view.inner_keys and clause.meta and not set(clause.meta.columns) <= set(view.inner_keys):
        out.append("inner query: the clause's columns aren't keys of the inner aggregation")
    return Verdict(tuple(out))
