"""Selections: clauses and the rule that resolves them to one predicate per view."""

from __future__ import annotations

import threading
from collections.abc import Callable

from .clause import Clause
from .pred import FALSE, TRUE, Pred, both, either


class Selection:
    """``resolve``: last, intersect or union. ``cross``: skip a clause for the views it names. ``empty``: all or none of the
    rows where there is no clause (judged before cross-filtering). ``includes``: upstream selections, whose clauses are relayed."""

    def __init__(self, resolve: str = "intersect", cross: bool = False, empty: str = "all", includes=()):
        if resolve not in ("last", "intersect", "union") or empty not in ("all", "none"):
            raise ValueError((resolve, empty))
        self.resolve, self.cross, self.empty = resolve, cross, empty
        self._own: dict[str, Clause] = {}
        self._lock = threading.RLock()
        self.active: Clause | None = None
        self._listeners: list[Callable[[str, Clause], None]] = []
        self._downstream: list[Selection] = []
        for up in includes:
            up._feed(self)

    def _feed(self, below: Selection) -> None:
        seen, todo = set(), [below]
        while todo:
            s = todo.pop()
            if s is self:
                raise ValueError("selections include each other")
            if id(s) not in seen:
                seen.add(id(s))
                todo += s._downstream
        self._downstream.append(below)
        for c in self.clauses():
            below._take(c)

    def _take(self, clause: Clause) -> None:
        with self._lock:
            self._own.pop(clause.source, None)  # a source's former clause goes, the new one is the newest
            if self.resolve == "last":
                self._own.clear()
            self._own[clause.source] = clause
            self.active = clause

    def clauses(self) -> list[Clause]:
        with self._lock:
            return list(self._own.values())

    def freeze(self, active: Clause | None = None) -> Selection:
        """The selection as it is now, which later updates don't change: what an event in flight is answered by. ``active``: its clause, if not the newest."""
        out = Selection(self.resolve, self.cross, self.empty)
        with self._lock:
            out._own, out.active = dict(self._own), active or self.active
        return out

    def listen(self, handler: Callable[[str, Clause], None]) -> None:
        self._listeners.append(handler)

    def update(self, clause: Clause) -> None:
        """Replace the source's clause, make it active, and tell listeners and downstream selections."""
        with self._lock:  # listeners see the selection as this clause made it
            self._take(clause)
            for h in self._listeners:
                h("update", clause)
        for s in self._downstream:
            s.update(clause)

    def activate(self, clause: Clause) -> None:
        """Announce the shape of clauses to come; nothing is selected by it."""
        for h in self._listeners:
            h("activate", clause)
        for s in self._downstream:
            s.activate(clause)

    def applying(self, view: str, without: Clause | None = None) -> list[Clause]:
        found = [c for c in self.clauses() if not c.cleared and not (self.cross and view in c.views)]
        return [c for c in found if without is None or c.source != without.source]

    def is_empty(self) -> bool:
        return all(c.cleared for c in self.clauses())

    def predicate(self, view: str, snapped: bool = False) -> Pred:
        """What the view is filtered by. ``snapped``: intervals at the resolution of their bins."""
        if self.is_empty():
            return TRUE if self.empty == "all" else FALSE
        parts = [c.bin_predicate() if snapped and c.meta and c.meta.scales else c.predicate for c in self.applying(view)]
        if not parts:
            return TRUE
        return either(*parts) if self.resolve == "union" else both(*parts)

    def residual(self, view: str, active: Clause) -> Pred:
        """What the other clauses ask, folded into the pre-aggregate of the active one."""
        return both(*[c.predicate for c in self.applying(view, without=active)])
