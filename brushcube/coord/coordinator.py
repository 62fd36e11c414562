"""The coordinator: connects views and selections, decides per update between cells and the direct query, and delivers results."""

from __future__ import annotations

import hashlib
import time
from collections import deque
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

from ..model.clause import Clause
from ..model.dispatch import Dispatcher
from ..model.pred import FALSE, TRUE, Pred, both
from ..model.selection import Selection
from ..plans import compat
from ..plans.measures import Options
from ..plans.preagg import PreAggregator, direct
from ..sources.store import Relations, Store
from ..views.spec import ViewSpec
from ..views.sqlview import sql_view
from .cache import ResultCache
from .consolidate import same_keys


#: Events that the log keeps, and gate estimates.
LOG = 10_000


@dataclass
class Event:
    """What happened to a view on an update: how it was answered, why, and how long it took."""

    view: str
    path: str
    reasons: tuple[str, ...] = ()
    ms: float = 0.0
    merged: str = ""  # where cells were merged: process or spark
    at: float = field(default_factory=time.time)


class Coordinator:
    def __init__(self, spark: SparkSession, store: str | None = None, options: Options = Options(), gate: float | None = None, threads: int = 8, optimise: bool = True):
        self.spark = spark
        self.relations = Relations(spark)
        self.store = Store(spark, store)
        self.cells = PreAggregator(spark, self.relations, self.store, options)
        self.gate, self.optimise = gate, optimise
        self.cache = ResultCache()
        self.views: dict[str, tuple[ViewSpec, Selection]] = {}
        self.plain: dict[str, tuple[DataFrame, list[str]]] = {}
        self.results: dict[str, pa.Table] = {}
        self.log: deque[Event] = deque(maxlen=LOG)
        self._handlers: dict[str, Callable[[str, pa.Table], None]] = {}
        self._pool = ThreadPoolExecutor(threads, "brushcube-view")
        self._background = ThreadPoolExecutor(2, "brushcube-prefetch")
        self._dispatchers: dict[int, Dispatcher] = {}
        self._gated: dict[str, float] = {}

    # -- connecting -------------------------------------------------------------------------------------------------
    def relation(self, name: str, df: DataFrame, snapshot: str | None = None) -> None:
        self.relations.add(name, df, snapshot)

    def connect(self, view: ViewSpec, selection: Selection, deliver: Callable[[str, pa.Table], None] | None = None) -> None:
        """A view belongs to one selection; a selection may have many views."""
        if view.id in self.views:
            raise ValueError(f"{view.id} has a selection already")
        self.views[view.id] = (view, selection)
        if deliver:
            self._handlers[view.id] = deliver
        if id(selection) not in self._dispatchers:
            d = Dispatcher(lambda state, s=selection: self.on_update(s, state.active, state))
            self._dispatchers[id(selection)] = d
            # an event is the selection as its clause made it: what waits or is in flight isn't touched by newer clauses
            selection.listen(lambda kind, clause, s=selection, d=d: d.send(s.freeze(clause)) if kind == "update" else self.on_activate(s, clause))

    def sql(self, id: str, text: str, selection: Selection, filter_stable: bool = False, args: dict | None = None) -> list[str]:
        """Connect a view given as SQL. Returns why it can't be optimised (nothing if it can)."""
        spec, base, plain, reasons = sql_view(self.spark, id, text, filter_stable, args)
        if spec is None:
            self.plain[id] = (plain, reasons)
            return reasons
        self.relation(spec.source, base)
        self.connect(spec, selection)
        return reasons

    # -- answering --------------------------------------------------------------------------------------------------
    def frame(self, view: ViewSpec, selection: Selection, clause: Clause | None, snapped: bool = False) -> tuple[DataFrame, str, tuple[str, ...]]:
        """(answer, path, reasons): from cells if that is sound, else the filtered query. ``snapped`` has the fallback filter at bin resolution too."""
        reasons, pred, residual = self._decide(view, selection, clause, snapped)
        if reasons:
            return direct(view, self.relations.get(view.source).df, pred), "direct", reasons
        return self.cells.answer(self.cells.ensure(view, clause, residual), view, clause), "cells", ()

    def _decide(self, view: ViewSpec, selection: Selection, clause: Clause | None, snapped: bool = False) -> tuple[tuple[str, ...], Pred, Pred]:
        """Why cells can't answer (nothing if they can), the predicate of the direct query, and the other clauses' predicate."""
        residual, pred = TRUE, selection.predicate(view.id, snapped)
        dynamic = tuple(c.predicate.sql() for c in selection.clauses() if not c.cleared)
        verdict = compat.check(selection, clause, view, dynamic) if clause is not None else compat.Verdict(("no active clause",))
        reasons = verdict.reasons if self.optimise else ("optimisation off",)
        if not reasons and pred == FALSE:
            reasons = ("empty selection",)
        if not reasons and selection.cross and view.id in clause.views:
            reasons = ("the active clause doesn't filter this view",)
        if not reasons:
            residual = selection.residual(view.id, clause)
            if self.gate is not None:
                key = f"{view.id}|{clause.meta}|{residual.sql()}"
                if key not in self._gated:
                    if len(self._gated) >= LOG:
                        self._gated.clear()
                    self._gated[key] = self.cells.worth(view, clause, residual)
                if self._gated[key] > self.gate:
                    reasons = (f"gate: about {self._gated[key]:.2f} cells a row",)
                    pred = both(residual, clause.bin_predicate())  # the rows that cells would hold: the gate's estimate decides no answer
        return reasons, pred, residual

    def query(self, view_id: str, clause: Clause | None = None, state: Selection | None = None) -> pa.Table:
        """``state``: the frozen selection to answer by; key, residual and bins all come from it."""
        view, selection = self.views[view_id]
        selection = state or selection.freeze(clause)
        clause = selection.active
        began = time.time()
        key = self._key(view, selection)
        if (hit := self.cache.get(key)) is not None:
            out, path, reasons, merged = hit, "cache", (), ""
        else:
            reasons, pred, residual = self._decide(view, selection, clause)
            if reasons:
                path, merged, out = "direct", "", direct(view, self.relations.get(view.source).df, pred).toArrow()
            else:
                path, (out, merged) = "cells", self.cells.merged(self.cells.ensure(view, clause, residual), view, clause)
            self.cache.put(key, out)
        return self._hand_out(view_id, out, Event(view_id, path, reasons, 1000 * (time.time() - began), merged))

    def _hand_out(self, view_id: str, out: pa.Table, event: Event) -> pa.Table:
        self.log.append(event)
        self.results[view_id] = out
        if view_id in self._handlers:
            self._handlers[view_id](view_id, out)
        return out

    def _shared(self, ids: list[str], state: Selection) -> list[list[str]]:
        """Views whose direct queries have the source, keys and predicate in common, in one list; every other view in its own."""
        groups: dict[object, list[str]] = {}
        for v in ids:
            view = self.views[v][0]
            key: object = v
            plain = view.aggs and not (view.raw or view.post or view.columns or view.having or view.order or view.limit is not None or view.offset)
            if plain and self.gate is None and len(ids) > 1 and self.cache.get(self._key(view, state)) is None:
                reasons, pred, _ = self._decide(view, state, state.active)
                if reasons:
                    key = (view.source, view.derive, view.explode, view.group, pred.sql())
            groups.setdefault(key, []).append(v)
        return list(groups.values())

    def query_together(self, ids: list[str], state: Selection) -> list[pa.Table]:
        """One scan for views that ``_shared`` put together."""
        began, views = time.time(), [self.views[v][0] for v in ids]
        reasons, pred, _ = self._decide(views[0], state, state.active)
        table = direct(same_keys(views), self.relations.get(views[0].source).df, pred).toArrow()
        keys, tables = [a for a, _ in views[0].group], []
        for v in views:
            out = table.select(keys + [f"{v.id}__{a.alias}" for a in v.aggs]).rename_columns(keys + [a.alias for a in v.aggs])
            self.cache.put(self._key(v, state), out)
            tables.append(self._hand_out(v.id, out, Event(v.id, "direct", (*reasons, "one scan for several views"), 1000 * (time.time() - began))))
        return tables

    def _key(self, view: ViewSpec, selection: Selection) -> str:
        r = self.relations.get(view.source)
        active = selection.active
        return hashlib.sha256(repr((view, r.snapshot, selection.predicate(view.id).sql(), selection.predicate(view.id, True).sql(), active and (active.source, active.meta, active.bin_predicate().sql() if active.meta and active.meta.scales else ""))).encode()).hexdigest()

    def affected(self, selection: Selection, clause: Clause) -> list[str]:
        return [v for v, (_, s) in self.views.items() if s is selection and not (s.cross and v in clause.views)]

    def on_update(self, selection: Selection, clause: Clause, state: Selection | None = None) -> list[Future]:
        state = state or selection.freeze(clause)
        run = inheritable_thread_target(self.spark)
        return [self._pool.submit(run(self.query), g[0], clause, state) if len(g) == 1 else self._pool.submit(run(self.query_together), g, state)
                for g in self._shared(self.affected(selection, clause), state)]

    # -- ahead of time ----------------------------------------------------------------------------------------------
    def on_activate(self, selection: Selection, example: Clause) -> list[Future]:
        """Build what the coming updates need, in the background; nothing is delivered."""
        out = []
        for v in self.affected(selection, example):
            view = self.views[v][0]
            if self.optimise and compat.check(selection, example, view).ok:
                self.log.append(Event(v, "activate"))
                out.append(self._background.submit(inheritable_thread_target(self.spark)(self.cells.ensure), view, example, selection.residual(v, example)))
        return out

    def precompute(self, selection: Selection, examples: list[Clause]) -> list[str]:
        """Cells of every (clause shape, view) pair in isolation. With resolver last these are all that is ever asked."""
        names = []
        for c in examples:
            for v in self.affected(selection, c):
                view = self.views[v][0]
                if compat.check(selection, c, view).ok:
                    names.append(self.cells.ensure(view, c, TRUE).name)
        return names

    def prefetch(self, view_id: str) -> Future:
        return self._background.submit(inheritable_thread_target(self.spark)(self.query), view_id)

    def settle(self, timeout: float | None = 120) -> bool:
        return all(d.drain(timeout) for d in self._dispatchers.values())

    def dispatch_stats(self) -> dict[str, int]:
        total = {"dispatched": 0, "dropped": 0, "failed": 0}
        for d in self._dispatchers.values():
            for k, v in d.stats().items():
                total[k] += v
        return total

    def close(self) -> None:
        for d in self._dispatchers.values():
            d.close()
        self._pool.shutdown()
        self._background.shutdown()
