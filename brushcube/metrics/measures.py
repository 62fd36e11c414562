"""Cost and accuracy: latencies of creation and update, sizes, speed-up, break-even, errors."""

from __future__ import annotations

import random
import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..bench.sweep import sweep
from ..bench.workloads import Pair
from ..coord.coordinator import Coordinator, Event
from ..operators.baselines import Axis
from ..plans.preagg import direct

METHODS = ("cells", "direct")


def quantiles(ms: list[float]) -> dict[str, float]:
    """p25, p50, p75, and the shares within 100 ms and one frame at 60 Hz."""
    s = sorted(ms)
    at = lambda q: s[min(len(s) - 1, int(q * len(s)))]
    return {"p25": at(0.25), "p50": median(s), "p75": at(0.75), "within_100ms": sum(x <= 100 for x in s) / len(s), "within_frame": sum(x <= 1000 / 60 for x in s) / len(s)}


def time_creation(coord: Coordinator, pair: Pair) -> tuple[float, object]:
    """(ms, cells) of building one pre-aggregate, with writing and warming."""
    began = time.time()
    cells = coord.cells.ensure(pair.view, pair.clause(0.0, 0.1))
    return 1000 * (time.time() - began), cells


def time_updates(coord: Coordinator, pair: Pair, positions: int = 6, widths=(0.1, 0.2, 0.3), warm: int = 3, seed: int = 1) -> list[dict]:
    """Both methods, interleaved in random order, over a sweep. One dict per query."""
    base = coord.relations.get(pair.view.source).df
    jobs = [(m, w, p, c) for w, p, c in sweep(pair, widths, positions) for m in METHODS]
    random.Random(seed).shuffle(jobs)
    out = []
    for k, (m, w, p, c) in enumerate(jobs[:warm] + jobs):
        began = time.time()
        if m == "cells":  # found again by name, as the coordinator does
            coord.cells.merged(coord.cells.ensure(pair.view, c), pair.view, c)
        else:
            direct(pair.view, base, c.predicate).toArrow()
        if k >= warm:
            out.append({"method": m, "template": pair.template, "view": pair.view.id, "width": w, "position": p, "ms": 1000 * (time.time() - began)})
    return out


def speed_up(rows: list[dict]) -> float:
    by = {m: [r["ms"] for r in rows if r["method"] == m] for m in METHODS}
    return median(by["direct"]) / median(by["cells"])


def break_even(creation_ms: float, rows: list[dict]) -> float | None:
    """Updates after which a pre-aggregate has paid for itself; None if never."""
    by = {m: median(r["ms"] for r in rows if r["method"] == m) for m in METHODS}
    return creation_ms / (by["direct"] - by["cells"]) if by["direct"] > by["cells"] else None


def size_facts(coord: Coordinator, pair: Pair, base_rows: int, key_axes: list[Axis] | None = None) -> dict:
    """Rows and bytes of a pre-aggregate, dense cells, density and reduction."""
    cells = coord.cells.ensure(pair.view, pair.clause(0.0, 0.1))
    dense = 1.0
    for s in pair.scales:
        dense *= abs(s.bins(pair.step))
    for a in key_axes or ():
        dense *= a.count
    return {"rows": cells.rows, "bytes": coord.store.size_bytes(cells.name), "dense": dense, "density": cells.rows / dense, "reduction": base_rows / max(1, cells.rows)}


def max_error(a: DataFrame, b: DataFrame, keys: list[str]) -> dict[str, float]:
    """Greatest absolute and relative difference of equal columns of two answers; rows in one only count as infinite."""
    cols = [c for c in a.columns if c not in keys]
    both = a.select(*keys, *[F.col(c).cast("double").alias(f"a_{c}") for c in cols], F.lit(1).alias("in_a")).join(
        b.select(*[F.col(k).alias(f"k_{k}") for k in keys], *[F.col(c).cast("double").alias(f"b_{c}") for c in cols], F.lit(1).alias("in_b")),
        on=[F.col(k).eqNullSafe(F.col(f"k_{k}")) for k in keys] or F.lit(True), how="full")
    gap = [F.abs(F.col(f"a_{c}") - F.col(f"b_{c}")) for c in cols]
    rel = [F.try_divide(g, F.abs(F.col(f"b_{c}"))) for g, c in zip(gap, cols)]
    got = both.agg(F.max(F.greatest(*gap, F.lit(0.0))).alias("abs"), F.max(F.greatest(*rel, F.lit(0.0))).alias("rel"), F.sum((F.col("in_a").isNull() | F.col("in_b").isNull()).cast("int")).alias("odd")).first()
    return {"abs": float("inf") if got["odd"] else got["abs"] or 0.0, "rel": float("inf") if got["odd"] else got["rel"] or 0.0}


def snap_error(base: DataFrame, pair: Pair, positions: int = 5) -> float:
    """Mean relative difference in rows between the snapped and the raw interval."""
    clauses = [c for _, _, c in sweep(pair, (0.1,), positions)]
    got = base.agg(*[F.count(F.when(c.predicate.column(), 1)).alias(f"r{i}") for i, c in enumerate(clauses)], *[F.count(F.when(c.bin_predicate().column(), 1)).alias(f"s{i}") for i, c in enumerate(clauses)]).first()
    gaps = [abs(got[f"s{i}"] - got[f"r{i}"]) / got[f"r{i}"] for i in range(len(clauses)) if got[f"r{i}"]]
    return sum(gaps) / len(gaps) if gaps else 0.0


def lead_time(log: list[Event]) -> float | None:
    """Seconds between an activation and the first update after it."""
    at = next((e.at for e in log if e.path == "activate"), None)
    after = [e.at for e in log if at and e.path != "activate" and e.at > at]
    return min(after) - at if after else None
