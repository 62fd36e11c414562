"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: update latency from cells and directly, and creation. Prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from statistics import median

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from brushcube.bench.registry import coordinator  # noqa: E402
from brushcube.bench.workloads import pairs  # noqa: E402
from brushcube.metrics.measures import break_even, quantiles, size_facts, speed_up, time_creation, time_updates  # noqa: E402
from brushcube.session import local_session  # noqa: E402


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(int(os.environ.get("BENCH_CPUS", "8")))
    chosen = [p for p in pairs() if (p.template, p.view.id) in {("w1", "hour"), ("w1l", "quantity"), ("w1l", "discount"), ("w2", "hist"), ("w3", "h5"), ("w4", "ci"), ("w5", "fit")}]
    # one pair per (template, view): the first active interactor
    chosen = list({(p.template, p.view.id): p for p in reversed(chosen)}.values())[::-1]
    queries, notes = {}, {}
    with tempfile.TemporaryDirectory() as store:
        coord = coordinator(spark, sf_dir, store=store)
        for p in chosen:
            name = f"{p.template}_{p.view.id}"
            base = coord.relations.get(p.view.source).df
            n = base.count()
            ms, _ = time_creation(coord, p)
            rows = time_updates(coord, p, positions=3)
            by = {m: [r["ms"] for r in rows if r["method"] == m] for m in ("cells", "direct")}
            queries[f"{name}_create"] = round(ms / 1000, 4)
            queries[f"{name}_update"] = round(median(by["cells"]) / 1000, 4)
            queries[f"{name}_direct"] = round(median(by["direct"]) / 1000, 4)
            even = break_even(ms, rows)
            notes[name] = {"update_ms": {k: round(v, 2) for k, v in quantiles(by["cells"]).items()}, "speed_up": round(speed_up(rows), 2), "break_even_updates": even and round(even, 1), "base_rows": n,
                           **{k: v for k, v in size_facts(coord, p, n).items() if k in ("rows", "bytes", "reduction")}}
        coord.close()
    print(json.dumps({"metric": "sum of median update latencies from pre-aggregates", "value": round(sum(v for k, v in queries.items() if k.endswith("_update")), 4), "unit": "sec", "queries": queries, "sf": sf_dir, "detail": notes, "at": round(time.time())}))
    spark.stop()


if __name__ == "__main__":
    main()
