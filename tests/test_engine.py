"""Answers from cells against DuckDB on the raw tables, goldens, statistics, reuse, baselines, coordinator, streaming."""

import math
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from brushcube.bench import registry as R
from brushcube.bench import workloads as w
from brushcube.bench.sweep import sweep
from brushcube.bench.upsample import upsample
from brushcube.coord.coordinator import Coordinator
from brushcube.metrics import measures as M
from brushcube.model.clause import clear, interval, interval_nd, match, point
from brushcube.model.pred import Constant
from brushcube.model.scales import Scale
from brushcube.model.selection import Selection
from brushcube.operators.baselines import Axis, DenseTile, OverBudget, PrefixTile, cube_baseline, runtime_frame
from brushcube.plans import measures
from brushcube.plans.measures import Options
from brushcube.plans.preagg import direct
from brushcube.sources.store import load
from brushcube.views.spec import Agg, ViewSpec

from .conftest import SF, rows_of

BIG = "/root/testdata/sf0.01"
SOME = ["scale_log", "bin_ceil", "bin_reversed", "clause_point2", "clause_interval2d", "resolve_union", "cross_intersect", "empty_none", "mv_cleared", "agg_corr", "agg_regr_r2", "agg_geomean", "agg_arg_max", "agg_product", "agg_filter", "agg_having",
        "match_regexp", "reject_median", "w2_hist", "w3_hist", "w4_ci", "w5_fit", "view_hexbin", "view_linear2d", "view_lines", "prefix_tile", "grouping_sets", "sql_view", "stream_cells", "mv_precompute_last", "op_join_asof", "op_join_range",
        "session_replay", "cold_start", "together", "sweep_step", "centring", "upsampled", "view_rebinned", "sketch_topk", "sketch_kll", "cube_baseline", "runtime_side", "st_late", "st_session", "st_dedup", "st_state", "stream_compacted", "w3c_balance", "w6_hover"]


def coord(spark, tmp_path, **k) -> Coordinator:
    c = Coordinator(spark, store=str(tmp_path), **k)
    c.relation("events", load(spark, SF, "events"))
    c.relation("lineitem", load(spark, SF, "lineitem"))
    return c


def picked(c, **k):
    s = Selection(**k)
    s.update(c)
    return s


DRAG = interval("drag", "value", (30, 90), w.VALUE)
HOUR = w.flight_views()["hour"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_oracle(spark, oracle, name):
    df = R.queries()[name](spark, SF)
    cols, want = oracle(R.oracle_sql()[name])
    assert sorted(cols) == sorted(df.columns)
    key = lambda r: tuple((x is None, str(x)) for x in r)
    assert rows_of(df, cols) == sorted(want, key=key)


def test_goldens(spark):
    ev, c = load(spark, BIG, "events"), R.coordinator(spark, BIG)
    got = {r.x: r.y for r in c.frame(HOUR, picked(DRAG), DRAG)[0].collect()}
    assert [got[h] for h in range(24)] == [162, 161, 173, 158, 209, 177, 164, 126, 185, 162, 177, 160, 157, 166, 168, 167, 171, 133, 174, 181, 144, 158, 160, 121]
    assert ev.where(DRAG.predicate.column()).count() == 3871  # the raw interval differs by the last bin's rest
    none = interval("drag", "value", (550, 599), w.VALUE)
    total = ViewSpec("total", "events", (), (Agg("n", "count"),), True)
    assert c.frame(total, picked(none), none)[0].collect()[0].n == 0 and not c.frame(HOUR, picked(none), none)[0].collect()


def test_sweeps_equal_direct(spark, tmp_path):
    c = coord(spark, tmp_path)
    for p in [p for p in w.pairs(("w1", "w4")) if p.view.id in ("hour", "ci")][:3]:
        cells = c.cells.ensure(p.view, p.clause(0, 0.1))
        for _, _, cl in sweep(p, (0.2,), 3):
            a, b = c.cells.answer(cells, p.view, cl), direct(p.view, c.relations.get("events").df, cl.bin_predicate())
            err = M.max_error(a, b, [p.view.group[0][0]])
            assert err["rel"] < 1e-9


def test_counts_add_up(spark, tmp_path):
    c = coord(spark, tmp_path)
    total = ViewSpec("total", "events", (), (Agg("n", "count"),), True)
    one = lambda a, b: c.frame(total, picked(x := interval("d", "value", (a, b), w.VALUE)), x)[0].collect()[0].n
    assert one(0, 99.5) + one(100, 600) == 1000 and c.frame(total, picked(clear(DRAG)), clear(DRAG))[0].collect()[0].n == 1000


def test_variance_survives_offsets_and_constants(spark, tmp_path):
    li = load(spark, SF, "lineitem").withColumn("far", F.expr("l_quantity + 1e9D")).withColumn("same", F.lit(0.07)).withColumn("holes", F.expr("CASE WHEN l_linenumber <> 3 THEN l_quantity END"))
    cl = interval("p", "l_extendedprice", (22000, 66000), w.PRICE)
    truth = li.where(cl.bin_predicate().column()).agg(F.var_samp("l_quantity").alias("v"), F.covar_samp("l_extendedprice", "l_quantity").alias("c"), F.avg("holes").alias("h")).first()
    aggs = (Agg("v", "var_samp", ("far",)), Agg("c", "covar_samp", ("l_extendedprice", "far")), Agg("z", "stddev_pop", ("same",)), Agg("r", "corr", ("l_quantity", "same")), Agg("r2", "regr_r2", ("same", "l_quantity")), Agg("h", "avg", ("holes",)))
    view = ViewSpec("off", "li", (), aggs, True)
    got = {}
    for mode in ("global", "none"):
        c = Coordinator(spark, store=str(tmp_path / mode), options=Options(centre=mode))
        c.relation("li", li)
        got[mode] = c.frame(view, picked(cl), cl)[0].first()
    g = got["global"]
    assert math.isclose(g.v, truth.v, rel_tol=1e-9) and math.isclose(g.c, truth.c, rel_tol=1e-9) and math.isclose(g.h, truth.h, rel_tol=1e-12)
    assert g.z == 0 and g.r is None and g.r2 == 1.0
    assert abs(got["none"].v - truth.v) > 1e-3 * truth.v  # sums about zero cancel


def test_null_nan_and_single_rows(spark, tmp_path):
    rows = [(1, 5.0, None), (1, 6.0, 2.0), (2, 7.0, float("nan")), (3, None, 1.0), (4, 50.0, -1.0)]
    c = Coordinator(spark, store=str(tmp_path))
    c.relation("t", spark.createDataFrame(rows, "k int, x double, y double"))
    v = ViewSpec("t", "t", (("k", "k"),), (Agg("n", "count", ("y",)), Agg("vs", "var_samp", ("y",)), Agg("g", "geomean", ("x",)), Agg("a", "avg", ("y",)), Agg("gy", "geomean", ("y",))), True)
    s = interval("d", "x", (0, 60), w.VALUE)
    got = {r.k: r for r in c.frame(v, picked(s), s)[0].collect()}
    assert set(got) == {1, 2, 4} and got[1].n == 1 and got[1].vs is None and math.isclose(got[1].g, 30 ** 0.5) and math.isnan(got[2].a) and got[4].gy is None
    both = clear(s)
    assert {r.k for r in c.frame(v, picked(both), both)[0].collect()} == {1, 2, 3, 4}


def test_reuse_residual_snapshot_and_races(spark, tmp_path):
    c = coord(spark, tmp_path)
    with ThreadPoolExecutor(4) as pool:
        names = {f.name for f in pool.map(lambda _: c.cells.ensure(HOUR, DRAG), range(4))}
    assert len(names) == 1 and c.store.builds == 1
    again = coord(spark, tmp_path)
    assert again.cells.ensure(HOUR, DRAG).name in names and again.store.builds == 0 and again.store.facts(next(iter(names)))["build_ms"] > 0
    other = point("m", "event_type", ["click"])
    assert c.cells.ensure(HOUR, DRAG, other.predicate).name not in names
    c.relation("events", load(spark, SF, "events"), "another snapshot")
    assert c.cells.ensure(HOUR, DRAG).name not in names and len(c.store.list()) == 3
    c.store.drop(next(iter(names)))
    assert len(c.store.list()) == 2


def test_snapshot_follows_files(spark, tmp_path):
    p = str(tmp_path / "r")
    load(spark, SF, "region").write.parquet(p)
    c = Coordinator(spark, store=str(tmp_path / "s"))
    a = c.relations.add("r", spark.read.parquet(p)).snapshot
    load(spark, SF, "region").limit(2).write.mode("overwrite").parquet(p)
    assert c.relations.add("r", spark.read.parquet(p)).snapshot != a


def test_coordinator_end_to_end(spark, tmp_path):
    c, sel, out = coord(spark, tmp_path), Selection(cross=True), {}
    views = w.flight_views()
    for v in views.values():
        c.connect(v, sel, lambda name, table: out.__setitem__(name, table))
    with pytest.raises(ValueError):
        c.connect(views["hour"], Selection())
    drag = replace(DRAG, views=frozenset({"value"}))
    for f in c.on_activate(sel, drag):
        f.result()
    built = c.store.builds
    sel.update(drag)
    assert c.settle() and set(out) == {"hour", "user"} and c.store.builds == built and M.lead_time(c.log) > 0
    want = rows_of(direct(views["hour"], c.relations.get("events").df, drag.bin_predicate()))
    assert set(zip(*out["hour"].to_pydict().values())) == set(want)
    sel.update(drag)
    c.settle()
    assert c.cache.hits >= 2 and c.dispatch_stats()["failed"] == 0
    c.close()


def test_gate_and_fallback(spark, tmp_path):
    c = coord(spark, tmp_path, gate=0.3)
    fine = ViewSpec("ids", "events", (("event_id", "event_id"),), (Agg("n", "count"),), True)
    assert c.frame(fine, picked(DRAG), DRAG)[1] == "direct"
    s = match("f", "event_type", "cl", "prefix")
    assert coord(spark, tmp_path / "b").frame(HOUR, picked(s), s)[1:] == ("direct", ("clause: match can't be binned",))


def test_gate_decides_no_answer(spark, tmp_path):
    """Cells and the direct path behind the gate hold the same rows, another clause and end bins cut by the drag included."""
    drag, other = interval("d", "value", (10.9, 90), w.VALUE), interval("u", "user_id", (0, 140), w.USERS)
    got = []
    for gate in (None, 0.0):
        c = coord(spark, tmp_path / str(gate), gate=gate)
        s = picked(other)
        s.update(drag)
        df, path, _ = c.frame(HOUR, s, drag)
        got.append((path, rows_of(df)))
        c.close()
    assert [p for p, _ in got] == ["cells", "direct"] and got[0][1] == got[1][1]


def test_dense_and_prefix_equal_sparse(spark, tmp_path):
    ev, c = load(spark, SF, "events"), coord(spark, tmp_path)
    keys = [Axis("x", w.HOUR, 0, 24)]
    want = {r.x: r.y for r in c.frame(HOUR, picked(DRAG), DRAG)[0].collect()}
    for kind in (DenseTile, PrefixTile):
        got = kind.build(ev, keys, DRAG).answer((30, 90))
        assert {h: int(v) for h, v in enumerate(got) if v} == want
    pick = interval_nd("a", ("value", "user_id"), ((0, 600), (0, 150)), (w.VALUE, w.USERS))
    p2 = PrefixTile.build(ev, keys, pick)
    d2 = DenseTile.build(ev, keys, pick)
    assert (p2.answer((10, 80), (5, 90)) == d2.answer((10, 80), (5, 90))).all() and (p2.answer((0, 80), (0, 9)) == d2.answer((0, 80), (0, 9))).all()
    big = [Axis("x", "0", 0, 300), Axis("y", "0", 0, 200)]
    with pytest.raises(OverBudget):
        DenseTile.build(ev, big, interval_nd("s", ("value", "user_id"), ((0, 1), (0, 1)), (w.DIM_X, w.DIM_Y)))
    assert {r.x: r.y for r in runtime_frame(HOUR, ev, DRAG.bin_predicate()).collect()} == want
    assert cube_baseline(ev, {"t": "event_type", "h": w.HOUR}, "value").where("t IS NULL AND h IS NULL").first().n == 1000


def test_sketches_are_near(spark, tmp_path):
    measures.register_sketches()
    c = coord(spark, tmp_path)
    q = interval("q", "l_quantity", (10, 40), w.QUANTITY)
    v = ViewSpec("sk", "lineitem", (), (Agg("h", "approx_distinct", ("l_partkey",)), Agg("t", "theta_distinct", ("l_partkey",)), Agg("m", "kll_median", ("l_extendedprice",)), Agg("b", "bitmap_distinct", ("l_linenumber",))), True)
    df, path, _ = c.frame(v, picked(q), q)
    got = df.first()
    want = load(spark, SF, "lineitem").where(q.bin_predicate().column()).agg(F.count_distinct("l_partkey").alias("d"), F.median("l_extendedprice").alias("m"), F.count_distinct("l_linenumber").alias("b")).first()
    assert path == "cells" and abs(got.h - want.d) <= 0.05 * want.d and abs(got.t - want.d) <= 0.05 * want.d and abs(got.m - want.m) <= 0.05 * want.m and got.b == want.b


def test_registered_measure(spark, tmp_path):
    measures.register_measure("sum_of_squares", lambda x: F.sum(x * x), F.sum)
    c = coord(spark, tmp_path)
    v = ViewSpec("ss", "events", (), (Agg("s", "sum_of_squares", ("value",)),), True)
    df, path, _ = c.frame(v, picked(DRAG), DRAG)
    want = load(spark, SF, "events").where(DRAG.bin_predicate().column()).agg(F.sum(F.col("value") * F.col("value"))).first()[0]
    assert path == "cells" and math.isclose(df.first().s, want, rel_tol=1e-12)


def test_line_density_refuses_row_level_clauses(spark, tmp_path):
    c = coord(spark, tmp_path)
    v = replace(HOUR, inner_keys=("user_id",))
    assert "inner query" in c.frame(v, picked(DRAG), DRAG)[2][0]


def test_upsample_and_measures(spark, tmp_path):
    up = upsample(load(spark, SF, "events"), 3, {"value": 1.0})
    assert 2500 < up.count() < 3500 and up.select("event_type").distinct().count() == 5
    c = coord(spark, tmp_path)
    p = [p for p in w.pairs(("w1",)) if p.view.id == "hour"][0]
    ms, cells = M.time_creation(c, p)
    rows = M.time_updates(c, p, positions=1, widths=(0.1,), warm=0)
    facts = M.size_facts(c, p, 1000, [Axis("x", w.HOUR, 0, 24)])
    assert ms > 0 and len(rows) == 2 and M.speed_up(rows) > 0 and facts["rows"] == cells.rows and 0 < facts["density"] < 1
    assert M.quantiles([1, 2, 3, 400])["within_100ms"] == 0.75 and 0 <= M.snap_error(load(spark, SF, "events"), p) < 0.2
    assert M.break_even(100, [{"method": "cells", "ms": 5}, {"method": "direct", "ms": 10}]) == 20


def test_streaming_windows(spark, tmp_path):
    from brushcube.streaming.windows import deduplicated, sessions, sliding, tumbling

    src = str(tmp_path / "in")
    ev = load(spark, SF, "events")
    ev.union(ev.limit(10)).repartition(2).write.parquet(src)
    for i, (make, mode) in enumerate(((tumbling, "complete"), (sliding, "complete"), (sessions, "append"), (deduplicated, "append"))):
        s = spark.readStream.schema(ev.schema).parquet(src)
        q = make(s).writeStream.outputMode(mode).format("memory").queryName(f"out{i}").option("checkpointLocation", str(tmp_path / f"cp{i}")).trigger(availableNow=True).start()
        q.awaitTermination()
        assert spark.table(f"out{i}").count() > 0
    assert spark.table("out0").agg(F.sum("n")).first()[0] == 1010 and spark.table("out3").count() == 1000
    assert rows_of(tumbling(ev, delay=None).select("n"))[0][0] > 0


def test_plans_push_down_and_stay_native(spark, tmp_path):
    c = coord(spark, tmp_path)
    plan = c.cells.create(HOUR, DRAG, point("m", "event_type", ["click"]).predicate, measures.plan(HOUR.aggs))._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(event_type), EqualTo(event_type,click)]" in plan and "props" not in plan and "Python" not in plan
    cells = c.cells.ensure(HOUR, DRAG)
    assert cells.warm and "Exchange" not in c.cells.answer(cells, HOUR, DRAG)._jdf.queryExecution().executedPlan().toString()
    assert Constant(True).sql() == "TRUE"


def _table(t):
    return sorted((tuple(round(x, 6) if isinstance(x, float) else x for x in r.values()) for r in t.to_pylist()), key=str)


@pytest.mark.parametrize("name", ["w1_hour", "w1_value", "w1l_quantity", "w2_hist", "w3_colour", "w4_ci", "w5_fit", "clause_point1", "bin_ceil", "bin_reversed", "bin_halfopen", "mv_cleared", "cross_intersect",
                                  "agg_corr", "agg_stddev_samp", "agg_covar_samp", "agg_regr_r2", "agg_geomean", "agg_max", "agg_filter", "view_summary", "scale_log", "agg_product", "agg_having"])
def test_merging_in_the_process_equals_spark(spark, name):
    case = R.view_cases()[name]
    sel, c = case.selection(), R.coordinator(spark, SF)
    cells = c.cells.ensure(case.view, sel.active, sel.residual(case.view.id, sel.active))
    got, where = c.cells.merged(cells, case.view, sel.active)
    assert where == ("spark" if name in ("scale_log", "agg_product", "agg_having") else "process")
    assert got.column_names == c.cells.answer(cells, case.view, sel.active).columns
    assert _table(got) == _table(c.cells.answer(cells, case.view, sel.active).toArrow())


def test_merging_in_the_process_of_nothing_and_nulls(spark, tmp_path):
    c, none = coord(spark, tmp_path), interval("drag", "value", (550, 599), w.VALUE)
    total = ViewSpec("total", "events", (), (Agg("n", "count"), Agg("m", "avg", ("value",)), Agg("lo", "min", ("value",)), Agg("sd", "stddev_samp", ("value",))), True)
    for view in (total, replace(HOUR, id="h2")):
        cells = c.cells.ensure(view, none)
        got, where = c.cells.merged(cells, view, none)
        assert where == "process" and _table(got) == _table(c.cells.answer(cells, view, none).toArrow())
    odd = spark.range(40).selectExpr("if(id % 5 = 0, null, id % 3) AS k", "if(id % 4 = 0, null, double(id)) AS v", "if(id % 7 = 0, null, double(id * id)) AS y", "if(id % 6 = 0, null, double(id)) AS x")
    c.relation("odd", odd)
    view = ViewSpec("odd", "odd", (("k", "k"),), (Agg("n", "count", ("v",)), Agg("s", "sum", ("v",)), Agg("a", "avg", ("v",)), Agg("b", "max", ("v",)), Agg("r", "regr_slope", ("y", "v")), Agg("c", "corr", ("y", "v"))), True)
    for ends in ((0, 40), (3, 9), (30, 31)):
        clause = interval("d", "x", ends, Scale("linear", (0, 40), (0, 40)))
        cells = c.cells.ensure(view, clause)
        got, where = c.cells.merged(cells, view, clause)
        assert where == "process" and _table(got) == _table(c.cells.answer(cells, view, clause).toArrow())


def test_an_event_in_flight_keeps_its_clauses(spark, tmp_path):
    c, s = coord(spark, tmp_path), Selection()
    c.views["hour"] = (HOUR, s)
    older, newer = DRAG, interval("drag", "value", (200, 400), w.VALUE)
    truth = {k.values: sum(r["y"] for r in c.frame(HOUR, picked(k), k)[0].collect()) for k in (older, newer)}
    s.update(older)
    state = s.freeze(older)
    s.update(newer)
    assert sum(c.query("hour", older, state).column("y").to_pylist()) == truth[older.values]
    assert sum(c.query("hour", newer).column("y").to_pylist()) == truth[newer.values]
    assert c.log[-1].path == "cells" and c.query("hour", newer) and c.log[-1].path == "cache"


def test_other_rows_under_one_name_get_other_cells(spark, tmp_path):
    c, ev = coord(spark, tmp_path), load(spark, SF, "events")
    for rows in (ev, ev.where("event_type = 'view'"), spark.createDataFrame([(1.0, 50.0)], "user_id double, value double").selectExpr("*", "timestamp_ntz'2020-01-01 03:00:00' AS ts"),
                 spark.createDataFrame([(1.0, 60.0), (2.0, 61.0)], "user_id double, value double").selectExpr("*", "timestamp_ntz'2020-01-01 03:00:00' AS ts")):
        c.relation("events", rows)
        assert sum(r["y"] for r in c.frame(HOUR, picked(DRAG), DRAG)[0].collect()) == rows.where("floor(value) BETWEEN 30 AND 90").count()


def test_sessions_hold_a_bounded_number_of_cells(spark, tmp_path, monkeypatch):
    from brushcube.plans import preagg

    monkeypatch.setattr(preagg, "OPEN", 2)
    c = coord(spark, tmp_path)
    for k in range(4):
        c.cells.ensure(replace(HOUR, id=f"h{k}", aggs=(Agg("y", "sum", (str(k),)),)), DRAG)
    assert len(c.cells._open) == 2 and c.cells.ensure(replace(HOUR, id="h0", aggs=(Agg("y", "sum", ("0",)),)), DRAG).rows > 0


def test_no_filter_may_hold_a_selections_predicate(spark, tmp_path):
    c, s = coord(spark, tmp_path), picked(DRAG)
    inside = replace(HOUR, id="own", aggs=(Agg("y", "count", where=DRAG.predicate.sql()),))
    assert c.frame(inside, s, DRAG)[1:] == ("direct", ("filter: holds a selection's predicate",))
