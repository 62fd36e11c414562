"""Scales and bins, predicates, resolvers, dispatch, compatibility: no Spark jobs but where bins are evaluated."""

import math
import threading
import time
from concurrent.futures import Future
from dataclasses import replace

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from brushcube.bench import workloads as w
from brushcube.model.clause import clear, interval, interval_nd, match, point, slider
from brushcube.model.dispatch import Dispatcher
from brushcube.model.interactors import BrushX, BrushXY, Hover, Menu, Search, Slider
from brushcube.model.pred import FALSE, TRUE, both, either
from brushcube.model.scales import Scale
from brushcube.model.selection import Selection
from brushcube.plans.compat import check
from brushcube.views import templates as t
from brushcube.views.spec import Agg, ViewSpec

SCALES = [Scale("linear", (0, 600), (0, 600)), Scale("log", (0.01, 1000), (0, 300)), Scale("pow", (0, 600), (0, 600), exponent=0.5), Scale("symlog", (-600, 600), (0, 600), constant=1), Scale("linear", (0, 600), (200, 0))]
HOUR = w.flight_views()["hour"]


@pytest.mark.parametrize("rule", ["floor", "ceil", "round"])
@pytest.mark.parametrize("step", [1, 2, 4, 10])
def test_bins_agree_with_the_driver_twin(spark, rule, step):
    xs = [0.013, 3.7, 41.2, 222.9, 599.1, 733.3]
    df = spark.createDataFrame([(x,) for x in xs], "x double")
    for s in SCALES:
        got = [r[0] for r in df.selectExpr(s.bin_sql("x", step, rule)).collect()]
        assert got == [s.bin_value(x, step, rule) for x in xs]


def test_bins_of_nulls_and_outside(spark):
    s = Scale("log", (1, 100), (0, 100))
    df = spark.createDataFrame([(None,), (0.0,), (-1.0,), (900.0,)], "x double")
    assert [r[0] for r in df.selectExpr(s.bin_sql("x")).collect()] == [None, None, None, 147]


@pytest.mark.parametrize("x", [10.0, 1000.0])
def test_edges_of_bins_fall_alike_for_data_and_endpoints(spark, x):
    """On an edge the last bit of the logarithm decides: either bin may hold it, but data and endpoints go the same way."""
    s = Scale("log", (1, 100), (0, 100))
    edge = round(s.bins() * math.log(x) / math.log(100))
    data, end = spark.createDataFrame([(x,)], "x double").selectExpr(s.bin_sql("x"), s.bin_sql(f"{x}D")).first()
    assert data == end and data in (edge - 1, edge)


@given(st.sampled_from(SCALES[:4]), st.integers(1, 299))
@settings(max_examples=60, deadline=None)
def test_edge_inverts_forward(s, k):
    x = s.edge(k)
    f0, f1 = map(s.forward, s.domain)
    assert abs(s.bins() * (s.forward(x) - f0) / (f1 - f0) - k) < 1e-6


def test_bad_scales_are_named():
    assert Scale("linear", (1, 1), (0, 5)).problems() and Scale("log", (0, 5), (0, 5)).problems() and Scale("odd", (0, 5), (0, 5)).problems()
    assert not SCALES[0].problems()


def test_predicates_fold():
    a, b = point("a", "x", [1]).predicate, point("b", "y", [2]).predicate
    assert both(a, TRUE) == a and both(a, FALSE) == FALSE and either(a, TRUE) == TRUE and either(FALSE, b) == b
    assert both(a, both(a, b)).sql().count("AND") == 2


def test_point_with_null_and_pairs(spark):
    df = spark.createDataFrame([(1, "a"), (None, "b"), (2, None)], "x int, y string")
    assert df.where(point("s", "x", [None, 2]).predicate.column()).count() == 2
    assert df.where(point("s", ("x", "y"), [(1, "a"), (2, None)]).predicate.column()).count() == 2


def _three():
    return [interval("a", "x", (0, 1)), interval("b", "y", (2, 3)), interval("c", "z", (4, 5))]


def test_resolvers():
    for rule, parts in (("last", 1), ("intersect", 3), ("union", 3)):
        s = Selection(rule)
        for c in _three():
            s.update(c)
        sql = s.predicate("v").sql()
        assert sql.count("BETWEEN") == parts
        assert (" OR " in sql) == (rule == "union")


def test_source_replaces_its_clause():
    s = Selection()
    s.update(interval("a", "x", (0, 1)))
    s.update(interval("a", "x", (5, 6)))
    assert s.predicate("v").sql().count("BETWEEN") == 1 and "5.0" in s.predicate("v").sql()


def test_cross_filter_and_empty():
    s = Selection(cross=True)
    s.update(interval("a", "x", (0, 1), views=["v"]))
    s.update(interval("b", "y", (2, 3), views=["u"]))
    assert "y" in s.predicate("v").sql() and "x BETWEEN" not in s.predicate("v").sql()
    one = Selection(cross=True, empty="none")
    assert one.predicate("v") == FALSE
    one.update(interval("a", "x", (0, 1), views=["v"]))
    assert one.predicate("v") == TRUE  # judged before the exclusion
    one.update(clear(one.active))
    assert one.predicate("v") == FALSE and Selection().predicate("v") == TRUE


def test_composition_relays_and_rejects_cycles():
    up = Selection()
    mid = Selection(includes=[up])
    low = Selection("union", includes=[mid])
    up.update(point("m", "x", [1]))
    mid.update(point("n", "y", [2]))
    assert len(low.clauses()) == 2 and " OR " in low.predicate("v").sql()
    with pytest.raises(ValueError):
        low._feed(up)


def test_interactors_emit_and_clear():
    b = BrushX("drag", column="x", scale=SCALES[0])
    assert b.emit((3, 9)).values == ((3.0, 9.0),) and b.emit(None).cleared and b.example().meta.kind == "interval"
    assert Menu("m", column="k").emit("a").values == (("a",),)
    assert Hover("h", columns=("k", "l")).emit((1, 2)).values == ((1, 2),)
    assert Slider("s", column="x", scale=SCALES[0]).emit(5).meta.rule == "ceil"
    assert len(BrushXY("r", columns=("x", "y"), scales=(SCALES[0], SCALES[0])).emit(((0, 1), (2, 3))).bins()) == 2
    assert Search("q", column="t", kind="prefix").emit("ab").meta.kind == "match"


def test_dispatcher_drops_stale_and_survives_failure():
    gate, seen = threading.Event(), []

    def handler(e):
        seen.append(e)
        if e == 1:
            gate.wait(5)
        f = Future()
        f.set_exception(ValueError()) if e == 3 else f.set_result(None)
        return [f]

    d = Dispatcher(handler)
    d.send(1)
    while not seen:
        time.sleep(0.01)
    d.send(2)
    d.send(3)
    gate.set()
    assert d.drain(5) and seen == [1, 3] and d.dropped == 1 and d.failed == 1
    d.send(4)
    assert d.drain(5) and seen[-1] == 4
    d.close()


def _why(view=HOUR, clause=None, **k):
    return check(Selection(**k), clause or interval("d", "value", (30, 90), w.VALUE), view).reasons


def test_compatibility_names_each_reason():
    assert not _why()
    assert "resolver" in _why(resolve="union")[0]
    assert "clause" in _why(clause=match("f", "x", "a"))[0]
    assert "metadata" in _why(clause=interval("d", "value", (1, 2)))[0]
    assert "scale" in _why(clause=interval("d", "value", (1, 2), Scale("log", (0, 1), (0, 5))))[0]
    assert "view" in _why(replace(HOUR, filter_stable=False))[0]
    assert "source" in _why(replace(HOUR, sources=("orders",)))[0]
    assert "distinct" in _why(replace(HOUR, aggs=(Agg("n", "count", ("x",), distinct=True),)))[0]
    assert "unsupported" in _why(replace(HOUR, aggs=(Agg("n", "median", ("x",)),)))[0]
    assert "inner" in _why(replace(HOUR, inner_keys=("user_id",)))[0] and "inner" in _why(replace(HOUR, opaque="Window"))[0]
    assert any("aggregation" in x for x in _why(t.scatter("s", "events", "a", "b")))
    assert "filter" in check(Selection(), interval("d", "value", (30, 90), w.VALUE), replace(HOUR, aggs=(Agg("n", "count", where="dyn > 1"),)), ("dyn > 1",)).reasons[0]
    assert "domain" in str(check(None, interval("d", "value", (30, 90), Scale("linear", (1, 1), (0, 2))), HOUR).reasons)


def test_reversed_and_halfopen_ends():
    rev = interval("d", "x", (60, 120), Scale("linear", (0, 600), (200, 0)))
    (a, b), = rev.bin_ends()
    assert a is not None and b is not None and "120.0" in a and "60.0" in b
    assert "ceil" in interval("d", "x", (0, 5), SCALES[0], snap="halfopen").bin_predicate().sql()
    assert interval_nd("d", ("x", "y"), ((5, 1), (0, 2)), SCALES[:2]).values[0] == (1.0, 5.0)
    assert slider("s", "x", 3, SCALES[0]).bin_predicate().sql().count("<=") == 1
    assert ViewSpec("v", "s").duck() == "SELECT * FROM (SELECT  FROM (SELECT * FROM s WHERE TRUE))"
