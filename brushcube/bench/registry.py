"""Every registered query of the engine with its oracle. View queries run through the coordinator; oracles state the same predicate on the raw table."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..coord.coordinator import Coordinator
from ..model.clause import Clause, clear, interval, interval_nd, match, point, slider
from ..model.interactors import Hover, Legend
from ..model.pred import both, to_duck
from ..model.scales import Scale
from ..model.selection import Selection
from ..plans import compat, measures
from ..sources.store import SALES_WIDE, load, shared_root
from ..views import templates as t
from ..views.spec import Agg, ViewSpec
from . import workloads as w
from .oracles import by_hand
from .studies import studies

TABLES = ("lineitem", "orders", "customer", "part", "supplier", "nation", "region", "events", "embeddings", "documents", "pages", "labels")


#: Decimals that are compared, where sums are large: 1e12 and more leave a double no reliable second decimal.
DIGITS = {"regr_syy": 0, "regr_sxy": 2, "covar_samp": 2, "covar_pop": 2, "regr_sxx": 2}


def coordinator(spark: SparkSession, sf_dir: str, **options) -> Coordinator:
    c = Coordinator(spark, **options)
    for name in (*TABLES, "sales_wide"):
        # read on first use: a relation is only resolved when a view asks for it
        c.relations._known.pop(name, None)
    c.relations.get = _lazy(c, spark, sf_dir)
    return c


def _lazy(c: Coordinator, spark: SparkSession, sf_dir: str) -> Callable:
    plain = type(c.relations).get

    def get(name: str):
        if name not in c.relations._known and name in (*TABLES, "sales_wide"):
            c.relations.add(name, load(spark, sf_dir, name))
        return plain(c.relations, name)

    return get


def tidy(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(F.col(c), digits).alias(c) if k == "double" else F.col(c) for c, k in df.dtypes])


def tidy_sql(q: str, cols: list[tuple[str, bool]], digits: int = 6) -> str:
    return f"SELECT {', '.join(f'round(CAST({c} AS DOUBLE), {digits}) AS {c}' if d else c for c, d in cols)} FROM ({q})"


@dataclass(frozen=True)
class Case:
    """A view under clauses, the last one active. ``path``: how the coordinator must answer. ``doubles``: columns that are rounded."""

    view: ViewSpec
    clauses: tuple[Clause, ...]
    resolve: str = "intersect"
    cross: bool = False
    empty: str = "all"
    path: str = "cells"
    digits: int = 6
    doubles: tuple[str, ...] = ()
    ints: tuple[str, ...] = ()
    then: Clause | None = None  # a first clause that is replaced

    def selection(self) -> Selection:
        s = Selection(self.resolve, self.cross, self.empty)
        for c in ((self.then,) if self.then else ()) + self.clauses:
            s.update(c)
        return s

    def run(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        sel, coord = self.selection(), coordinator(spark, sf_dir)
        df, path, reasons = coord.frame(self.view, sel, sel.active)
        if path != self.path:
            raise AssertionError(f"{self.view.id} was answered by {path}: {reasons}")
        return tidy(df, self.digits)

    def sql(self, text: str | None = None) -> str:
        """The oracle's SQL: ``text``, if it was written by hand, else from the view and the clauses."""
        names = list(self.view.columns) or [a for a, _ in self.view.group] + [a.alias for a in self.view.aggs] + [a for a, _ in self.view.post]
        if text:
            return tidy_sql(text, [(c, c in self.doubles) for c in names], self.digits)
        sel = self.selection()
        if self.path == "cells":
            pred = both(sel.residual(self.view.id, sel.active), sel.active.bin_predicate())
        else:
            pred = sel.predicate(self.view.id)
        q = self.view.duck(pred, SALES_WIDE if self.view.source == "sales_wide" else None)
        return tidy_sql(q, [(c, c in self.doubles) for c in names], self.digits)


def _hours(id: str = "hour") -> ViewSpec:
    return replace(w.flight_views()["hour"], id=id)


def _brush(lo=30, hi=90, scale=w.VALUE, col="value", source="drag", **k) -> Clause:
    return interval(source, col, (lo, hi), scale, **k)


def view_cases() -> dict[str, Case]:
    hour, fv, iv, mv, sv = _hours(), w.flight_views(), w.item_views(), w.map_views(), w.sky_views()
    out: dict[str, Case] = {}
    scales = {"linear": w.VALUE, "log": Scale("log", (0.01, 1000), (0, 300)), "pow": Scale("pow", (0, 600), (0, 600), exponent=0.5), "symlog": Scale("symlog", (-600, 600), (0, 600), constant=1)}
    for k, s in scales.items():
        out[f"scale_{k}"] = Case(hour, (_brush(31.7, 90.3, s),))
        bins = ViewSpec(f"bins_{k}", "events", (("b", s.bin_sql("value")),), (Agg("n", "count"),), True)
        out[f"scale_{k}_bins"] = Case(bins, (interval("drag", w.HOUR, (3, 9), w.HOURS),))
    for r in ("floor", "ceil", "round"):
        out[f"bin_{r}"] = Case(hour, (_brush(30.2, 90.7, rule=r),))
    for s in (2, 4, 10):
        out[f"bin_step{s}"] = Case(hour, (_brush(33, 91, step=s),))
    out["bin_reversed"] = Case(hour, (_brush(60, 120, Scale("linear", (0, 600), (200, 0))),))
    out["bin_outside_domain"] = Case(hour, (_brush(-50, 400, Scale("linear", (50, 300), (0, 250))),))
    out["bin_halfopen"] = Case(hour, (_brush(30, 90, snap="halfopen"),))
    types = replace(hour, id="types", group=(("event_type", "event_type"),))
    out["clause_point1"] = Case(hour, (point("menu", "event_type", ["click", "view"]),))
    out["clause_point2"] = Case(iv["quantity"], (point("menu", ("l_returnflag", "l_linestatus"), [("R", "O"), ("A", "F")]),), doubles=("x",))
    out["clause_interval1d"] = Case(iv["quantity"], (_brush(22000, 33000, w.PRICE, "l_extendedprice"),), doubles=("x",))
    box = interval_nd("area", (w.DAY, "o_totalprice"), ((9600, 10100), (125000, 225000)), (w.DAY_X, w.TOTAL_Y))
    out["clause_interval2d"] = Case(ViewSpec("prio", "orders", (("o_orderpriority", "o_orderpriority"),), (Agg("n", "count"),), True), (box,))
    out["clause_slider"] = Case(types, (slider("slide", w.MINUTE, 720, w.MINUTES),))
    brands = ViewSpec("brands", "part", (("p_brand", "p_brand"),), (Agg("n", "count"),), True)
    for kind, text in (("prefix", "red"), ("suffix", "ring"), ("contains", "blue"), ("regexp", "^(red|blue) ")):
        out[f"match_{kind}"] = Case(brands, (match("find", "p_name", text, kind),), path="direct")
    three = (_brush(30, 200), interval("time", w.HOUR, (6, 18), w.HOURS), interval("who", "user_id", (20, 90), w.USERS))
    for r in ("last", "intersect", "union"):
        out[f"resolve_{r}"] = Case(types, three, r, path="direct" if r == "union" else "cells")
        mine = tuple(replace(c, views=frozenset({v})) for c, v in zip(three, ("value", "hour", "user")))
        out[f"cross_{r}"] = Case(hour, (mine[1], mine[0]), r, cross=True, path="direct" if r == "union" else "cells")
    out["empty_all"] = Case(types, (clear(_brush()),))
    out["mv_cleared"] = Case(types, (clear(_brush()),), then=_brush())
    out["mv_residual"] = Case(types, (point("menu", "event_type", ["click", "error", "view"]), _brush(10, 60)))

    # The thirty functions, under a price interval, by return flag.
    price = _brush(22000, 66000, w.PRICE, "l_extendedprice")
    q, p = "l_quantity", "l_extendedprice"
    args = {"count": ("*",), "product": ("1 + l_tax / 1000",), "bit_and": ("l_partkey",), "bit_or": ("l_partkey",), "bit_xor": ("l_partkey",), "bool_and": ("l_tax > 0",), "bool_or": ("l_tax > 0",),
            "arg_max": ("l_partkey", f"struct({p}, l_partkey)"), "arg_min": ("l_partkey", f"struct({p}, l_partkey)")}
    exact = {"count", "bit_and", "bit_or", "bit_xor", "bool_and", "bool_or", "arg_max", "arg_min", "regr_count"}
    for fn in measures.FUNCTIONS:
        a = args.get(fn) or ((p, q) if measures.FUNCTIONS[fn] == 2 else (q,))
        v = ViewSpec(f"agg_{fn}", "lineitem", (("flag", "l_returnflag"),), (Agg("v", fn, a),), True)
        out[f"agg_{fn}"] = Case(v, (price,), doubles=() if fn in exact else ("v",), digits=DIGITS.get(fn, 6))
    by = lambda id, *aggs, **k: ViewSpec(id, "lineitem", (("flag", "l_returnflag"),), aggs, True, **k)
    out["agg_filter"] = Case(by("agg_filter", Agg("n", "count", where="l_tax > CAST(0.04 AS DOUBLE)"), Agg("s", "avg", (q,), "l_linestatus = 'O'")), (price,), doubles=("s",))
    out["agg_having"] = Case(ViewSpec("agg_having", "lineitem", (("size", "l_quantity"),), (Agg("n", "count"),), True, having="n > 100", order=("n DESC", "size"), limit=20), (price,), doubles=("size",))
    out["agg_expr_ci"] = Case(t.mean_ci("ci", "lineitem", "l_returnflag", q), (price,), doubles=("mean", "sd", "lo", "hi"))
    for name, v, c, r in (
        ("union", hour, _brush(), "union"), ("match", brands, match("find", "p_name", "red", "prefix"), "intersect"), ("unstable", replace(hour, id="unstable", filter_stable=False), _brush(), "intersect"),
        ("distinct", by("distinct", Agg("n", "count", ("l_suppkey",), distinct=True)), price, "intersect"), ("median", by("median", Agg("m", "median", (q,))), price, "intersect"), ("no_scale", hour, interval("x", "value", (30, 90)), "intersect"),
    ):
        out[f"reject_{name}"] = Case(v, (c,), r, path="direct", doubles=("m",))

    # Workloads.
    out["w1_hour"] = Case(hour, (_brush(),))
    out["w1_value"] = Case(fv["value"], (interval("time", w.HOUR, (6, 12), w.HOURS),), doubles=("x",))
    out["w1_user"] = Case(fv["user"], (_brush(),), doubles=("x",))
    for k, c in (("price", interval("q", q, (10, 20), w.QUANTITY)), ("quantity", price), ("discount", price)):
        out[f"w1l_{k}"] = Case(iv[k], (c,), doubles=("x",))
    pick = interval_nd("pick", (w.DAY, "o_totalprice"), ((9624.8, 10110.7), (125000, 222500)), (w.DAY_X, w.TOTAL_Y))
    drop = interval_nd("drop", (w.SHIP, "l_extendedprice"), ((9700, 10400), (30000, 60000)), (w.SHIP_X, w.PRICE_Y))
    out["w2_dropoff"] = Case(mv["dropoff"], (pick,))
    out["w2_pickup"] = Case(mv["pickup"], (pick, drop), cross=False)
    out["w2_hist"] = Case(mv["hist"], (pick, drop), doubles=("x",))
    e = [f"embedding[{i}]" for i in range(6)]
    sky = interval_nd("sky", (e[0], e[1]), ((-0.1, 0.2), (-0.15, 0.1)), (w.DIM_X, w.DIM_Y))
    out["w3_sky"] = Case(sv["sky"], (interval("h4", e[4], (-0.1, 0.1), w.DIM_600),))
    out["w3_colour"] = Case(sv["colour"], (sky,))
    out["w3_hist"] = Case(sv["h4"], (sky,), doubles=("x",))
    stars = interval_nd("sky", (w.DAY, "o_totalprice"), ((9700, 10100), (100000, 200000)), (w.DAY_X, w.TOTAL_Y))
    cat = w.catalogue_views()
    out["w3c_sky"] = Case(cat["sky"], (interval("balance", "c_acctbal", (2000, 6000), w.BALANCE),))
    out["w3c_colour"] = Case(cat["colour"], (stars,))
    out["w3c_balance"] = Case(cat["balance"], (stars,), doubles=("x",))
    out["w3c_discount"] = Case(cat["discount"], (stars,), doubles=("x",))
    out["w4_ci"] = Case(t.mean_ci("w4", "events", "event_type", "value"), (slider("slide", w.MINUTE, 720, w.MINUTES),), doubles=("mean", "sd", "lo", "hi"))
    out["w5_fit"] = Case(replace(t.regression("w5", "orders", "o_totalprice", w.DAY), columns=("n", "slope", "r2", "avgx", "avgy")), (interval("days", w.DAY, (9131 + 200 * 2469 / 600 + 1, 9131 + 319 * 2469 / 600 + 1), w.DAY_600),), doubles=("slope", "r2", "avgx", "avgy"), digits=5)
    promo = point("type", "p_type", ["PROMO"])
    region = interval_nd("region", ("p_size", "p_retailprice"), ((10, 30), (920, 960)), (w.SIZE, w.RETAIL))
    mx, my = t.marginals("w6", "part", "p_size", "p_retailprice", w.SIZE, w.RETAIL)
    out["w6_menu"] = Case(t.menu("menu", "part", "p_brand"), (promo,))
    out["w6_marginal_x"] = Case(mx, (promo, region))
    out["w6_marginal_y"] = Case(my, (region,))
    out["w6_brands"] = Case(ViewSpec("w6b", "part", (("p_brand", "p_brand"),), (Agg("n", "count"),), True, order=("n DESC", "p_brand"), limit=10), (promo,))
    out["w6_legend"] = Case(brands, (Legend("legend", column="p_type").emit(["PROMO", "ECONOMY"]),))
    out["w6_hover"] = Case(ViewSpec("w6h", "part", (("p_type", "p_type"),), (Agg("n", "count"),), True), (Hover("hover", columns=("p_brand", "p_size")).emit(("Brand#8", 10)),))
    out["w6_scatter"] = Case(t.scatter("w6s", "part", "p_size", "p_retailprice", "p_partkey"), (promo, region), path="direct", doubles=("y",))
    out["w6_table"] = Case(t.table_window("w6t", "part", ("p_partkey", "p_brand", "p_retailprice"), ("p_retailprice DESC", "p_partkey"), 20, 15), (promo,), path="direct", doubles=("p_retailprice",))
    out["w7_search"] = Case(ViewSpec("w7", "documents", (("lang", "lang"),), (Agg("n", "count"), Agg("chars", "sum", ("n_chars",))), True), (match("find", "text", "Licensed", "contains"),), path="direct", doubles=("chars",))
    out["w7_urls"] = Case(ViewSpec("w7u", "pages", (), (Agg("n", "count"),), True), (match("find", "url", "https", "prefix"),), path="direct")
    out["view_hexbin"] = Case(t.hexbin("hex", "embeddings", e[0], e[1], 0.02), (interval("h4", e[4], (-0.1, 0.1), w.DIM_600),), doubles=("cx", "cy"))
    out["view_summary"] = Case(t.summary("sum", "lineitem", (Agg("n", "count"), Agg("m", "avg", (q,)), Agg("least", "min", (p,)))), (interval("q", q, (10, 20), w.QUANTITY),), doubles=("m", "least"))
    out["view_pixelcol"] = Case(t.pixel_column("px", "events", "event_id", "value", Scale("linear", (0, 10000), (0, 100))), (interval("time", w.HOUR, (6, 12), w.HOURS),), doubles=("vmin", "vmax", "v_at_tmin", "v_at_tmax"))
    return out


# -- queries beyond one view under one selection --------------------------------------------------------------------------
def _frame(spark, sf_dir, view, clause, **k) -> DataFrame:
    s = Selection(**k)
    s.update(clause)
    return coordinator(spark, sf_dir).frame(view, s, clause)[0]


def compose_includes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Type menu -> brand menu -> histogram of sizes: clauses of upstream selections filter downstream."""
    types, brands = Selection(), Selection()
    region = Selection(includes=(types, brands))
    types.update(point("type", "p_type", ["PROMO", "STANDARD"]))
    brands.update(point("brand", "p_brand", ["Brand#2", "Brand#8", "Brand#9"]))
    view = ViewSpec("sizes", "part", (("p_size", "p_size"),), (Agg("n", "count"),), True)
    return coordinator(spark, sf_dir).frame(view, region, region.active)[0]


def empty_none(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A selection that keeps nothing while it is empty: types of event before the first brush, under it, and after it is cleared."""
    coord, sel, out = coordinator(spark, sf_dir), Selection(empty="none"), None
    types = replace(_hours("types"), group=(("event_type", "event_type"),))
    for state, clause, by in (("before", None, "direct"), ("brushed", _brush(), "cells"), ("cleared", clear(_brush()), "direct")):
        if clause:
            sel.update(clause)
        got, path, reasons = coord.frame(types, sel, sel.active)
        assert path == by, reasons
        got = got.select(F.lit(state).alias("state"), *got.columns)
        out = got if out is None else out.unionByName(got)
    return out


def mv_precompute_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells built ahead for every shape; with resolver last, updates only ever find them."""
    coord, sel = coordinator(spark, sf_dir), Selection("last")
    view = _hours()
    coord.connect(view, sel)
    shapes = [_brush(), point("menu", "event_type", ["click"])]
    built = coord.precompute(sel, shapes)
    before = coord.store.builds
    sel.update(shapes[0])
    coord.settle()
    sel.update(point("menu", "event_type", ["view", "click"]))
    coord.settle()
    assert len(built) == 2 and coord.store.builds == before
    out = coord.frame(view, sel, sel.active)[0]
    coord.close()
    return out


def view_linear(two: bool) -> Callable:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = t.linear_density("lin", "events", "value", Scale("linear", (0, 600), (0, 60)), *(("user_id", Scale("linear", (0, 150), (0, 15))) if two else ()))
        return tidy(_frame(spark, sf_dir, v, interval("time", w.HOUR, (6, 12), w.HOURS)))

    return run


def view_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Density of many lines: cells per series and column, each series' column normalised to 1, summed over the chosen series. The clause picks series, so the inner step is sound."""
    cells = load(spark, sf_dir, "events").selectExpr("user_id", f"{w.HOUR} AS x", "CAST(floor(value / 20D) AS BIGINT) AS y").groupBy("user_id", "x", "y").agg(F.count("*").alias("k"))
    total = cells.groupBy("user_id", "x").agg(F.sum("k").alias("t"))
    norm = cells.join(total, ["user_id", "x"]).withColumn("share", F.col("k") / F.col("t"))
    coord = coordinator(spark, sf_dir)
    coord.relation("line_cells", norm)
    view = ViewSpec("lines", "line_cells", (("x", "x"), ("y", "y")), (Agg("w", "sum", ("share",)),), True, inner_keys=("user_id", "x", "y"))
    sel = Selection()
    sel.update(point("who", "user_id", list(range(0, 40))))
    return tidy(coord.frame(view, sel, sel.active)[0])


def dense_tile(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.baselines import Axis, dense_frame

    ev = load(spark, sf_dir, "events")
    dense = dense_frame(ev, [Axis("x", w.HOUR, 0, 24)], _brush())
    return dense.where("a_0 BETWEEN 30 AND 90").groupBy("x").agg(F.sum("v").cast("long").alias("y"))


def prefix_tile(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.baselines import Axis, dense_frame, prefix_frame

    ev = load(spark, sf_dir, "events")
    sums = prefix_frame(dense_frame(ev, [Axis("x", w.HOUR, 0, 24)], _brush()), ["x"], ["a_0"])
    corner = F.when(F.col("a_0") == 90, F.col("v")).when(F.col("a_0") == 29, -F.col("v"))
    return sums.where("a_0 IN (29, 90)").groupBy("x").agg(F.sum(corner).cast("long").alias("y"))


def consolidated_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..coord.consolidate import consolidated

    key = (("flag", "l_returnflag"),)
    views = [ViewSpec("n", "lineitem", key, (Agg("n", "count"),)), ViewSpec("q", "lineitem", key, (Agg("mean", "avg", ("l_quantity",)),))]
    got = consolidated(views, load(spark, sf_dir, "lineitem"), _brush(22000, 66000, w.PRICE, "l_extendedprice").predicate)
    return tidy(got["n"].join(got["q"], "flag"))


def grouping_sets_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..coord.consolidate import grouping_sets

    views = [ViewSpec("f", "lineitem", (("flag", "l_returnflag"),), (Agg("n", "count"),)), ViewSpec("s", "lineitem", (("status", "l_linestatus"),), (Agg("n", "count"),))]
    return grouping_sets(views, load(spark, sf_dir, "lineitem")).select(F.coalesce("k0_flag", "k1_status").alias("value"), "view", "n")


def sketch(kind: str) -> Callable:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        measures.register_sketches()
        arg = "l_extendedprice" if kind.startswith("kll") else "l_partkey" if kind != "bitmap_distinct" else "l_linenumber"
        v = ViewSpec(kind, "lineitem", (("flag", "l_returnflag"),), (Agg("v", kind, (arg,)),), True)
        df, path, _ = (coord := coordinator(spark, sf_dir)).frame(v, (s := _sel(interval("q", "l_quantity", (10, 20), w.QUANTITY))), s.active)
        assert path == "cells" and coord
        return df

    return run


def _sel(c: Clause, **k) -> Selection:
    s = Selection(**k)
    s.update(c)
    return s


def sql_view_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view given as SQL text with a CTE and HAVING, answered from cells."""
    coord, sel = coordinator(spark, sf_dir), _sel(_brush(22000, 66000, w.PRICE, "l_extendedprice"))
    load(spark, sf_dir, "lineitem").createOrReplaceTempView("brushcube_items")
    why = coord.sql("sqlv", "WITH r AS (SELECT * FROM brushcube_items WHERE l_tax > 0) SELECT l_returnflag AS flag, count(*) AS n, avg(l_quantity) AS m FROM r GROUP BY l_returnflag HAVING count(*) > 10", sel, True)
    why = why or coord.sql("sqlv2", "WITH r AS (SELECT * FROM brushcube_items WHERE l_tax > 0) SELECT l_returnflag AS flag, count(*) AS n, avg(l_quantity) AS m FROM r GROUP BY l_returnflag", sel, True)
    view, _ = coord.views["sqlv2"]
    df, path, reasons = coord.frame(view, sel, sel.active)
    assert path == "cells", reasons
    coord.close()
    return tidy(df)


def stream_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events replayed as a stream of files into delta cells, then asked."""
    import uuid

    from ..streaming.maintain import LiveCells

    folder = f"{shared_root(spark)}/stream-{uuid.uuid4().hex}"
    events = load(spark, sf_dir, "events")
    events.repartition(4).write.parquet(f"{folder}/in")
    live = LiveCells(spark, folder, _hours(), _brush())
    q = live.start(spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in"))
    q.awaitTermination()
    return live.answer(_brush())


def cache_race(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An older event that is answered after a newer clause arrived, then the newer one: each by its own clause, the cache included."""
    coord, sel, view, frames = coordinator(spark, sf_dir), Selection(), _hours(), []
    coord.views[view.id] = (view, sel)
    older, newer = _brush(30, 90), _brush(200, 400)
    sel.update(older)
    state = sel.freeze(older)
    sel.update(newer)
    for name, got in (("older", coord.query(view.id, older, state)), ("newer", coord.query(view.id, newer)), ("cached", coord.query(view.id, newer))):
        frames.append(spark.createDataFrame(got).select(F.lit(name).alias("event"), "x", "y"))
    coord.close()
    return frames[0].unionByName(frames[1]).unionByName(frames[2])


def snapshot_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One name and the same files, read with another filter, and from a frame of the session: cells of one are never taken for the other's."""
    coord, out = coordinator(spark, sf_dir), None
    ev = load(spark, sf_dir, "events")
    for kind in ("view", "click"):
        for relation in (ev.where(F.col("event_type") == kind), spark.createDataFrame(ev.where(F.col("event_type") == kind).toArrow())):
            coord.relation("events", relation)
            got = coord.frame(_hours(), sel := _sel(_brush()), sel.active)[0].select(F.lit(kind).alias("kind"), "x", "y")
            out = got if out is None else out.unionByName(got)
    return out


def gate_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gate's estimate of cells per row lies within a tenth of the truth."""
    coord = coordinator(spark, sf_dir)
    found = coord.cells.worth(w.item_views()["quantity"], _brush(22000, 66000, w.PRICE, "l_extendedprice"))
    exact = load(spark, sf_dir, "lineitem").selectExpr("floor(l_quantity / 5D) AS q", f"{w.PRICE.bin_sql('l_extendedprice')} AS p").agg(F.count_distinct("q", "p") / F.count("*")).first()[0]
    return spark.range(1).select(F.lit(abs(found - exact) <= 0.1 * exact).alias("near"), F.lit(found < 0.5).alias("worth"))


def highlight(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = interval_nd("region", ("p_size", "p_retailprice"), ((10, 30), (920, 960)), (w.SIZE, w.RETAIL))
    return load(spark, sf_dir, "part").select("p_partkey", c.predicate.column().alias("selected"))


def windowed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A window value in a subquery, filtered outside: always the direct path."""
    from pyspark.sql import Window as W

    last = W.partitionBy("user_id").orderBy("ts", "event_id")
    rows = load(spark, sf_dir, "events").withColumn("gap", F.round(F.col("value") - F.lag("value").over(last), 6))
    return rows.where("gap > 300").select("event_id", "user_id", "gap")


_H = f"SELECT {w.HOUR} AS x, count(*) AS y FROM events WHERE CAST(floor(CAST(600.0 AS DOUBLE) * value / CAST(600.0 AS DOUBLE)) AS BIGINT) BETWEEN 30 AND 90 GROUP BY 1"
_P = "l_extendedprice BETWEEN 22000 AND 66000"
_U, _V = "(CAST(60.0 AS DOUBLE) * (value - CAST(0.0 AS DOUBLE)) / (CAST(600.0 AS DOUBLE) - CAST(0.0 AS DOUBLE)))", "(CAST(15.0 AS DOUBLE) * (CAST(user_id AS DOUBLE) - CAST(0.0 AS DOUBLE)) / (CAST(150.0 AS DOUBLE) - CAST(0.0 AS DOUBLE)))"
_HRS = "hour(ts) BETWEEN 6 AND 12"


def _linear_sql(two: bool) -> str:
    rows = f"SELECT {_U} AS u, {_V} AS v FROM events WHERE {_HRS}"
    parts = []
    for i in (0, 1):
        for j in (0, 1) if two else (None,):
            wx = "u - floor(u)" if i else "1 - (u - floor(u))"
            wy = "" if j is None else f" * ({'v - floor(v)' if j else '1 - (v - floor(v))'})"
            parts.append(f"SELECT CAST(floor(u) + {i} AS BIGINT) AS x{'' if j is None else f', CAST(floor(v) + {j} AS BIGINT) AS y'}, ({wx}){wy} AS w FROM r")
    keys = "x, y" if two else "x"
    return f"WITH r AS ({rows}) SELECT {keys}, round(sum(w), 6) AS w FROM ({' UNION ALL '.join(parts)}) GROUP BY {keys}"


def other() -> dict[str, tuple[Callable, str | None]]:
    return {
        "compose_includes": (compose_includes, "SELECT p_size, count(*) AS n FROM part WHERE p_type IN ('PROMO', 'STANDARD') AND p_brand IN ('Brand#2', 'Brand#8', 'Brand#9') GROUP BY 1"),
        "empty_none": (empty_none, "SELECT 'brushed' AS state, event_type, count(*) AS y FROM events WHERE floor(value) BETWEEN 30 AND 90 GROUP BY 2"),
        "mv_precompute_last": (mv_precompute_last, f"SELECT {w.HOUR} AS x, count(*) AS y FROM events WHERE event_type IN ('view', 'click') GROUP BY 1"),
        "view_linear1d": (view_linear(False), _linear_sql(False)), "view_linear2d": (view_linear(True), _linear_sql(True)),
        "view_lines": (view_lines, f"WITH c AS (SELECT user_id, {w.HOUR} AS x, CAST(floor(value / 20) AS BIGINT) AS y, count(*) AS k FROM events GROUP BY 1, 2, 3), n AS (SELECT *, k / sum(k) OVER (PARTITION BY user_id, x) AS s FROM c) SELECT x, y, round(sum(s), 6) AS w FROM n WHERE user_id BETWEEN 0 AND 39 GROUP BY 1, 2"),
        "dense_tile": (dense_tile, _H), "prefix_tile": (prefix_tile, _H), "stream_cells": (stream_cells, _H),
        "consolidated": (consolidated_query, f"SELECT l_returnflag AS flag, count(*) AS n, round(avg(l_quantity), 6) AS mean FROM lineitem WHERE {_P} GROUP BY 1"),
        "grouping_sets": (grouping_sets_query, "SELECT l_returnflag AS value, 0::INTEGER AS view, count(*) AS n FROM lineitem GROUP BY 1 UNION ALL SELECT l_linestatus, 1, count(*) FROM lineitem GROUP BY 1"),
        "sql_view": (sql_view_query, "SELECT l_returnflag AS flag, count(*) AS n, round(avg(l_quantity), 6) AS m FROM lineitem WHERE l_tax > 0 AND CAST(floor(CAST(600.0 AS DOUBLE) * (l_extendedprice - 0) / CAST(110000.0 AS DOUBLE)) AS BIGINT) BETWEEN 120 AND 360 GROUP BY 1"),
        "cache_race": (cache_race, f"WITH e AS (SELECT {w.HOUR} AS x, floor(value) AS v FROM events), n AS (SELECT x, count(*) AS y FROM e WHERE v BETWEEN 200 AND 400 GROUP BY 1) "
                       "SELECT 'older' AS event, x, count(*) AS y FROM e WHERE v BETWEEN 30 AND 90 GROUP BY 2 UNION ALL SELECT 'newer', x, y FROM n UNION ALL SELECT 'cached', x, y FROM n"),
        "snapshot_plan": (snapshot_plan, f"SELECT event_type AS kind, {w.HOUR} AS x, count(*) AS y FROM events, range(2) WHERE event_type IN ('view', 'click') AND floor(value) BETWEEN 30 AND 90 GROUP BY 1, 2, range"),
        "gate_estimate": (gate_estimate, "SELECT true AS near, count(DISTINCT (floor(l_quantity / 5), floor(600 * l_extendedprice / 110000))) / count(*) < 0.5 AS worth FROM lineitem"),
        "w6_highlight": (highlight, "SELECT p_partkey, p_size BETWEEN 10 AND 30 AND p_retailprice BETWEEN 920 AND 960 AS selected FROM part"),
        "view_windowed": (windowed, "SELECT event_id, user_id, gap FROM (SELECT *, round(value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), 6) AS gap FROM events) WHERE gap > 300"),
        "sketch_bitmap": (sketch("bitmap_distinct"), "SELECT l_returnflag AS flag, count(DISTINCT l_linenumber) AS v FROM lineitem WHERE CAST(floor(CAST(600.0 AS DOUBLE) * l_quantity / CAST(50.0 AS DOUBLE)) AS BIGINT) BETWEEN 120 AND 240 GROUP BY 1"),
    }


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from ..operators import relational

    return {k: c.run for k, c in view_cases().items()} | {k: f for k, (f, _) in (other() | studies()).items()} | relational.queries()


def oracle_sql() -> dict[str, str]:
    from ..operators import relational

    own = by_hand()
    return {k: c.sql(own.get(k)) for k, c in view_cases().items()} | {k: to_duck(s) if "unix_" in s else s for k, (_, s) in (other() | studies()).items() if s} | relational.oracle_sql()
