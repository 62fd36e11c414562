"""The experiment workloads on the given tables: fixed axes, views, interactors."""

from __future__ import annotations

from dataclasses import dataclass, replace

from ..functions.safe import epoch_days
from ..model.clause import Clause, interval, interval_nd, slider
from ..model.scales import Scale
from ..views import templates as t
from ..views.spec import Agg, ViewSpec

# Axes: the same for all scale factors, so that an oracle can spell them out.
DAY, SHIP = epoch_days("o_orderdate"), epoch_days("l_shipdate")
HOUR, MINUTE = "hour(ts)", "hour(ts) * 60 + minute(ts)"
VALUE = Scale("linear", (0, 600), (0, 600))
HOURS = Scale("linear", (0, 24), (0, 240))
MINUTES = Scale("linear", (0, 1440), (0, 144))
USERS = Scale("linear", (0, 150), (0, 150))
PRICE, QUANTITY, DISCOUNT = Scale("linear", (0, 110000), (0, 600)), Scale("linear", (0, 50), (0, 600)), Scale("linear", (0, 0.1), (0, 600))
PRICE_Y, TOTAL_Y = Scale("linear", (0, 110000), (0, 200)), Scale("linear", (0, 500000), (0, 200))
DAY_X, SHIP_X, DAY_600 = Scale("linear", (9131, 11600), (0, 300)), Scale("linear", (9131, 11700), (0, 300)), Scale("linear", (9131, 11600), (0, 600))
BALANCE = Scale("linear", (-1000, 10000), (0, 600))
DIM_X, DIM_Y, DIM_600 = Scale("linear", (-0.5, 0.5), (0, 300)), Scale("linear", (-0.5, 0.5), (0, 200)), Scale("linear", (-0.5, 0.5), (0, 600))
SIZE, RETAIL = Scale("linear", (0, 50), (0, 300)), Scale("linear", (900, 1000), (0, 200))


@dataclass(frozen=True)
class Pair:
    """A view, and the clause of an interactor that filters it at relative position and width in [0, 1]."""

    template: str
    view: ViewSpec
    columns: tuple[str, ...]
    scales: tuple[Scale, ...]
    kind: str = "interval"
    step: float = 1

    def clause(self, start: float, width: float) -> Clause:
        ends = [tuple(s.domain[0] + (s.domain[1] - s.domain[0]) * min(1.0, p) for p in (start, start + width)) for s in self.scales]
        if self.kind == "slider":
            return slider("sweep", self.columns[0], ends[0][1], self.scales[0], self.step)
        if len(ends) == 1:
            return interval("sweep", self.columns[0], ends[0], self.scales[0], self.step)
        return interval_nd("sweep", self.columns, ends, self.scales, self.step)


def flight_views(source: str = "events") -> dict[str, ViewSpec]:
    return {
        "value": t.histogram("value", source, "value", 10), "hour": ViewSpec("hour", source, (("x", HOUR),), (Agg("y", "count"),), True), "user": t.histogram("user", source, "user_id", 10),
    }


def item_views(source: str = "lineitem") -> dict[str, ViewSpec]:
    return {"price": t.histogram("price", source, "l_extendedprice", 5500), "quantity": t.histogram("quantity", source, "l_quantity", 5), "discount": ViewSpec("discount", source, (("x", "l_discount"),), (Agg("y", "count"),), True)}


def map_views(source: str = "sales_wide") -> dict[str, ViewSpec]:
    return {"pickup": t.raster("pickup", source, DAY, "o_totalprice", DAY_X, TOTAL_Y), "dropoff": t.raster("dropoff", source, SHIP, "l_extendedprice", SHIP_X, PRICE_Y), "hist": t.histogram("hist", source, "l_quantity", 5)}


def sky_views(source: str = "embeddings") -> dict[str, ViewSpec]:
    e = [f"embedding[{i}]" for i in range(6)]
    return {"sky": t.raster("sky", source, e[0], e[1], DIM_X, DIM_Y), "colour": t.raster("colour", source, e[2], e[3], DIM_X, DIM_Y), "h4": t.histogram("h4", source, e[4], 0.02), "h5": t.histogram("h5", source, e[5], 0.02)}


def catalogue_views(source: str = "sales_wide") -> dict[str, ViewSpec]:
    """The star catalogue on the larger table: two rasters, two histograms."""
    m = map_views(source)
    return {"sky": replace(m["pickup"], id="c_sky"), "colour": replace(m["dropoff"], id="c_colour"), "balance": t.histogram("c_balance", source, "c_acctbal", 500),
            "discount": ViewSpec("c_discount", source, (("x", "l_discount"),), (Agg("y", "count"),), True)}


def pairs(templates: tuple[str, ...] = ("w1", "w1l", "w2", "w3", "w3c", "w4", "w5")) -> list[Pair]:
    """All (active interactor, view) pairs of the templates."""
    out: list[Pair] = []

    def crossed(template: str, views: dict[str, ViewSpec], brushes: dict[str, tuple[tuple[str, ...], tuple[Scale, ...]]]) -> None:
        out.extend(Pair(template, views[v], c, s) for b, (c, s) in brushes.items() for v in views if v != b)

    if "w1" in templates:
        crossed("w1", flight_views(), {"value": (("value",), (VALUE,)), "hour": ((HOUR,), (HOURS,)), "user": (("user_id",), (USERS,))})
    if "w1l" in templates:
        crossed("w1l", item_views(), {"price": (("l_extendedprice",), (PRICE,)), "quantity": (("l_quantity",), (QUANTITY,)), "discount": (("l_discount",), (DISCOUNT,))})
    if "w2" in templates:
        crossed("w2", map_views(), {"pickup": ((DAY, "o_totalprice"), (DAY_X, TOTAL_Y)), "dropoff": ((SHIP, "l_extendedprice"), (SHIP_X, PRICE_Y)), "hist": (("l_quantity",), (QUANTITY,))})
    if "w3" in templates:
        e = [f"embedding[{i}]" for i in range(6)]
        crossed("w3", sky_views(), {"sky": ((e[0], e[1]), (DIM_X, DIM_Y)), "colour": ((e[2], e[3]), (DIM_X, DIM_Y)), "h4": ((e[4],), (DIM_600,)), "h5": ((e[5],), (DIM_600,))})
    if "w3c" in templates:
        crossed("w3c", catalogue_views(), {"sky": ((DAY, "o_totalprice"), (DAY_X, TOTAL_Y)), "colour": ((SHIP, "l_extendedprice"), (SHIP_X, PRICE_Y)), "balance": (("c_acctbal",), (BALANCE,)), "discount": (("l_discount",), (DISCOUNT,))})
    if "w4" in templates:
        out.append(Pair("w4", t.mean_ci("ci", "events", "event_type", "value"), (MINUTE,), (MINUTES,), "slider"))
    if "w5" in templates:
        out.append(Pair("w5", t.regression("fit", "orders", "o_totalprice", DAY), (DAY,), (DAY_600,)))
    return out
