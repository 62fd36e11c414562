"""SQL of view queries, written by hand for the oracle engine: bins, predicates and keys are spelled out here and share no text with the engine's."""

from __future__ import annotations

WIDE = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"
DAY, SHIP = ("date_diff('day', DATE '1970-01-01', CAST({} AS DATE))".format(c) for c in ("o_orderdate", "l_shipdate"))
MINUTE = "(hour(ts) * 60 + minute(ts))"


def pixel(x: str, first: float, last: float, pixels: float) -> str:
    """Pixel of a value on a linear axis from ``first`` to ``last``."""
    return f"floor({float(pixels)}::DOUBLE * (({x})::DOUBLE - {float(first)}::DOUBLE) / {float(last - first)}::DOUBLE)"


def drag(x: str, ends: tuple[float, float], axis: tuple[float, float, float]) -> str:
    """Rows in the pixels from that of one end to that of the other."""
    return f"{pixel(x, *axis)} BETWEEN {pixel(str(ends[0]), *axis)} AND {pixel(str(ends[1]), *axis)}"


def hours(where: str) -> str:
    return f"SELECT hour(ts) AS x, count(*) AS y FROM events WHERE {where} GROUP BY 1"


def kinds(where: str) -> str:
    return f"SELECT event_type, count(*) AS y FROM events WHERE {where} GROUP BY 1"


def steps(x: str, width: float, where: str, source: str) -> str:
    return f"SELECT {float(width)}::DOUBLE * floor(({x})::DOUBLE / {float(width)}::DOUBLE) AS x, count(*) AS y FROM {source} WHERE {where} GROUP BY 1"


def raster(x: str, xaxis: tuple, y: str, yaxis: tuple, where: str, source: str) -> str:
    return f"SELECT {pixel(x, *xaxis)}::BIGINT AS x, {pixel(y, *yaxis)}::BIGINT AS y, count(*) AS n FROM {source} WHERE {where} GROUP BY 1, 2"


PRICE, QUANTITY = (0, 110000, 600), (0, 50, 600)
DAY_X, TOTAL_Y, SHIP_X, PRICE_Y = (9131, 11600, 300), (0, 500000, 200), (9131, 11700, 300), (0, 110000, 200)
DIM_X, DIM_Y, DIM = (-0.5, 0.5, 300), (-0.5, 0.5, 200), (-0.5, 0.5, 600)
PRICED, FEW = drag("l_extendedprice", (22000, 66000), PRICE), drag("l_quantity", (10, 20), QUANTITY)
PICK = f"{drag(DAY, (9624.8, 10110.7), DAY_X)} AND {drag('o_totalprice', (125000, 222500), TOTAL_Y)}"
PICK_RAW = f"{DAY} BETWEEN 9624.8 AND 10110.7 AND o_totalprice BETWEEN 125000 AND 222500"
DROP = f"{drag(SHIP, (9700, 10400), SHIP_X)} AND {drag('l_extendedprice', (30000, 60000), PRICE_Y)}"
SKY = f"{drag('embedding[1]', (-0.1, 0.2), DIM_X)} AND {drag('embedding[2]', (-0.15, 0.1), DIM_Y)}"
H4 = drag("embedding[5]", (-0.1, 0.1), DIM)
STARS = f"{drag(DAY, (9700, 10100), DAY_X)} AND {drag('o_totalprice', (100000, 200000), TOTAL_Y)}"
RICH = drag("c_acctbal", (2000, 6000), (-1000, 10000, 600))
PROMO = "p_type = 'PROMO'"
REGION = f"{drag('p_size', (10, 30), (0, 50, 300))} AND {drag('p_retailprice', (920, 960), (900, 1000, 200))}"
REGION_RAW = "p_size BETWEEN 10 AND 30 AND p_retailprice BETWEEN 920 AND 960"
BRANDS = "SELECT p_brand, count(*) AS n FROM part WHERE {} GROUP BY 1"

#: Bins of a value of ``events`` on each kind of scale.
SCALED = {
    "linear": "floor(({0})::DOUBLE)",
    "log": "floor(300 * (ln(CASE WHEN ({0})::DOUBLE > 0 THEN ({0})::DOUBLE END) - ln(0.01::DOUBLE)) / (ln(1000::DOUBLE) - ln(0.01::DOUBLE)))",
    "pow": "floor(600 * (sign({0}) * sqrt(abs(({0})::DOUBLE)) - 0) / sqrt(600::DOUBLE))",
    "symlog": "floor(600 * (sign({0}) * ln(1 + abs(({0})::DOUBLE)) + ln(601::DOUBLE)) / (2 * ln(601::DOUBLE)))",
}


def by_hand() -> dict[str, str]:
    out: dict[str, str] = {}
    for k, text in SCALED.items():
        out[f"scale_{k}"] = hours(f"{text.format('value')} BETWEEN {text.format('31.7')} AND {text.format('90.3')}")
        out[f"scale_{k}_bins"] = f"SELECT {text.format('value')}::BIGINT AS b, count(*) AS n FROM events WHERE hour(ts) BETWEEN 3 AND 9 GROUP BY 1"
    out["bin_floor"] = hours("floor(value) BETWEEN 30 AND 90")
    out["bin_ceil"] = hours("ceil(value) BETWEEN 31 AND 91")
    out["bin_round"] = hours("floor(value + 0.5) BETWEEN 30 AND 91")
    for s in (2, 4, 10):
        out[f"bin_step{s}"] = hours(f"floor(value / {s}) BETWEEN {33 // s} AND {91 // s}")
    out["bin_reversed"] = hours("floor(-200 * value / 600) BETWEEN -40 AND -20")
    out["bin_outside_domain"] = hours("floor(value - 50) BETWEEN -100 AND 350")
    out["bin_halfopen"] = hours("floor(value) BETWEEN 30 AND 89")
    out["clause_point1"] = hours("event_type IN ('click', 'view')")
    out["clause_point2"] = steps("l_quantity", 5, "(l_returnflag = 'R' AND l_linestatus = 'O') OR (l_returnflag = 'A' AND l_linestatus = 'F')", "lineitem")
    out["clause_interval1d"] = steps("l_quantity", 5, drag("l_extendedprice", (22000, 33000), PRICE), "lineitem")
    out["clause_interval2d"] = f"SELECT o_orderpriority, count(*) AS n FROM orders WHERE {drag(DAY, (9600, 10100), DAY_X)} AND {drag('o_totalprice', (125000, 225000), TOTAL_Y)} GROUP BY 1"
    out["clause_slider"] = kinds(f"ceil({MINUTE} / 10.0) <= 72")
    for kind, test in (("prefix", "p_name LIKE 'red%'"), ("suffix", "p_name LIKE '%ring'"), ("contains", "p_name LIKE '%blue%'"), ("regexp", "p_name LIKE 'red %' OR p_name LIKE 'blue %'")):
        out[f"match_{kind}"] = BRANDS.format(test)
    value, hour, user = "value BETWEEN 30 AND 200", "hour(ts) BETWEEN 6 AND 18", "floor(user_id::DOUBLE) BETWEEN 20 AND 90"
    out["resolve_last"], out["resolve_intersect"], out["resolve_union"] = kinds(user), kinds(f"{value} AND {hour} AND {user}"), kinds(f"{value} OR {hour} OR user_id BETWEEN 20 AND 90")
    out["cross_last"] = out["cross_intersect"] = hours("floor(value) BETWEEN 30 AND 200")
    out["cross_union"] = hours(value)
    out["empty_all"] = out["mv_cleared"] = kinds("true")
    out["mv_residual"] = kinds("event_type IN ('click', 'error', 'view') AND floor(value) BETWEEN 10 AND 60")

    args = {"count": "*", "product": "1 + l_tax / 1000", "bit_and": "l_partkey", "bit_or": "l_partkey", "bit_xor": "l_partkey", "bool_and": "l_tax > 0", "bool_or": "l_tax > 0"}
    names = "count sum max min product bit_and bit_or bit_xor bool_and bool_or avg var_samp var_pop stddev_samp stddev_pop"
    own = {n: f"{n}({args.get(n, 'l_quantity')})" for n in names.split()}
    own["geomean"] = "exp(avg(ln(l_quantity)))"
    own |= {f"arg_{m}": f"first(l_partkey ORDER BY l_extendedprice {d}, l_partkey {d})" for m, d in (("max", "DESC"), ("min", "ASC"))}
    own |= {n: f"{n}(l_extendedprice, l_quantity)" for n in "covar_samp covar_pop corr regr_count regr_avgx regr_avgy regr_sxx regr_syy regr_sxy regr_slope regr_intercept regr_r2".split()}
    for n, call in own.items():
        call = f"CAST({call} AS BIGINT)" if n in ("count", "regr_count") else call
        out[f"agg_{n}"] = f"SELECT l_returnflag AS flag, {call} AS v FROM lineitem WHERE {PRICED} GROUP BY 1"
    out["agg_filter"] = f"SELECT l_returnflag AS flag, count(CASE WHEN l_tax > 0.04::DOUBLE THEN 1 END) AS n, avg(CASE WHEN l_linestatus = 'O' THEN l_quantity END) AS s FROM lineitem WHERE {PRICED} GROUP BY 1"
    out["agg_having"] = f"SELECT l_quantity AS size, count(*) AS n FROM lineitem WHERE {PRICED} GROUP BY 1 HAVING count(*) > 100 ORDER BY n DESC, size LIMIT 20"

    def ci(key: str, x: str, source: str, where: str) -> str:
        half = "1.96 * sd / sqrt(n)"
        return f"SELECT *, mean - {half} AS lo, mean + {half} AS hi FROM (SELECT {key} AS key, avg({x}) AS mean, stddev_samp({x}) AS sd, count({x}) AS n FROM {source} WHERE {where} GROUP BY 1)"

    out["agg_expr_ci"] = ci("l_returnflag", "l_quantity", "lineitem", PRICED)
    out["reject_union"], out["reject_unstable"], out["reject_no_scale"] = (hours("value BETWEEN 30 AND 90"),) * 3
    out["reject_match"] = BRANDS.format("p_name LIKE 'red%'")
    out["reject_distinct"] = "SELECT l_returnflag AS flag, count(DISTINCT l_suppkey) AS n FROM lineitem WHERE l_extendedprice BETWEEN 22000 AND 66000 GROUP BY 1"
    out["reject_median"] = "SELECT l_returnflag AS flag, quantile_cont(l_quantity, 0.5) AS m FROM lineitem WHERE l_extendedprice BETWEEN 22000 AND 66000 GROUP BY 1"

    out["w1_hour"] = hours("floor(value) BETWEEN 30 AND 90")
    out["w1_value"] = steps("value", 10, "hour(ts) BETWEEN 6 AND 12", "events")
    out["w1_user"] = steps("user_id", 10, "floor(value) BETWEEN 30 AND 90", "events")
    out["w1l_price"] = steps("l_extendedprice", 5500, FEW, "lineitem")
    out["w1l_quantity"] = steps("l_quantity", 5, PRICED, "lineitem")
    out["w1l_discount"] = f"SELECT l_discount AS x, count(*) AS y FROM lineitem WHERE {PRICED} GROUP BY 1"
    out["w2_dropoff"] = raster(SHIP, SHIP_X, "l_extendedprice", PRICE_Y, PICK, WIDE)
    out["w2_pickup"] = raster(DAY, DAY_X, "o_totalprice", TOTAL_Y, f"{PICK_RAW} AND {DROP}", WIDE)
    out["w2_hist"] = steps("l_quantity", 5, f"{PICK_RAW} AND {DROP}", WIDE)
    out["w3_sky"] = raster("embedding[1]", DIM_X, "embedding[2]", DIM_Y, H4, "embeddings")
    out["w3_colour"] = raster("embedding[3]", DIM_X, "embedding[4]", DIM_Y, SKY, "embeddings")
    out["w3_hist"] = steps("embedding[5]", 0.02, SKY, "embeddings")
    out["w3c_sky"] = raster(DAY, DAY_X, "o_totalprice", TOTAL_Y, RICH, WIDE)
    out["w3c_colour"] = raster(SHIP, SHIP_X, "l_extendedprice", PRICE_Y, STARS, WIDE)
    out["w3c_balance"] = steps("c_acctbal", 500, STARS, WIDE)
    out["w3c_discount"] = f"SELECT l_discount AS x, count(*) AS y FROM {WIDE} WHERE {STARS} GROUP BY 1"
    out["w4_ci"] = ci("event_type", "value", "events", f"ceil({MINUTE} / 10.0) <= 72")
    fit = drag(DAY, (9131 + 200 * 2469 / 600 + 1, 9131 + 319 * 2469 / 600 + 1), (9131, 11600, 600))
    out["w5_fit"] = f"SELECT regr_count(y, x)::BIGINT AS n, regr_slope(y, x) AS slope, regr_r2(y, x) AS r2, regr_avgx(y, x) AS avgx, regr_avgy(y, x) AS avgy FROM (SELECT o_totalprice AS y, {DAY}::DOUBLE AS x FROM orders WHERE {fit})"
    out["w6_menu"] = f"SELECT DISTINCT p_brand AS value FROM part WHERE {PROMO} ORDER BY 1"
    for axis, x, scale in (("x", "p_size", (0, 50, 300)), ("y", "p_retailprice", (900, 1000, 200))):
        where = f"{PROMO} AND {REGION}" if axis == "x" else REGION
        out[f"w6_marginal_{axis}"] = f"SELECT {pixel(x, *scale)}::BIGINT AS x, count(*) AS n FROM part WHERE {where} GROUP BY 1"
    out["w6_brands"] = BRANDS.format(PROMO) + " ORDER BY n DESC, p_brand LIMIT 10"
    out["w6_legend"], out["w6_hover"] = BRANDS.format("p_type IN ('PROMO', 'ECONOMY')"), "SELECT p_type, count(*) AS n FROM part WHERE p_brand = 'Brand#8' AND p_size = 10 GROUP BY 1"
    out["w6_scatter"] = f"SELECT p_size AS x, p_retailprice AS y, p_partkey AS key FROM part WHERE {PROMO} AND {REGION_RAW}"
    out["w6_table"] = f"SELECT p_partkey, p_brand, p_retailprice FROM part WHERE {PROMO} ORDER BY p_retailprice DESC, p_partkey LIMIT 15 OFFSET 20"
    out["w7_search"] = "SELECT lang, count(*) AS n, sum(n_chars) AS chars FROM documents WHERE text LIKE '%Licensed%' GROUP BY 1"
    out["w7_urls"] = "SELECT count(*) AS n FROM pages WHERE url LIKE 'https%'"
    out["view_summary"] = f"SELECT count(*) AS n, avg(l_quantity) AS m, min(l_extendedprice) AS least FROM lineitem WHERE {FEW}"
    return out
