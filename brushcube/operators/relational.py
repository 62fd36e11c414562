"""The relational operators around the methods: scans, predicates, joins, aggregates, windows, sorts, sets, scalar functions."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.store import load, shared_root


# -- operators Spark lacks ------------------------------------------------------------------------------------------------
def band_join(df: DataFrame, value: str, bands: DataFrame, lo: str, hi: str, width: float) -> DataFrame:
    """lo <= value < hi as an equi-join: bands are cut into cells of ``width``, so neither side is compared with all of the other."""
    cells = bands.withColumn("band_cell", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    keyed = df.withColumn("band_cell", F.floor(F.col(value) / width))
    return keyed.join(cells, "band_cell").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("band_cell")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, take: dict[str, str], tie: str) -> DataFrame:
    """Each left row with the last earlier-or-equal right row of its key: one union and one window, no range join. ``take``: right column -> output name."""
    row = F.struct(*[F.col(c).alias(n) for c, n in take.items()])
    l = left.withColumn("side", F.lit(1)).withColumn("carried", F.lit(None).cast(right.select(row.alias("r")).schema["r"].dataType))  # noqa: E741
    r = right.select(key, at, tie, F.lit(0).alias("side"), row.alias("carried"))
    both = l.unionByName(r, allowMissingColumns=True)
    w = W.partitionBy(key).orderBy(at, "side", tie).rowsBetween(W.unboundedPreceding, 0)
    out = both.withColumn("found", F.last("carried", ignorenulls=True).over(w)).where("side = 1")
    return out.select(*left.columns, *[F.col(f"found.{n}").alias(n) for n in take.values()])


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Equi-join for a key that holds much of ``big``: its rows are dealt over ``salts`` parts, the other side is repeated for each.
    Both sides are exchanged: Spark's estimate of the repeated side leaves the repeats out, so it would be broadcast ``salts`` times as large as it seems."""
    spread = big.withColumn("salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    repeated = small.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return spread.join(repeated.hint("merge"), [key, "salt"]).drop("salt")


def keyset_page(df: DataFrame, sort: str, key: str, after: tuple | None, limit: int) -> DataFrame:
    """The page after a (sort value, key): deep pages cost what the first does, unlike an offset."""
    if after is not None:
        df = df.where((F.col(sort) > after[0]) | ((F.col(sort) == after[0]) & (F.col(key) > after[1])))
    return df.orderBy(sort, key).limit(limit)


# -- registered queries ---------------------------------------------------------------------------------------------------
def _r(c: Column, d: int = 6) -> Column:
    return F.round(c, d)


def _scan(kind: str) -> Callable:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = load(spark, sf_dir, "region")
        if kind == "parquet":
            return src
        root = shared_root(spark)
        path = f"{root.rstrip('/')}/scan-{kind}-{uuid.uuid4().hex}"
        src.write.format(kind).save(path)
        return spark.read.schema(src.schema).format(kind).load(path)

    return run


def _tables(f: Callable[..., DataFrame], *names: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: f(*[load(spark, sf_dir, n) for n in names])


# Functions, since columns and windows need a session and the oracle's SQL must be readable without one.
def _rank():
    return W.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")


def _user():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


def _ranges(ev: DataFrame) -> DataFrame:
    bands = ev.sparkSession.sql("SELECT * FROM VALUES ('low', 0D, 12.5D), ('mid', 12.5D, 80D), ('high', 80D, 1000D) AS b(band, lo, hi)")
    return band_join(ev.select("event_id", "value"), "value", bands, "lo", "hi", 25.0).groupBy("band").agg(F.count("*").alias("n"))


def _as_of(ev: DataFrame) -> DataFrame:
    clicks = ev.where("event_type = 'click'").select("user_id", "ts", "event_id", F.col("event_id").alias("click_event"))
    buys = ev.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    return as_of(buys, clicks, "user_id", "ts", {"click_event": "last_click"}, "event_id").select("event_id", "last_click")


QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    **{f"op_scan_{k}": (_scan(k), "SELECT * FROM region") for k in ("parquet", "csv", "json", "orc")},
    "op_project": (_tables(lambda li: li.select("l_orderkey", "l_linenumber", _r(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net")), "lineitem"), "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 6) AS net FROM lineitem"),
    "op_filter_and_or": (_tables(lambda li: li.where("(l_quantity < 3 AND l_tax = 0) OR l_discount = 0.1D").select("l_orderkey", "l_quantity"), "lineitem"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE (l_quantity < 3 AND l_tax = 0) OR l_discount = CAST(0.1 AS DOUBLE)"),
    "op_filter_in": (_tables(lambda p: p.where(F.col("p_brand").isin("Brand#1", "Brand#2")).select("p_partkey"), "part"), "SELECT p_partkey FROM part WHERE p_brand IN ('Brand#1', 'Brand#2')"),
    "op_filter_between": (_tables(lambda o: o.where(F.col("o_totalprice").between(1000, 50000)).select("o_orderkey"), "orders"), "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000"),
    "op_filter_null": (_tables(lambda e: e.select("event_id", F.expr("nullif(event_type, 'error')").alias("t")).where("t IS NULL OR t <=> 'click'"), "events"), "SELECT * FROM (SELECT event_id, nullif(event_type, 'error') AS t FROM events) WHERE t IS NULL OR t = 'click'"),
    "op_join_inner": (_tables(lambda o, c: o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "orders", "customer"), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"),
    **{f"op_join_{k}": (_tables(lambda d, b, k=k: d.select("doc_id").join(b.select(F.col("doc_id").alias("lab_id"), "toxic"), F.col("doc_id") == F.col("lab_id"), k), "documents", "labels"), f"SELECT d.doc_id, b.doc_id AS lab_id, toxic FROM documents d {k.upper()} JOIN labels b ON d.doc_id = b.doc_id") for k in ("left", "right", "full")},
    "op_join_broadcast": (_tables(lambda c, n, r: c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).groupBy("r_name").agg(F.count("*").alias("n")), "customer", "nation", "region"), "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"),
    "op_join_semi": (_tables(lambda d, b: d.join(b, "doc_id", "left_semi").select("doc_id"), "documents", "labels"), "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)"),
    "op_join_anti": (_tables(lambda d, b: d.join(b, "doc_id", "left_anti").select("doc_id"), "documents", "labels"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)"),
    "op_join_range": (_tables(_ranges, "events"), "SELECT band, count(*) AS n FROM events JOIN (VALUES ('low', 0, 12.5), ('mid', 12.5, 80), ('high', 80, 1000)) b(band, lo, hi) ON value >= lo AND value < hi GROUP BY 1"),
    "op_join_asof": (_tables(_as_of, "events"), "SELECT b.event_id, (SELECT arg_max(c.event_id, row(c.ts, c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = b.user_id AND c.ts <= b.ts) AS last_click FROM events b WHERE event_type = 'purchase'"),
    "op_join_salted": (_tables(lambda li, o: salted_join(li.select("l_orderkey", "l_linenumber", "l_quantity").withColumnRenamed("l_orderkey", "k"), o.select(F.col("o_orderkey").alias("k"), "o_orderstatus"), "k").groupBy("o_orderstatus").agg(F.count("*").alias("n")), "lineitem", "orders"), "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
    "op_join_cross": (_tables(lambda n, r: n.crossJoin(F.broadcast(r)).select("n_name", "r_name"), "nation", "region"), "SELECT n_name, r_name FROM nation, region"),
    "op_agg_hash": (_tables(lambda li: li.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), _r(F.sum("l_quantity"), 2).alias("q")), "lineitem"), "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY 1, 2"),
    "op_agg_filter": (_tables(lambda li: li.groupBy("l_returnflag").agg(F.expr("count(*) FILTER (WHERE l_tax > 0.04D)").alias("n")), "lineitem"), "SELECT l_returnflag, count(*) FILTER (WHERE l_tax > CAST(0.04 AS DOUBLE)) AS n FROM lineitem GROUP BY 1"),
    "op_agg_distinct": (_tables(lambda li: li.groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("n")), "lineitem"), "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY 1"),
    "op_rollup": (_tables(lambda li: li.rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "lineitem"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (1, 2)"),
    "op_cube": (_tables(lambda li: li.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "lineitem"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "op_grouping_sets": (_tables(lambda li: li.groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "lineitem"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))"),
    "op_win_rank": (_tables(lambda o: o.select("o_orderkey", F.row_number().over(_rank()).alias("rn"), F.rank().over(_rank()).alias("rk"), F.dense_rank().over(_rank()).alias("dr"), F.ntile(4).over(_rank()).alias("nt"), _r(F.percent_rank().over(_rank())).alias("pr")), "orders"), "SELECT o_orderkey, row_number() OVER r AS rn, rank() OVER r AS rk, dense_rank() OVER r AS dr, ntile(4) OVER r AS nt, round(percent_rank() OVER r, 6) AS pr FROM orders WINDOW r AS (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey)"),
    "op_win_lag_lead": (_tables(lambda e: e.select("event_id", F.lag("value").over(_user()).alias("before"), F.lead("value").over(_user()).alias("after")), "events"), "SELECT event_id, lag(value) OVER u AS before, lead(value) OVER u AS after FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "op_win_first_last": (_tables(lambda e: e.select("event_id", F.first("value").over(_user()).alias("first"), F.last("value").over(_user()).alias("last")), "events"), "SELECT event_id, first_value(value) OVER u AS first, last_value(value) OVER u AS last FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "op_win_rows": (_tables(lambda e: e.select("event_id", _r(F.sum("value").over(_user().rowsBetween(-2, 0))).alias("s")), "events"), "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS s FROM events"),
    "op_win_range": (_tables(lambda o: o.select("o_orderkey", F.count("*").over(W.partitionBy("o_orderpriority").orderBy("o_totalprice").rangeBetween(-1000, 0)).alias("n")), "orders"), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n FROM orders"),
    "op_win_then_filter": (_tables(lambda e: e.withColumn("rn", F.row_number().over(_user())).where("rn % 10 = 0").select("event_id", "rn"), "events"), "SELECT * FROM (SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events) WHERE rn % 10 = 0"),
    "op_sort": (_tables(lambda p: p.select("p_partkey", "p_size").orderBy("p_size", "p_partkey"), "part"), "SELECT p_partkey, p_size FROM part"),
    "op_limit_offset": (_tables(lambda p: p.select("p_partkey", "p_size").orderBy("p_size", "p_partkey").offset(30).limit(10), "part"), "SELECT p_partkey, p_size FROM part ORDER BY p_size, p_partkey LIMIT 10 OFFSET 30"),
    "op_keyset_page": (_tables(lambda p: keyset_page(p.select("p_partkey", "p_size"), "p_size", "p_partkey", (10, 50), 10), "part"), "SELECT p_partkey, p_size FROM part WHERE p_size > 10 OR (p_size = 10 AND p_partkey > 50) ORDER BY p_size, p_partkey LIMIT 10"),
    "op_topk": (_tables(lambda o: o.select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10), "orders"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    "op_topk_per_group": (_tables(lambda o: o.withColumn("rn", F.row_number().over(_rank())).where("rn <= 3").select("o_orderpriority", "o_orderkey", "rn"), "orders"), "SELECT * FROM (SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3"),
    "op_union": (_tables(lambda c, s: c.select(F.col("c_nationkey").alias("k")).unionByName(s.select(F.col("s_nationkey").alias("k"))).groupBy("k").agg(F.count("*").alias("n")), "customer", "supplier"), "SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1"),
    "op_union_distinct": (_tables(lambda c, s: c.select(F.col("c_nationkey").alias("k")).union(s.select("s_nationkey")).distinct(), "customer", "supplier"), "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier"),
    "op_intersect": (_tables(lambda c, s: c.select(F.col("c_nationkey").alias("k")).intersect(s.select("s_nationkey")), "customer", "supplier"), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier"),
    "op_except": (_tables(lambda p, s: p.select(F.col("p_size").cast("long").alias("k")).subtract(s.select(F.col("s_nationkey").cast("long"))), "part", "supplier"), "SELECT p_size::BIGINT AS k FROM part EXCEPT SELECT s_nationkey FROM supplier"),
    "op_except_all": (_tables(lambda c, s: c.select(F.col("c_nationkey").alias("k")).exceptAll(s.select("s_nationkey")), "customer", "supplier"), "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier"),
    "op_having": (_tables(lambda li: li.groupBy("l_quantity").agg(F.count("*").alias("n")).where("n > 1200"), "lineitem"), "SELECT l_quantity, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 1200"),
    "op_scalar_subquery": (_tables(lambda o: o.crossJoin(F.broadcast(o.agg(F.avg("o_totalprice").alias("mean")))).where("o_totalprice > 1.9D * mean").select("o_orderkey"), "orders"), "SELECT o_orderkey FROM orders WHERE o_totalprice > CAST(1.9 AS DOUBLE) * (SELECT avg(o_totalprice) FROM orders)"),
    "op_cte": (_tables(lambda li: li.where("l_tax > 0").groupBy("l_returnflag").agg(F.count("*").alias("n")), "lineitem"), "WITH r AS (SELECT * FROM lineitem WHERE l_tax > 0) SELECT l_returnflag, count(*) AS n FROM r GROUP BY 1"),
    "op_str": (_tables(lambda p: p.select("p_partkey", F.lower("p_type").alias("t"), F.substring("p_name", 1, 3).alias("s"), F.length("p_name").alias("n"), F.regexp_extract("p_brand", r"#(\d+)", 1).alias("b"), F.split("p_name", " ")[0].alias("w")), "part"), "SELECT p_partkey, lower(p_type) AS t, substring(p_name, 1, 3) AS s, length(p_name)::INTEGER AS n, regexp_extract(p_brand, '#([0-9]+)', 1) AS b, string_split(p_name, ' ')[1] AS w FROM part"),
    "op_date": (_tables(lambda o: o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.expr("unix_date(CAST(o_orderdate AS DATE))").alias("d")), "orders"), "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE))::INTEGER AS d FROM orders"),
    "op_math": (_tables(lambda c: c.select("c_custkey", _r(F.sqrt(F.abs("c_acctbal"))).alias("s"), F.signum("c_acctbal").cast("int").alias("g"), F.expr("CAST(floor(c_acctbal) AS BIGINT)").alias("f"), F.expr("try_divide(1D, nullif(c_acctbal, c_acctbal))").alias("z")), "customer"), "SELECT c_custkey, round(sqrt(abs(c_acctbal)), 6) AS s, sign(c_acctbal)::INTEGER AS g, floor(c_acctbal)::BIGINT AS f, NULL::DOUBLE AS z FROM customer"),
    "op_array": (_tables(lambda e: e.select("vec_id", F.size("embedding").alias("n"), _r(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")), 4).alias("s")), "embeddings"), "SELECT vec_id, len(embedding)::INTEGER AS n, round(list_sum([x::DOUBLE FOR x IN embedding]), 4) AS s FROM embeddings"),
    "op_map": (_tables(lambda r: r.select("r_regionkey", F.map_from_arrays(F.array("r_regionkey"), F.array("r_name"))[F.col("r_regionkey")].alias("v")), "region"), "SELECT r_regionkey, r_name AS v FROM region"),
    "op_json": (_tables(lambda e: e.select(F.get_json_object("props", "$.k").cast("int").alias("k")).groupBy("k").agg(F.count("*").alias("n")), "events"), "SELECT (props->>'$.k')::INTEGER AS k, count(*) AS n FROM events GROUP BY 1"),
    "op_explode": (_tables(lambda e: e.select("vec_id", F.posexplode(F.slice("embedding", 1, 3)).alias("i", "v")).select("vec_id", "i", _r(F.col("v").cast("double")).alias("v")), "embeddings"), "SELECT vec_id, (i - 1)::INTEGER AS i, round(embedding[i]::DOUBLE, 6) AS v FROM embeddings, (VALUES (1), (2), (3)) t(i)"),
    "op_percentile": (_tables(lambda li: li.groupBy("l_returnflag").agg(_r(F.percentile("l_extendedprice", 0.9)).alias("p")), "lineitem"), "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.9), 6) AS p FROM lineitem GROUP BY 1"),
    "op_median": (_tables(lambda li: li.groupBy("l_returnflag").agg(_r(F.median("l_extendedprice")).alias("p")), "lineitem"), "SELECT l_returnflag, round(median(l_extendedprice), 6) AS p FROM lineitem GROUP BY 1"),
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, (f, _) in QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in QUERIES.items()}
