"""Registered studies beyond the smallest tables."""

from pyspark.sql import functions as F

from brushcube.bench import registry as R
from brushcube.bench import workloads as w
from brushcube.bench.studies import top_counts
from brushcube.coord.coordinator import Coordinator
from brushcube.model.clause import interval
from brushcube.model.scales import Scale
from brushcube.model.selection import Selection
from brushcube.plans.preagg import direct
from brushcube.sources.store import load
from brushcube.views.templates import pixel_column

from .conftest import SF, rows_of


def test_topk_with_more_values_than_are_tracked(spark, oracle, tmp_path):
    """20,000 suppliers of one row each, three of two: the sketches name none of those with one, the counts are right."""
    li = load(spark, SF, "lineitem")
    row = li.where("l_quantity BETWEEN 11 AND 19 AND l_returnflag = 'A'").limit(1)
    many = row.crossJoin(spark.range(20_003)).withColumn("l_suppkey", F.expr("id % 20000")).select(*li.columns)
    many.unionByName(li.where("l_returnflag <> 'A'")).write.parquet(f"{tmp_path}/lineitem.parquet")
    df = R.queries()["sketch_topk"](spark, str(tmp_path))
    cols, want = oracle(R.oracle_sql()["sketch_topk"], str(tmp_path).rstrip("/"))
    assert rows_of(df, cols) == sorted(want, key=str)


def test_topk_bar_drops_no_value(spark):
    """Candidates that aren't the most frequent, and none at all; null values count."""
    counts = spark.createDataFrame([("a", i, 10 - i) for i in range(9)] + [("a", None, 7), (None, 1, 3), (None, 2, 4)], "flag string, item long, n long")
    sketched = spark.createDataFrame([("a", [(7, 9), (8, 9)]), (None, [])], "flag string, v array<struct<item: long, count: long>>")
    want = [("a", 0, 10), ("a", 1, 9), (None, 0, 4), (None, 1, 3)]
    assert sorted(rows_of(top_counts(sketched, counts, 2)), key=str) == sorted(want, key=str)


def test_pixel_column_takes_the_first_of_equal_values(spark, tmp_path):
    """Points of equal value in one cell, in several, and in several partitions: the first in time, from cells and directly. A null value is no point."""
    hour = lambda i: "07" if i % 3 else "09"
    rows = [(i, f"2020-01-01 {hour(i)}:00:00", None if i % 50 == 0 else 1.0 + (i // 5 % 2)) for i in range(400)]
    ev = spark.createDataFrame(rows, "event_id long, ts string, value double").withColumn("ts", F.to_timestamp_ntz("ts")).repartition(5)
    view = pixel_column("px", "ev", "event_id", "value", Scale("linear", (0, 10000), (0, 100)))
    clause = interval("time", w.HOUR, (6, 12), w.HOURS)
    sel = Selection()
    sel.update(clause)
    c = Coordinator(spark, store=str(tmp_path))
    c.relation("ev", ev)
    got, path, _ = c.frame(view, sel, clause)
    want = [(k, 100 * k + 1, 100 * k + 5) for k in range(4)]
    assert path == "cells"
    for df in (got, direct(view, ev, clause.bin_predicate())):
        assert rows_of(df.selectExpr("px", "t_at_vmin", "t_at_vmax")) == want
    c.close()


def test_empty_none_reads_its_table(spark):
    """Nothing is kept before the first brush and after it; what is kept under it is read from the table by Spark's tasks."""
    df = R.queries()["empty_none"](spark, SF)
    assert {r.state for r in df.collect()} == {"brushed"}
    assert "Scan" in df._jdf.queryExecution().executedPlan().toString()
