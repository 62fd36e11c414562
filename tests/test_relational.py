"""Relational operators: joins of skewed keys."""

from brushcube.operators.relational import salted_join
from brushcube.sources.store import load

from .conftest import SF, rows_of


def test_salted_join_is_exchanged(spark):
    """However small the repeated side is estimated, it isn't broadcast; rows are the plain join's."""
    li = load(spark, SF, "lineitem").selectExpr("l_orderkey AS k", "l_linenumber")
    o = load(spark, SF, "orders").selectExpr("o_orderkey AS k", "o_orderstatus")
    got = salted_join(li, o, "k")
    assert "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()
    assert rows_of(got) == rows_of(li.join(o, "k"))
