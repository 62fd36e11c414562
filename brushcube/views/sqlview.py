"""Views given as SQL text: the analysed plan is walked; what isn't understood runs directly, with the reason."""

from __future__ import annotations

import re
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession

from .spec import Agg, ViewSpec

#: Canonical names of Spark's aggregates.
_NAMES = {"max_by": "arg_max", "min_by": "arg_min", "every": "bool_and", "some": "bool_or", "any": "bool_or", "mean": "avg", "std": "stddev_samp", "stddev": "stddev_samp", "variance": "var_samp"}
_ROWWISE = {"Project", "Filter", "SubqueryAlias", "View", "Relation", "LogicalRelation", "LocalRelation", "Range", "CTERelationRef", "WithCTE", "CTERelationDef", "Generate", "LogicalRDD", "Join"}


def _seq(s) -> list:
    return [s.apply(i) for i in range(s.length())]


def _name(node) -> str:
    return node.getClass().getSimpleName()


def _text(e) -> str:
    """SQL of an expression over the inner query's output, without qualifiers."""
    return re.sub(r"(?:`?[\w$]+`?\.)+(`?[\w$]+`?)(?!\()", r"\1", e.sql())


def _leaves(node, defs: dict, found: set, hidden: list, below: bool = False) -> None:
    name = _name(node)
    if name == "WithCTE":
        for d in _seq(node.cteDefs()):
            defs[str(d.id())] = d.child()
        _leaves(node.plan(), defs, found, hidden, below)
        return
    if name == "CTERelationRef":
        _leaves(defs[str(node.cteId())], defs, found, hidden, below)
        return
    kids = _seq(node.children())
    if not kids:
        found.add(re.sub(r"#\d+L?", "", node.toString()).strip())
    if below and name not in _ROWWISE:
        hidden.append(name)
    for k in kids:
        _leaves(k, defs, found, hidden, below or name == "Aggregate")


def sql_view(spark: SparkSession, id: str, sql: str, filter_stable: bool, args: dict | None = None) -> tuple[ViewSpec | None, DataFrame | None, DataFrame, list[str]]:
    """(spec, rows under its aggregation, plain query, reasons). Without a spec only the plain query can run. Needs a classic session."""
    plain = spark.sql(sql, args=args) if args else spark.sql(sql)
    try:
        node = plain._jdf.queryExecution().analyzed()
    except Exception:
        return None, None, plain, ["session: plans can't be read"]
    if _name(node) == "WithCTE":  # each reference becomes its definition
        node = spark._jvm.org.apache.spark.sql.catalyst.optimizer.InlineCTE(True, False).apply(node)
    found, hidden, defs = set(), [], {}
    _leaves(node, defs, found, hidden)
    reasons = [] if len(found) == 1 else [f"source: {len(found)} base relations"]
    if hidden:
        reasons.append(f"inner query: {', '.join(sorted(set(hidden)))}")
    if _name(node) == "WithCTE":
        node = node.plan()
    post: dict = {}
    while _name(node) in ("GlobalLimit", "LocalLimit", "Sort", "Project", "SubqueryAlias"):
        if _name(node) in ("GlobalLimit", "LocalLimit"):
            post["limit"] = int(str(node.limitExpr()))
        elif _name(node) == "Sort":
            post["order"] = tuple(_text(o.child()) + (" DESC" if "Descending" in _name(o.direction()) else "") for o in _seq(node.order()))
        elif _name(node) == "Project" and not all(_name(e) == "AttributeReference" for e in _seq(node.projectList())):
            return None, None, plain, [*reasons, "query: computes above its aggregation"]
        node = _seq(node.children())[0]
    if _name(node) == "Filter":
        post["having"], node = _text(node.condition()), _seq(node.children())[0]
    if _name(node) != "Aggregate":
        return None, None, plain, [*reasons, "query: no aggregation on top"]
    group, aggs = [], []
    keys = {_text(g): g for g in _seq(node.groupingExpressions())}
    for e in _seq(node.aggregateExpressions()):
        alias, child = (e.name(), e.child()) if _name(e) == "Alias" else (e.name(), e)
        if _name(child) == "AggregateExpression":
            f = child.aggregateFunction()
            fn = _NAMES.get(f.prettyName(), f.prettyName())
            inputs = [_text(c) for c in _seq(f.children())]
            where = _text(child.filter().get()) if child.filter().isDefined() else None
            aggs.append(Agg(alias, fn, ("*",) if fn == "count" and inputs == ["1"] else tuple(inputs), where, child.isDistinct()))
        elif _text(child) in keys:
            group.append((alias, _text(child)))
        else:
            return None, None, plain, [*reasons, f"query: {_text(child)} is neither key nor aggregate"]
    if len(group) != len(keys):
        return None, None, plain, [*reasons, "query: keys that it doesn't return"]
    base = DataFrame(spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, node.child()), spark)
    spec = replace(ViewSpec(id, f"sql:{id}", tuple(group), tuple(aggs), filter_stable), **post, sources=(f"sql:{id}",) if len(found) == 1 else tuple(sorted(found)), opaque=", ".join(sorted(set(hidden))) or None)
    return spec, base, plain, reasons
