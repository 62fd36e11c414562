"""Direct queries that can share a scan: same keys -> one select list; other keys -> grouping sets."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.pred import TRUE, Pred
from ..plans.preagg import direct
from ..views.spec import Agg, ViewSpec


def same_keys(views: list[ViewSpec]) -> ViewSpec:
    """One view whose aggregates are those of all (aliases get the view's id before them)."""
    first = views[0]
    if any((v.source, v.group, v.derive, v.explode) != (first.source, first.group, first.derive, first.explode) or v.having or v.limit for v in views):
        raise ValueError("views don't share source, steps and keys")
    return replace(first, id="+".join(v.id for v in views), aggs=tuple(replace(a, alias=f"{v.id}__{a.alias}") for v in views for a in v.aggs), post=(), columns=(), order=())


def consolidated(views: list[ViewSpec], base: DataFrame, pred: Pred = TRUE) -> dict[str, DataFrame]:
    """Results of all views from one scan over their common keys."""
    one = direct(same_keys(views), base, pred).cache()
    keys = [a for a, _ in views[0].group]
    return {v.id: v.after(one.select(*keys, *[F.col(f"{v.id}__{a.alias}").alias(a.alias) for a in v.aggs])) for v in views}


def grouping_sets(views: list[ViewSpec], base: DataFrame, pred: Pred = TRUE, most: int = 8) -> DataFrame:
    """Views of one source with different keys and the same aggregates, in one scan: rows carry ``view`` (its place). Expand multiplies rows by the number of views, so at most ``most`` go together."""
    aggs: tuple[Agg, ...] = views[0].aggs
    if len(views) > most or any(v.aggs != aggs or v.source != views[0].source for v in views):
        raise ValueError("views can't share grouping sets")
    rows = base.where(pred.column())
    cols = [F.expr(sql).alias(f"k{i}_{a}") for i, v in enumerate(views) for a, sql in v.group]
    names = [f"k{i}_{a}" for i, v in enumerate(views) for a, _ in v.group]
    rows = rows.select("*", *cols)
    sets = [[F.col(f"k{i}_{a}") for a, _ in v.group] for i, v in enumerate(views)]
    from ..plans.preagg import _direct_agg

    out = rows.groupingSets(sets, *names).agg(*[_direct_agg(a) for a in aggs], F.grouping_id().alias("gid"))
    n = len(names)
    ids = {sum(1 << (n - 1 - k) for k, name in enumerate(names) if not name.startswith(f"k{i}_")): i for i in range(len(views))}
    return out.withColumn("view", F.element_at(F.create_map(*[F.lit(x) for kv in ids.items() for x in kv]), F.col("gid").cast("int"))).drop("gid")
