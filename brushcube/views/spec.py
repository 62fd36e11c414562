"""Declarative view queries: one source, row-wise steps, group keys, aggregates, and steps after the aggregation."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.pred import TRUE, Pred, to_duck

#: The thirty supported aggregate functions, by canonical name, with their numbers of arguments.
FUNCTIONS = {
    **dict.fromkeys("count sum max min product bit_and bit_or bit_xor bool_and bool_or avg geomean var_samp var_pop stddev_samp stddev_pop".split(), 1),
    **dict.fromkeys("arg_max arg_min covar_samp covar_pop corr regr_count regr_avgx regr_avgy regr_sxx regr_syy regr_sxy regr_slope regr_intercept regr_r2".split(), 2),
}


@dataclass(frozen=True)
class Agg:
    """fn(args) under an alias; ``where``: a static FILTER; bivariate functions take (y, x), arg_* take (value, ordering).
    ``first``: a number, by which arg_* take the least of rows that are equal in the ordering (without it, any of them; the oracle's SQL leaves them open)."""

    alias: str
    fn: str
    args: tuple[str, ...] = ("*",)
    where: str | None = None
    distinct: bool = False
    first: str | None = None

    def ordering(self) -> str:
        """SQL of the ordering of arg_*, null where the ordering is, ``first`` included."""
        by = self.args[1]
        if not self.first:
            return by
        first = f"({self.first})" if self.fn == "arg_min" else f"-({self.first})"
        return f"CASE WHEN ({by}) IS NOT NULL THEN struct({by} AS o, {first} AS f) END"

    def duck(self) -> str:
        args = ", ".join(self.args).replace("struct(", "row(")
        call = f"{self.fn}({'DISTINCT ' if self.distinct else ''}{args})" + (f" FILTER (WHERE {self.where})" if self.where else "")
        if self.fn in ("count", "regr_count"):
            return f"CAST({call} AS BIGINT)"
        return call


@dataclass(frozen=True)
class ViewSpec:
    """``derive``: row-wise computed columns, in order; ``explode``: (alias, SQL array) steps after them. ``group``: alias -> SQL.
    ``post``: alias -> SQL over the aggregates' aliases; ``columns`` picks the result's columns if not all. ``filter_stable``: the group domain doesn't hang on the filter.
    ``inner``: (keys, aggregates) of an inner aggregation, for views like line density."""

    id: str
    source: str
    group: tuple[tuple[str, str], ...] = ()
    aggs: tuple[Agg, ...] = ()
    filter_stable: bool = False
    derive: tuple[tuple[str, str], ...] = ()
    explode: tuple[tuple[str, str], ...] = ()
    post: tuple[tuple[str, str], ...] = ()
    columns: tuple[str, ...] = ()
    having: str | None = None
    order: tuple[str, ...] = ()
    limit: int | None = None
    offset: int = 0
    inner_keys: tuple[str, ...] = ()
    opaque: str | None = field(default=None)  # why the rows can't be told apart before the aggregation (windows, limits, ...)
    sources: tuple[str, ...] = ()  # base relations, if there are more than ``source``
    raw: bool = False  # rows, not aggregates

    def steps(self, base: DataFrame) -> DataFrame:
        for alias, sql in self.derive:
            base = base.withColumn(alias, F.expr(sql))
        for alias, sql in self.explode:
            base = base.withColumn(alias, F.explode(F.expr(sql)))
        return base

    def after(self, df: DataFrame) -> DataFrame:
        """HAVING, computed columns, order and limit: re-applied to every answer."""
        if self.having:
            df = df.where(self.having)
        for alias, sql in self.post:
            df = df.withColumn(alias, F.expr(sql))
        if self.columns:
            df = df.select(*self.columns)
        if self.order:
            df = df.orderBy(*[F.expr(o.removesuffix(" DESC")).desc() if o.endswith(" DESC") else F.expr(o) for o in self.order])
        if self.offset:
            df = df.offset(self.offset)
        return df if self.limit is None else df.limit(self.limit)

    def duck(self, pred: Pred = TRUE, source: str | None = None) -> str:
        """The filtered query over the raw table as SQL for the oracle: independent of any pre-aggregate."""
        inner = "*" + "".join(f", {sql} AS {a}" for a, sql in self.derive)
        base = f"SELECT {inner} FROM {source or self.source}" + (f" WHERE {pred.sql()}" if not self.derive else "")
        if self.derive:
            base = f"SELECT * FROM ({base}) WHERE {pred.sql()}"
        cols = [f"{sql} AS {a}" for a, sql in self.group] + [f"{a.duck()} AS {a.alias}" for a in self.aggs]
        q = f"SELECT {', '.join(cols)} FROM ({base})" + (f" GROUP BY {', '.join(str(i + 1) for i in range(len(self.group)))}" if self.group else "")
        q = f"SELECT * FROM ({q})" + (f" WHERE {self.having}" if self.having else "")
        for a, sql in self.post:
            q = f"SELECT *, {sql} AS {a} FROM ({q})"
        if self.columns:
            q = f"SELECT {', '.join(self.columns)} FROM ({q})"
        if self.order:
            q += f" ORDER BY {', '.join(self.order)}"
        if self.limit is not None:
            q += f" LIMIT {self.limit}" + (f" OFFSET {self.offset}" if self.offset else "")
        return to_duck(q)
