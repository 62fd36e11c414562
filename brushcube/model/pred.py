"""Predicates as data: built by clauses and resolvers, rendered to SQL text (and from it to a Column)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


def literal(v) -> str:
    if v is None:
        return "NULL"
    if isinstance(v, bool):
        return str(v).upper()
    if isinstance(v, int):
        return str(v)
    if isinstance(v, float):
        return f"CAST({v!r} AS DOUBLE)"
    return "'" + str(v).replace("\\", "\\\\").replace("'", "\\'") + "'" if "\\" in str(v) else "'" + str(v).replace("'", "''") + "'"


class Pred:
    def sql(self) -> str:
        raise NotImplementedError

    def column(self) -> Column:
        return F.expr(self.sql())

    def __and__(self, other: Pred) -> Pred:
        return both(self, other)


@dataclass(frozen=True)
class Constant(Pred):
    value: bool

    def sql(self) -> str:
        return "TRUE" if self.value else "FALSE"


TRUE, FALSE = Constant(True), Constant(False)


@dataclass(frozen=True)
class All(Pred):
    parts: tuple[Pred, ...]

    def sql(self) -> str:
        return " AND ".join(f"({p.sql()})" for p in self.parts)


@dataclass(frozen=True)
class Any_(Pred):
    parts: tuple[Pred, ...]

    def sql(self) -> str:
        return " OR ".join(f"({p.sql()})" for p in self.parts)


@dataclass(frozen=True)
class Raw(Pred):
    """SQL text that both engines understand."""

    text: str

    def sql(self) -> str:
        return self.text


@dataclass(frozen=True)
class PointIn(Pred):
    """Equality with one of the tuples; a null value equals null."""

    columns: tuple[str, ...]
    rows: tuple[tuple, ...]

    def sql(self) -> str:
        if not self.rows:
            return "FALSE"
        if len(self.columns) == 1 and all(r[0] is not None for r in self.rows):
            return f"{self.columns[0]} IN ({', '.join(literal(r[0]) for r in self.rows)})"
        one = lambda c, v: f"{c} IS NULL" if v is None else f"({c} IS NOT NULL AND {c} = {literal(v)})"
        return " OR ".join("(" + " AND ".join(one(c, v) for c, v in zip(self.columns, r, strict=True)) + ")" for r in self.rows)


@dataclass(frozen=True)
class Range(Pred):
    """lo <= column <= hi; a missing end is open."""

    column_sql: str
    lo: float | None
    hi: float | None

    def sql(self) -> str:
        if self.lo is not None and self.hi is not None:
            return f"{self.column_sql} BETWEEN {literal(self.lo)} AND {literal(self.hi)}"
        if self.hi is not None:
            return f"{self.column_sql} <= {literal(self.hi)}"
        return f"{self.column_sql} >= {literal(self.lo)}" if self.lo is not None else "TRUE"


@dataclass(frozen=True)
class Match(Pred):
    column_sql: str
    text: str
    kind: str = "contains"

    def sql(self) -> str:
        if self.kind == "regexp":
            return f"regexp_like({self.column_sql}, {literal(self.text)})"
        fn = {"prefix": "startswith", "suffix": "endswith", "contains": "contains"}[self.kind]
        return f"{fn}({self.column_sql}, {literal(self.text)})"


def both(*parts: Pred) -> Pred:
    flat = [q for p in parts for q in (p.parts if isinstance(p, All) else (p,)) if q != TRUE]
    if FALSE in flat:
        return FALSE
    return TRUE if not flat else flat[0] if len(flat) == 1 else All(tuple(flat))


def either(*parts: Pred) -> Pred:
    flat = [q for p in parts for q in (p.parts if isinstance(p, Any_) else (p,)) if q != FALSE]
    if TRUE in flat:
        return TRUE
    return FALSE if not flat else flat[0] if len(flat) == 1 else Any_(tuple(flat))


def to_duck(sql: str) -> str:
    """The same SQL text for the oracle engine: only function names differ."""
    import re

    sql = re.sub(r"unix_date\((CAST\([\w.]+ AS DATE\))\)", r"date_diff('day', DATE '1970-01-01', \1)", sql)
    sql = re.sub(r"unix_seconds\(CAST\(([\w.]+) AS TIMESTAMP\)\)", r"CAST(epoch(\1) AS BIGINT)", sql)
    sql = re.sub(r"embedding\[(\d+)\]", lambda m: f"embedding[{int(m[1]) + 1}]", sql)
    for a, b in (("startswith(", "starts_with("), ("endswith(", "ends_with("), ("regexp_like(", "regexp_matches(")):
        sql = sql.replace(a, b)
    return sql
