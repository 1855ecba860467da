"""One query, two targets: Spark columns and frames, and SQL text that Spark and DuckDB both run."""

from __future__ import annotations

import datetime as dt
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cardest.query.ir import And, Clause, JoinEdge, Not, Opaque, Query

COMPARE = {
    "<": lambda a, b: a < b,
    "<=": lambda a, b: a <= b,
    ">": lambda a, b: a > b,
    ">=": lambda a, b: a >= b,
    "=": lambda a, b: a == b,
    "!=": lambda a, b: a != b,
}


def to_expr(p, name=lambda c: f"`{c}`") -> str:
    """A predicate as Spark SQL text: one call to the JVM however large the predicate."""
    if p is None:
        return "true"
    if isinstance(p, Clause):
        return f"{name(p.col)} {p.op} {spark_value(p.value)}"
    if isinstance(p, Not):
        return f"not ({to_expr(p.part, name)})"
    if isinstance(p, Opaque):
        return f"({p.sql})"
    return "(" + (" and " if isinstance(p, And) else " or ").join(to_expr(x, name) for x in p.parts) + ")"


def spark_value(v) -> str:
    if isinstance(v, str):
        return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(v, dt.datetime):
        return f"timestamp_ntz '{v.isoformat(sep=' ')}'"
    return f"{v!r}D" if isinstance(v, float) else repr(v)


def to_column(p, name=lambda c: f"`{c}`") -> Column:
    """A predicate as a column; ``name`` maps a column to where it is found."""
    return F.expr(to_expr(p, name))


def edge_expr(e: JoinEdge) -> str:
    return f"`{e.a1}__{e.c1}` {e.op} `{e.a2}__{e.c2}`"


def edge_column(e: JoinEdge, name=lambda a, c: f"{a}__{c}") -> Column:
    return COMPARE[e.op](F.col(name(e.a1, e.c1)), F.col(name(e.a2, e.c2)))


def prefixed(df: DataFrame, alias: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """Columns named ``alias__column``; those in ``keep`` as they are."""
    return df.select(*[F.col(f"`{c}`").alias(c if c in keep else f"{alias}__{c}") for c in df.columns])


def to_dataframe(q: Query, db: dict[str, DataFrame], order: list[str] | None = None, hints: dict[str, str] | None = None) -> DataFrame:
    """The query as written: selections on the scans, then joins in the order of ``order`` (aliases)."""
    order = list(order or q.aliases)
    hints = hints or {}

    def leaf(a: str) -> DataFrame:
        df = db[q.tables[a]]
        df = df.where(to_column(q.selections[a])) if a in q.selections else df
        df = prefixed(df, a)
        return df.hint(hints[a]) if a in hints else df

    done, out = {order[0]}, leaf(order[0])
    for a in order[1:]:
        edges = [e for e in q.joins if a in (e.a1, e.a2) and ({e.a1, e.a2} - {a}) <= done]
        out = out.join(leaf(a), reduce(and_, map(edge_column, edges))) if edges else out.crossJoin(leaf(a))
        done.add(a)
    return out


def sql_value(v) -> str:
    if isinstance(v, str):
        return "'" + v.replace("'", "''") + "'"
    if isinstance(v, dt.datetime):
        return f"timestamp '{v.isoformat(sep=' ')}'"
    return repr(v) + "::double" if isinstance(v, float) else repr(v)


def predicate_sql(p, name=lambda c: c) -> str:
    if p is None:
        return "true"
    if isinstance(p, Clause):
        return f"{name(p.col)} {'<>' if p.op == '!=' else p.op} {sql_value(p.value)}"
    if isinstance(p, Not):
        return f"not ({predicate_sql(p.part, name)})"
    if isinstance(p, Opaque):
        return p.sql
    return "(" + (" and " if isinstance(p, And) else " or ").join(predicate_sql(x, name) for x in p.parts) + ")"


def edge_sql(e: JoinEdge) -> str:
    return f"{e.a1}.{e.c1} {'<>' if e.op == '!=' else e.op} {e.a2}.{e.c2}"


def to_sql(q: Query, select: str = "count(*) as n") -> str:
    where = [predicate_sql(p, lambda c, a=a: f"{a}.{c}") for a, p in q.selections.items()] + list(map(edge_sql, q.joins))
    return f"select {select} from {', '.join(f'{t} {a}' for a, t in q.tables.items())}" + (f" where {' and '.join(where)}" if where else "")
