"""Queries as immutable values that serialise to JSON."""

from __future__ import annotations

import datetime as dt
import json
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce
from typing import Any

from pyspark.sql import Column

OPS = ("<", "<=", ">", ">=", "=", "!=")
NEGATED = {"<": ">=", ">=": "<", ">": "<=", "<=": ">", "=": "!=", "!=": "="}
MIRRORED = {"<": ">", ">": "<", "<=": ">=", ">=": "<=", "=": "=", "!=": "!="}


@dataclass(frozen=True)
class Clause:
    """``col op value``."""

    col: str
    op: str
    value: Any

    def __post_init__(self) -> None:
        if self.op not in OPS:
            raise ValueError(f"unknown comparator {self.op!r}")


@dataclass(frozen=True)
class And:
    parts: tuple

    def __init__(self, *parts) -> None:
        object.__setattr__(self, "parts", tuple(parts))


@dataclass(frozen=True)
class Or:
    parts: tuple

    def __init__(self, *parts) -> None:
        object.__setattr__(self, "parts", tuple(parts))


@dataclass(frozen=True)
class Not:
    part: Any


@dataclass(frozen=True)
class Opaque:
    """A predicate the theory knows nothing of (LIKE, a function): ``sql`` runs on samples, ``dimension`` is declared by the user."""

    sql: str
    dimension: int


@dataclass(frozen=True)
class JoinEdge:
    """``a1.c1 op a2.c2``."""

    a1: str
    c1: str
    op: str
    a2: str
    c2: str

    def __post_init__(self) -> None:
        if self.op not in OPS:
            raise ValueError(f"unknown comparator {self.op!r}")


@dataclass(frozen=True)
class Query:
    """Tables by alias, one selection per alias at most, and join edges; selections stand at the leaves."""

    tables: dict[str, str]
    selections: dict[str, Any] = field(default_factory=dict)
    joins: tuple[JoinEdge, ...] = ()

    def __post_init__(self) -> None:
        object.__setattr__(self, "joins", tuple(self.joins))
        for a in [*self.selections, *(x for e in self.joins for x in (e.a1, e.a2))]:
            if a not in self.tables:
                raise ValueError(f"alias {a!r} has no table")

    @property
    def aliases(self) -> tuple[str, ...]:
        return tuple(self.tables)

    def restricted(self, aliases) -> Query:
        """The sub-query below a plan node over these aliases."""
        keep = set(aliases)
        return Query({a: t for a, t in self.tables.items() if a in keep}, {a: p for a, p in self.selections.items() if a in keep}, tuple(e for e in self.joins if {e.a1, e.a2} <= keep))

    def key(self) -> str:
        return self.to_json()

    def to_json(self) -> str:
        return json.dumps({"tables": dict(sorted(self.tables.items())), "selections": {a: _dump(p) for a, p in sorted(self.selections.items())}, "joins": [[e.a1, e.c1, e.op, e.a2, e.c2] for e in self.joins]}, sort_keys=True)

    @staticmethod
    def from_json(text: str) -> Query:
        d = json.loads(text)
        return Query(d["tables"], {a: _load(p) for a, p in d["selections"].items()}, tuple(JoinEdge(*e) for e in d["joins"]))


def _dump(p) -> list:
    if isinstance(p, Clause):
        v = p.value
        return ["clause", p.col, p.op, {"at": v.isoformat()} if isinstance(v, dt.datetime | dt.date) else v]
    if isinstance(p, Not):
        return ["not", _dump(p.part)]
    if isinstance(p, Opaque):
        return ["opaque", p.sql, p.dimension]
    return ["and" if isinstance(p, And) else "or", *map(_dump, p.parts)]


def _load(x: list):
    kind, *rest = x
    if kind == "clause":
        v = rest[2]
        return Clause(rest[0], rest[1], dt.datetime.fromisoformat(v["at"]) if isinstance(v, dict) else v)
    if kind == "not":
        return Not(_load(rest[0]))
    if kind == "opaque":
        return Opaque(*rest)
    return (And if kind == "and" else Or)(*map(_load, rest))


def clauses(p) -> Iterator[Clause]:
    if isinstance(p, Clause):
        yield p
    elif isinstance(p, Not):
        yield from clauses(p.part)
    elif isinstance(p, And | Or):
        for x in p.parts:
            yield from clauses(x)


def between(col: str, low: Any, high: Any) -> And:
    return And(Clause(col, ">=", low), Clause(col, "<=", high))


def in_list(col: str, values) -> Or:
    return Or(*[Clause(col, "=", v) for v in values])


def all_of(columns: list[Column]) -> Column | None:
    return reduce(lambda a, b: a & b, columns) if columns else None
