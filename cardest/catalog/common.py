"""Sample tables and estimates as SQL, from the same query values that Spark runs."""

from __future__ import annotations

from cardest.experiments.workload import KEYS, Workbench, derived_sql
from cardest.functions.rng import draws_sql
from cardest.query.compile import edge_sql, predicate_sql
from cardest.query.ir import Query
from cardest.sources import load_db

SEED = 42
LINEITEM_ORDER = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
SAMPLE_KEYS: dict = KEYS | {"lineitem": LINEITEM_ORDER}


def bench(spark, sf_dir: str) -> Workbench:
    return Workbench(load_db(spark, sf_dir))


def derived_ctes(names) -> list[str]:
    have = derived_sql()
    return [f"{n} as ({have[n]})" for n in sorted(set(names)) if n in have]


def sample_sql(alias: str, table: str, s: int, seed: int = SEED, name: str | None = None) -> list[str]:
    """Common table expressions that end in the sample of an alias."""
    key = SAMPLE_KEYS[table]
    name = name or f"s_{alias}"
    draws = draws_sql(s, seed, alias, f"select count(*) from {table}")
    if isinstance(key, str):
        return [f"{name} as (select d.sampleindex, t.* from ({draws}) d join {table} t on t.{key} = d.pos)"]
    return [f"r_{alias} as (select *, row_number() over (order by {', '.join(key)}) - 1 as rk from {table})", f"{name} as (select d.sampleindex, t.* exclude (rk) from ({draws}) d join r_{alias} t on t.rk = d.pos)"]


def condition_sql(q: Query) -> str:
    parts = [predicate_sql(p, lambda c, a=a: f"{a}.{c}") for a, p in q.selections.items()] + [edge_sql(e) for e in q.joins]
    return " and ".join(parts) or "true"


def counts_sql(queries: dict[str, Query], relation: str, ctes: list[str], per: str = "{s}", value: str = "hits::double / {s}", s: int = 0) -> str:
    """``query_id, s, hits, sigma`` of many conditions in one pass over a relation."""
    names = list(queries)
    head = "with " + ", ".join([*ctes, "agg as (select " + ", ".join(f"count(*) filter (where {condition_sql(q)}) as h{i}" for i, q in enumerate(queries.values())) + f" from {relation})"])
    ids = ", ".join(f"'{n}'" for n in names)
    hits = ", ".join(f"h{i}" for i in range(len(names)))
    return f"{head} select query_id, {s}::bigint as s, hits::bigint as hits, {value.format(s=s)} as sigma from (select unnest([{ids}]) as query_id, unnest([{hits}]) as hits from agg)"


def estimate_sql(queries: dict[str, Query], s: int, seed: int = SEED) -> str:
    """The index-matched estimate in SQL: samples joined on their index, conditions counted."""
    tables = next(iter(queries.values())).tables
    ctes = derived_ctes(tables.values())
    for a, t in tables.items():
        ctes += sample_sql(a, t, s, seed)
    first, *rest = tables
    relation = f"s_{first} {first}" + "".join(f" join s_{a} {a} on {a}.sampleindex = {first}.sampleindex" for a in rest)
    return counts_sql(queries, relation, ctes, s=s)
