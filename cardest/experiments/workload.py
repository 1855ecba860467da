"""Tables with known distributions derived from dense keys, and random queries over them.

Derived columns are integer arithmetic on digests of the key, so any engine builds the same tables.
"""

from __future__ import annotations

import json
import random

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.functions.rng import u60, u60_sql
from cardest.query.ir import And, Clause, JoinEdge, Or, Query

SEED = 7
DOMAIN = 1000
JOIN_DOMAIN = 25
UNIFORM = ("u1", "u2", "u3", "u4", "u5")
#: Sum of ten three-digit hexadecimal groups: nearly normal, this mean and deviation.
NORMAL_MEAN, NORMAL_SD = 20475.0, 3739.0


def orders_u(db, seed: int = SEED, domain: int = DOMAIN, join_domain: int = JOIN_DOMAIN) -> DataFrame:
    """``o_orderkey, u1..u5, jc``: independent uniform columns, one row per order."""
    return _uniform(db["orders"], "o_orderkey", seed, domain, join_domain)


def events_u(db, seed: int = SEED, domain: int = DOMAIN, join_domain: int = JOIN_DOMAIN) -> DataFrame:
    """``event_id, u1..u5, jc``: the join partner, with streams of its own."""
    return _uniform(db["events"], "event_id", seed, domain, join_domain)


def _uniform(df: DataFrame, key: str, seed: int, domain: int, join_domain: int) -> DataFrame:
    cols = [F.pmod(u60(seed, f"{key[0]}{u}", F.col(key)), F.lit(domain)).alias(u) for u in UNIFORM]
    return df.select(key, *cols, F.pmod(u60(seed, f"{key[0]}jc", F.col(key)), F.lit(join_domain)).alias("jc"))


def _bell(seed: int, name: str, key: str) -> Column:
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(name), F.col(key).cast("string")))
    out = F.lit(0).cast("long")
    for i in range(10):
        out = out + F.conv(F.substring(h, 1 + 3 * i, 3), 16, 10).cast("long")
    return out


def orders_c(db, seed: int = SEED, own: int = 3, other: int = 4, scale: int = 5) -> DataFrame:
    """``o_orderkey, c1, c2``: a correlated nearly normal pair, correlation own / sqrt(own^2 + other^2)."""
    z = db["orders"].select("o_orderkey", _bell(seed, "z1", "o_orderkey").alias("z1"), _bell(seed, "z2", "o_orderkey").alias("z2"))
    return z.select("o_orderkey", F.col("z1").alias("c1"), F.expr(f"({own} * z1 + {other} * z2) div {scale}").alias("c2"))


class Workbench(dict):
    """The base tables and the derived ones, by name."""

    def __init__(self, db) -> None:
        super().__init__()
        self.db = db

    def __missing__(self, name: str) -> DataFrame:
        made = {"orders_u": orders_u, "events_u": events_u, "orders_c": orders_c}.get(name)
        self[name] = made(self.db) if made else self.db[name]
        return self[name]


KEYS = {"orders_u": "o_orderkey", "events_u": "event_id", "orders_c": "o_orderkey", "orders": "o_orderkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "events": "event_id", "documents": "doc_id", "nation": "n_nationkey", "region": "r_regionkey"}


def derived_sql() -> dict[str, str]:
    """The derived tables as SQL, by name."""

    def uniform(table: str, key: str) -> str:
        cols = ", ".join(f"{u60_sql(SEED, repr(key[0] + u), key)} % {DOMAIN} as {u}" for u in UNIFORM)
        return f"select {key}, {cols}, {u60_sql(SEED, repr(key[0] + 'jc'), key)} % {JOIN_DOMAIN} as jc from {table}"

    def bell(name: str) -> str:
        h = f"md5(concat_ws('|', '{SEED}', '{name}', o_orderkey::varchar))"
        return "(" + " + ".join(f"('0x' || substr({h}, {1 + 3 * i}, 3))::bigint" for i in range(10)) + ")"

    return {
        "orders_u": uniform("orders", "o_orderkey"),
        "events_u": uniform("events", "event_id"),
        "orders_c": f"select o_orderkey, z1 as c1, (3 * z1 + 4 * z2) // 5 as c2 from (select o_orderkey, {bell('z1')} as z1, {bell('z2')} as z2 from orders)",
    }


def random_predicate(rng: random.Random, columns: dict[str, tuple[int, int]], m: int, b: int, ops: tuple[str, ...] = ("<=", ">="), shape: str = "random"):
    """``b`` clauses over ``m`` random columns (each used while clauses last); comparators, constants and connectives uniform."""
    chosen = rng.sample(sorted(columns), min(m, len(columns), b))
    picks = chosen + [rng.choice(chosen) for _ in range(b - len(chosen))]
    rng.shuffle(picks)
    parts: list = [Clause(c, rng.choice(ops), rng.randint(*columns[c])) for c in picks]
    while len(parts) > 1:
        i = 0 if shape == "left" else rng.randrange(len(parts) - 1)
        parts[i : i + 2] = [rng.choice((And, Or))(parts[i], parts[i + 1])]
    return parts[0]


def select_queries(table: str, alias: str, columns: dict[str, tuple[int, int]], m: int, b: int, count: int = 100, seed: int = 1, ops: tuple[str, ...] = ("<=", ">=")) -> dict[str, Query]:
    rng = random.Random(f"{seed}/{table}/{m}/{b}")
    return {f"q{i:03d}": Query({alias: table}, {alias: random_predicate(rng, columns, m, b, ops)}) for i in range(count)}


def join_queries(left: str, right: str, columns: dict[str, tuple[int, int]], m: int, b: int, count: int = 100, seed: int = 1, op: str | None = "=", key: str = "jc") -> dict[str, Query]:
    """Pairs of selections joined on ``key``; a random comparator where ``op`` is None."""
    rng = random.Random(f"{seed}/{left}/{right}/{m}/{b}/{op}")
    ops = ("<", "<=", ">", ">=", "=", "!=")
    out = {}
    for i in range(count):
        edge = JoinEdge("a", key, op or rng.choice(ops), "b", key)
        out[f"q{i:03d}"] = Query({"a": left, "b": right}, {"a": random_predicate(rng, columns, m, b), "b": random_predicate(rng, columns, m, b)}, (edge,))
    return out


UNIFORM_COLUMNS = {u: (0, DOMAIN - 1) for u in UNIFORM}
CORRELATED_COLUMNS = {"c1": (12000, 29000), "c2": (18000, 39000)}


def save(spark: SparkSession, queries: dict[str, Query], path: str) -> None:
    spark.createDataFrame([(k, q.to_json()) for k, q in queries.items()], "query_id string, ir string").write.mode("overwrite").json(path)


def load(spark: SparkSession, path: str) -> dict[str, Query]:
    rows = spark.read.schema("query_id string, ir string").json(path).orderBy("query_id").collect()
    return {r["query_id"]: Query.from_json(r["ir"]) for r in rows}


def as_json(queries: dict[str, Query]) -> str:
    return json.dumps({k: json.loads(q.to_json()) for k, q in queries.items()}, sort_keys=True)
