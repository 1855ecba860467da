"""Shared plumbing: the folder all executors see, salted lookups for hot keys, connected components."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Edges of one task of the first contraction.
EDGES = 500_000
#: ASCII white space of the contracts, as a regular-expression class body.
BLANK = r"\x20\x09-\x0D"


@lru_cache(maxsize=1)
def _scratch() -> str:
    path = tempfile.mkdtemp(prefix="cardest-")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    return path


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; a temporary one only where the driver is the whole cluster."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return _scratch()


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut and a lost executor costs nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def narrow_batches(spark: SparkSession, rows: int) -> Iterator[None]:
    """Arrow batches of at most ``rows`` for the jobs run inside, where single rows are wide."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def salts(spark: SparkSession) -> int:
    """Into how many parts a hot key is dealt: follows the cluster's shuffle width."""
    return max(16, int(spark.conf.get("spark.sql.shuffle.partitions")))


def salt(n: int, *by: Column) -> Column:
    return F.pmod(F.xxhash64(*by), F.lit(n)).cast("int")


def attach(rows: DataFrame, key: str, spread: str, lookup: DataFrame) -> DataFrame:
    """Left join of ``lookup`` (one row per ``key``) to ``rows`` when one key may hold a third of all rows.

    Every key is dealt into parts by a hash of ``spread``; the lookup value is first joined to the parts that exist
    (at most ``salts`` a key), then to the rows of each part. No task sees more than a part of a hot key.
    """
    part, n = "__part", salts(rows.sparkSession)
    rows = rows.withColumn(part, salt(n, F.col(spread)))
    parts = rows.groupBy(key, part).agg(F.lit(1).alias("__one")).drop("__one").join(lookup, key, "left")
    return rows.join(parts, [key, part], "left").drop(part)


def components(edges: DataFrame, a: str = "a", b: str = "b", limit: int = 60) -> DataFrame:
    """Connected components of an edge list of longs: ``node``, ``root`` (smallest node reachable), nodes with edges only.

    Edges are dealt into tasks of ``EDGES`` and each task keeps only a forest of stars, which removes long chains; then
    large-star and small-star contractions alternate. Each round is two aggregations with map-side combining and joins that
    adaptive execution may split, and is written to the shared folder, so that plans stay short and lost executors are
    survived. Stops when a round changes nothing.
    """
    links = stored(
        edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b))).select(F.greatest(a, b).cast("long").alias("hi"), F.least(a, b).cast("long").alias("lo")).distinct(),
        "links",
    )
    n = links.count()
    if not n:
        return links.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
    links = stored(links.repartition(-(-n // EDGES)).mapInPandas(_stars, "hi long, lo long"), "links")
    before = _state(links)
    for _ in range(limit):
        links = stored(_small_star(_large_star(links)), "links")
        state = _state(links)
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components: no fixed point after {limit} rounds")
    return links.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(links.select(F.col("lo").alias("node"), F.col("lo").alias("root"))).groupBy("node").agg(F.min("root").alias("root"))


def _state(links: DataFrame):
    return links.agg(F.count("*").alias("n"), F.sum(F.hash("hi", "lo").cast("long")).alias("h"), F.sum(F.col("lo").cast("decimal(38,0)")).alias("t")).first()


def _stars(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Union-find over one task's edges: every node tied to the smallest it reaches there."""
    up: dict[int, int] = {}

    def find(x: int) -> int:
        while (p := up.setdefault(x, x)) != x:
            up[x] = up.setdefault(p, p)
            x = up[x]
        return x

    for b in batches:
        for x, y in zip(b["hi"].tolist(), b["lo"].tolist(), strict=True):
            x, y = find(x), find(y)
            if x != y:
                up[max(x, y)] = min(x, y)
    rows = [(x, r) for x in list(up) if (r := find(x)) != x]
    yield pd.DataFrame(rows, columns=["hi", "lo"]).astype("int64")


def _large_star(links: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is tied to the node's smallest neighbour (itself included)."""
    both = links.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(links.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
    return both.where("v > u").join(least, "u").where("v <> m").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()


def _small_star(links: DataFrame) -> DataFrame:
    """A node and its smaller neighbours are tied to the smallest of these."""
    least = links.groupBy("hi").agg(F.min("lo").alias("m"))
    moved = links.join(least, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
    return moved.unionByName(least.select("hi", F.col("m").alias("lo"))).distinct()


#: Identifiers that may be broadcast to drop rows without moving texts: 8 bytes each.
BROADCAST_IDS = 2_000_000


def without(docs: DataFrame, dropped: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """``docs`` without the identifiers in ``dropped`` (one column, same name): broadcast up to a bound, shuffled beyond."""
    dropped = stored(dropped.select(id_col).where(F.col(id_col).isNotNull()).distinct(), "dropped")
    return docs.join(F.broadcast(dropped) if dropped.count() <= BROADCAST_IDS else dropped, id_col, "left_anti").select(*docs.columns)
