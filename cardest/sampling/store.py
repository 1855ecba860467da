"""Samples on disk: one Parquet folder per alias, ordered by index, with a manifest; and when to build anew."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.query.normalize import QueryClass
from cardest.sampling.build import INDEX, SampleDB


def save(sdb: SampleDB, path: str, buckets: int = 8) -> None:
    """All sample tables are parted by index in the same way, so that later joins on it find partners together."""
    spark = next(iter(sdb.tables.values())).sparkSession
    for a, df in sdb.tables.items():
        df.repartitionByRange(buckets, INDEX).sortWithinPartitions(INDEX).write.mode("overwrite").parquet(f"{path}/{a}")
    manifest = {"sizes": sdb.sizes, "s": sdb.s, "seed": sdb.seed, "source": sdb.source, "qclass": sdb.qclass and asdict(sdb.qclass), "delta": sdb.delta, "c": sdb.c, "replacement": sdb.replacement, "exact": sorted(sdb.exact)}
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/_manifest")


def load(spark: SparkSession, path: str) -> SampleDB:
    m = json.loads(spark.read.text(f"{path}/_manifest").first()[0])
    tables = {a: spark.read.parquet(f"{path}/{a}") for a in m["source"]}
    qclass = QueryClass(**m["qclass"]) if m["qclass"] else None
    return SampleDB(tables, m["sizes"], m["s"], m["seed"], m["source"], qclass, m["delta"], m["c"], m["replacement"], frozenset(m["exact"]))


def save_bucketed(sdb: SampleDB, prefix: str, buckets: int = 8) -> list[str]:
    """As bucketed catalog tables: a join on the index of two of them needs no shuffle."""
    names = []
    for a, df in sdb.tables.items():
        df.write.bucketBy(buckets, INDEX).sortBy(INDEX).mode("overwrite").saveAsTable(f"{prefix}_{a}")
        names.append(f"{prefix}_{a}")
    return names


def footprint(sdb: SampleDB) -> DataFrame:
    """``alias, sample_rows, base_rows, columns, cells`` per sample table."""
    parts = [df.agg(F.count("*").alias("sample_rows")).select(F.lit(a).alias("alias"), "sample_rows", F.lit(sdb.sizes[a]).cast("long").alias("base_rows"), F.lit(len(df.columns)).alias("columns")) for a, df in sdb.tables.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.withColumn("cells", F.col("sample_rows") * F.col("columns"))


def needs_refresh(old: dict[str, float], new: dict[str, float], eps: float, growth: float = 0.0, most_growth: float = 0.5) -> bool:
    """Whether the database has changed in a major way: it has grown much, or probe estimates moved by more than 2 eps."""
    return growth > most_growth or any(abs(old[q] - new[q]) > 2 * eps for q in old.keys() & new.keys())
