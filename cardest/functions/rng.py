"""Random numbers from a counter and a digest: the same on every engine, partitioning and retry."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPAN = 2**60


def u60(*parts: Column | str | int) -> Column:
    """60 uniform bits of the parts, joined by vertical bars."""
    columns = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in columns])), 1, 15), 16, 10).cast("long")


def u60_sql(*parts: str | int) -> str:
    """The same as DuckDB SQL; numbers and quoted strings are constants, other strings expressions."""
    texts = [f"'{p}'" if isinstance(p, int) else p if p.startswith("'") else f"({p})::varchar" for p in parts]
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(texts)})), 1, 15))::bigint"


def draws(spark: SparkSession, s: int, seed: int, alias: str, population: int) -> DataFrame:
    """``sampleindex, pos``: ``s`` independent uniform positions of a table; the stream depends on seed and alias."""
    index = F.col("id").alias("sampleindex")
    return spark.range(1, s + 1).select(index, F.pmod(u60(seed, alias, F.col("id")), F.lit(population)).alias("pos"))


def draws_sql(s: int, seed: int, alias: str, population: str) -> str:
    return f"select i as sampleindex, {u60_sql(seed, repr(alias), 'i')} % ({population}) as pos from range(1, {s + 1}) r(i)"
