"""Many conditions counted in one pass."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.query.compile import spark_value
from cardest.sources import stored

#: Clauses counted in one aggregation, so that generated code stays below the JVM's 64 KB per method.
BATCH_CLAUSES = 200


def batches(conditions: dict[str, str], weights: dict[str, int] | None) -> list[list[str]]:
    out: list[list[str]] = []
    load = 0
    for name in conditions:
        w = (weights or {}).get(name, 1) + 1
        if not out or load + w > BATCH_CLAUSES:
            out.append([])
            load = 0
        out[-1].append(name)
        load += w
    return out


def counts_of(frame: DataFrame, conditions: dict[str, str], weights: dict[str, int] | None = None, keep: bool = False) -> DataFrame:
    """``query_id, hits``: one pass over the frame per batch of conditions, one row per task shuffled.

    ``weights`` are clauses per condition. A small frame that several batches read is written once if ``keep``.
    """
    groups = batches(conditions, weights)
    if keep and len(groups) > 1:
        frame = stored(frame, "frame")
    parts = [frame.agg(hits_array(conditions, batch)).select(named_hits(batch)).select("x.*") for batch in groups]
    return reduce(DataFrame.unionByName, parts)


def hits_array(conditions: dict[str, str], batch: list[str]):
    """Counts of all conditions of a batch as one array: one expression text instead of thousands of calls to the JVM."""
    return F.expr(f"array({', '.join(f'count_if({conditions[n]})' for n in batch)})").alias("hits")


def named_hits(batch: list[str]):
    """The array as rows of ``query_id, hits``."""
    return F.explode(F.arrays_zip(F.expr(f"array({', '.join(map(spark_value, batch))})").alias("query_id"), F.col("hits"))).alias("x")
