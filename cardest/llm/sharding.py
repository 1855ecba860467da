"""Sharding by a minimax contiguous partition of ordered atomic groups.

Equal texts are one atomic group. Groups are ordered by a hash of the text and laid into ``2**UNIT_BITS`` consecutive
units; a unit is never cut, so neither is a group. The smallest capacity for which a greedy walk over the ordered unit
sizes needs no more than the wanted shards is found by binary search; the cuts are then placed as evenly as that capacity
allows. What reaches the driver is one number per unit, a fixed bound that does not grow with the data.
"""

from __future__ import annotations

from itertools import pairwise

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import salt, salts, stored

#: 65,536 units: a shard of forty holds about 1,600 of them, so the cut costs at most 0.06 % of a shard.
UNIT_BITS = 16
#: Bytes that a row costs besides its text.
ROW_BYTES = 16


def minimax_capacity(sizes: np.ndarray, shards: int) -> int:
    """Smallest capacity with which consecutive sizes fit into ``shards`` parts."""
    ends = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    if len(sizes) == 0 or ends[-1] == 0:
        return 0
    low, high = max(int(sizes.max()), -(-int(ends[-1]) // shards)), int(ends[-1])
    while low < high:
        middle = (low + high) // 2
        if _parts(ends, middle, shards) <= shards:
            high = middle
        else:
            low = middle + 1
    return low


def _parts(ends: np.ndarray, capacity: int, most: int) -> int:
    at = used = 0
    while at < len(ends) - 1 and used <= most:
        at = int(np.searchsorted(ends, ends[at] + capacity, side="right")) - 1
        used += 1
    return used


def minimax_cuts(sizes: np.ndarray, shards: int) -> list[int]:
    """First position of every shard but the first, none above the minimax capacity, as even as that allows."""
    ends = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    capacity = minimax_capacity(sizes, shards)
    # the earliest start from which the rest still fits into 1, 2, ... shards
    earliest = [len(sizes)]
    for _ in range(shards):
        earliest.append(int(np.searchsorted(ends, ends[earliest[-1]] - capacity, side="left")))
    cuts, at = [], 0
    for left in range(shards - 1, 0, -1):
        reach = int(np.searchsorted(ends, ends[at] + capacity, side="right")) - 1
        ideal = ends[at] + (ends[-1] - ends[at]) / (left + 1)
        near = int(np.searchsorted(ends, ideal, side="left"))
        if near > at and ideal - ends[near - 1] <= ends[min(near, len(sizes))] - ideal:
            near -= 1
        at = max(at, min(max(near, earliest[left]), reach))
        cuts.append(at)
    return cuts


def shard_of(unit: Column, cuts: list[int]) -> Column:
    """Number of cuts at or before the unit."""
    total = F.lit(0)
    for c in cuts:
        total = total + (unit >= F.lit(c)).cast("int")
    return total


def shard(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Assign every row to a shard of near equal bytes and to a gapless slot in it.

    Returns ``doc_id, size, text_crc32, law, shard, slot, grown_shard``; ``law`` is ``bytes`` and ``grown_shard`` null. A
    null text has no bytes and is grouped with the empty text. Rows that repeat are rows of their own, next to each other
    in slot order; null identifiers come first among their group. A group larger than an even share is a shard of its own
    size at least: groups are never cut. An empty table gives an empty result.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    unit = F.shiftrightunsigned(F.xxhash64(text), 64 - UNIT_BITS).cast("int")
    n = salts(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), (F.octet_length(text) + ROW_BYTES).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"), unit.alias("unit"))
    rows = stored(rows.withColumn("part", salt(n, F.col("doc_id"))), "shard-rows")
    counts = stored(rows.groupBy("unit", "part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")), "shard-units")
    sizes = np.zeros(2**UNIT_BITS, dtype=np.int64)
    per_unit = counts.groupBy("unit").agg(F.sum("bytes").alias("bytes")).toPandas()  # at most 2**UNIT_BITS rows
    sizes[per_unit["unit"].to_numpy()] = per_unit["bytes"].to_numpy()
    cuts = minimax_cuts(sizes, shards)
    assert all(a <= b for a, b in pairwise(cuts))
    counts = counts.withColumn("shard", shard_of(F.col("unit"), cuts))
    # slots: rows before this unit in the shard, before this part in the unit, before this row in the part
    units = counts.groupBy("shard", "unit").agg(F.sum("n").alias("n"))
    before_unit = F.coalesce(F.sum("n").over(W.partitionBy("shard").orderBy("unit").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    units = units.select("unit", before_unit.alias("base"))
    before_part = F.coalesce(F.sum("n").over(W.partitionBy("unit").orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    bases = counts.withColumn("before", before_part).join(units, "unit").select("unit", "part", "shard", (F.col("base") + F.col("before")).alias("base"))
    turn = F.row_number().over(W.partitionBy("unit", "part").orderBy("doc_id", "size", "text_crc32")) - 1
    placed = rows.withColumn("turn", turn).join(bases, ["unit", "part"])
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("base") + F.col("turn")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
