"""Mixing sources to target weights by Pareto order sampling (DataFrame functions only).

Sources share the words of the whole table by weight; a source gives at most ``cap`` times its own words and what it
cannot give is shared again among the rest. A source's target is met by whole copies of every document first (certain
inclusions); the remaining words are a fixed-size sample with unequal probabilities: documents are ranked by random odds
divided by inclusion odds and taken in that order until the words are there. No source is ever gathered in one task: ranks
are cut into fixed bins, and only the bin in which the target falls is ordered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import BLANK, stored

#: Fixed bins of the rank odds; documents of one source that fall into the target's bin are ordered in one task.
BINS = 4096
#: 52 bits of a digest, so that the uniform number and its complement are exact doubles.
UNIFORM_HEX = 13


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(f"[^{BLANK}]+")), F.lit(0)).cast("long")


def random_odds(id_col: str, seed: int) -> Column:
    digest = F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col(id_col).cast("string"), F.lit("null")))), 1, UNIFORM_HEX)
    u = (F.conv(digest, 16, 10).cast("double") + 0.5) / float(16**UNIFORM_HEX)
    return u / (1 - u)


def source_targets(sources: DataFrame, cap: float = 3.0) -> DataFrame:
    """``source, source_size`` (one row per source) with ``target``: all words shared by weight 1, 2, 3, 1, 2, 3, ...

    Closed form of sharing the excess again until nobody is above ``cap`` times its size: sources are ordered by size per
    weight, the first ones are full, the rest share what is left. The table holds one row per source.
    """
    order = W.orderBy(F.col("source").asc_nulls_last())
    by_room = W.orderBy("room", F.col("source").asc_nulls_last())
    ranked = sources.withColumn("weight", ((F.row_number().over(order) - 1) % 3 + 1).cast("double"))
    ranked = ranked.withColumn("most", F.col("source_size") * F.lit(float(cap))).withColumn("room", F.col("most") / F.col("weight"))
    everything = W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    before = by_room.rowsBetween(W.unboundedPreceding, -1)
    level = (F.sum("source_size").over(everything) - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / F.sum("weight").over(by_room.rowsBetween(0, W.unboundedFollowing))
    ranked = ranked.withColumn("level", level).withColumn("full", F.col("level") >= F.col("room"))
    shared = F.max(F.when(~F.col("full"), F.col("level"))).over(everything)
    return ranked.select("source", "source_size", "merit_size", F.when(F.col("full"), F.col("most")).otherwise(shared * F.col("weight")).alias("target"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", cap: int = 3, seed: int = 1) -> DataFrame:
    """How many copies of every document the mix takes.

    Returns one row per input row: ``doc_id, source, size, source_size, target, copies, taken`` (``taken = copies * size``).
    Inclusion probabilities fall with the bit length of a document's word count, so repeats spread over more texts. After
    the sample, one more document per source closes the gap where that brings the words nearer to the target. Reruns give
    the same result: random numbers come from a digest of the identifier. Null text has no words; null is a source of its
    own, ordered last; null identifiers share one random number; rows that repeat everything are separate documents (two
    of them may close a gap together). Ties in rank are broken by identifier. An empty table gives an empty result.
    """
    base = stored(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).alias("source"), words(F.col(text_col)).alias("size")), "mix-sizes")
    base = base.withColumn("merit", F.expr(f"{2**20} div length(bin(size))"))
    sources = base.groupBy("source").agg(F.sum("size").alias("source_size"), F.sum(F.col("merit").cast("decimal(38,0)") * F.col("size")).cast("double").alias("merit_size"))
    plan = stored(_quota(source_targets(sources, cap), cap), "mix-targets")
    pi = F.least(F.lit(1.0), F.col("rest") * F.col("merit") / F.col("merit_size"))
    rows = base.join(plan, base.source.eqNullSafe(plan.source)).drop(plan.source).withColumn("pi", pi)
    q = F.when(F.col("pi") >= 1, 0.0).when(F.col("pi") > 0, random_odds("doc_id", seed) * (1 - F.col("pi")) / F.col("pi"))
    rows = rows.withColumn("q", q).withColumn("bin", F.floor(F.lit(BINS) * F.col("q") / (1 + F.col("q"))))
    bins = rows.where("rest > 0").groupBy("source", "bin").agg(F.sum("size").alias("bin_size"), F.first("rest").alias("rest"))
    upto = F.sum("bin_size").over(W.partitionBy("source").orderBy(F.col("bin").asc_nulls_last()).rowsBetween(W.unboundedPreceding, 0))
    edge = bins.withColumn("upto", upto).where("upto > rest").groupBy("source").agg(F.min(F.struct(F.coalesce("bin", F.lit(BINS)).alias("bin"), (F.col("upto") - F.col("bin_size")).alias("before"))).alias("e")).select(F.col("source").alias("e_source"), "e.bin", "e.before")
    edge = edge.withColumnsRenamed({"bin": "edge_bin"})
    rows = rows.join(edge, rows.source.eqNullSafe(edge.e_source), "left").drop("e_source")
    # without an edge the whole source is wanted once more, but for rounding
    place = F.coalesce(F.col("bin"), F.lit(BINS))
    inside = rows.where(place == F.col("edge_bin"))
    run = F.sum("size").over(W.partitionBy("source").orderBy(F.col("q").asc_nulls_last(), "doc_id", "size").rowsBetween(W.unboundedPreceding, 0))
    inside = inside.withColumn("extra", (F.col("before") + run <= F.col("rest")).cast("int"))
    outside = rows.where(F.col("edge_bin").isNull() | (place != F.col("edge_bin"))).withColumn("extra", F.when(F.col("rest") <= 0, 0).when(F.col("edge_bin").isNull(), 1).otherwise((place < F.col("edge_bin")).cast("int")))
    drawn = stored(inside.unionByName(outside).select("doc_id", "source", "size", "source_size", "target", "whole", "rest", "extra"), "mix-drawn")
    gap = drawn.groupBy("source").agg((F.first("rest") - F.sum(F.col("size") * F.col("extra"))).alias("gap")).select(F.col("source").alias("g_source"), "gap")
    near = F.abs(F.col("size") - F.col("gap"))
    gaps = drawn.where("extra = 0 and size > 0 and rest > 0").join(gap, F.col("source").eqNullSafe(F.col("g_source"))).where(near < F.col("gap"))
    closing = gaps.groupBy("source").agg(F.min(F.struct(near.alias("near"), "doc_id", "size")).alias("c")).select(F.col("source").alias("c_source"), F.col("c.doc_id").alias("c_id"), F.col("c.size").alias("c_size"))
    out = drawn.join(closing, F.col("source").eqNullSafe(F.col("c_source")), "left")
    closes = (F.col("extra") == 0) & F.col("c_source_hit")
    out = out.withColumn("c_source_hit", F.coalesce(F.col("c_size") == F.col("size"), F.lit(False)) & F.col("doc_id").eqNullSafe(F.col("c_id")))
    copies = (F.col("whole") + F.col("extra") + closes.cast("int")).cast("long")
    return out.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))


def _quota(targets: DataFrame, cap: int) -> DataFrame:
    """Whole copies that every document of the source gets for certain, and the words that are left to sample."""
    whole = F.when(F.col("source_size") > 0, F.least(F.lit(cap), F.floor(F.col("target") / F.col("source_size")))).otherwise(0).cast("int")
    t = targets.withColumn("whole", whole)
    return t.withColumn("rest", F.when(F.col("whole") >= cap, 0.0).otherwise(F.col("target") - F.col("whole") * F.col("source_size")))


def materialise(docs: DataFrame, taken: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The mixed corpus: every document as often as ``copies`` says, with the columns of ``docs``.

    ``docs`` must not repeat an identifier with a different text; copies of a row are rows of their own.
    """
    copies = taken.where("copies > 0").groupBy("doc_id").agg(F.min("copies").alias("__copies"))
    rows = docs.join(copies, docs[id_col].eqNullSafe(copies["doc_id"])).select(*[docs[c] for c in docs.columns], "__copies")
    return rows.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies").cast("int")))).select(*docs.columns)
