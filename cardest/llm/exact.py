"""Exact deduplication with a log-structured merge index of digests (DataFrame functions only).

Level 0: every input task is a memtable; it flushes one run, sorted by digest, whose Parquet footer carries minimum,
maximum and a Bloom filter of the digest, so that a probe opens only the runs and row groups that may hold it.
Compaction merges any number of runs and levels: of each digest it keeps the smallest identifier and adds up the counts.
Hits are then verified byte for byte, each group in parts.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import BLANK, attach, salt, shared_dir, stored, without

#: Parts into which a group of copies is dealt while it is verified.
VERIFY_PARTS = 64
#: Digests of repeated texts that may be broadcast: 32 bytes each, so at most 32 MB of keys.
BROADCAST_GROUPS = 1_000_000


def normalised(text: Column) -> Column:
    """Null is empty; every run of ASCII white space is one space."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), f"[{BLANK}]+", " ")


@dataclass
class DigestIndex:
    """Runs of (digest, first_id, copies), sorted by digest, in a folder that all executors share."""

    spark: SparkSession
    path: str
    levels: list[list[str]] = field(default_factory=list)

    @classmethod
    def create(cls, spark: SparkSession) -> DigestIndex:
        return cls(spark, f"{shared_dir(spark)}/digest-index-{uuid.uuid4().hex}")

    def _put(self, rows: DataFrame, level: int) -> None:
        run = f"{self.path}/L{level}/{uuid.uuid4().hex}"
        rows.sortWithinPartitions("digest").write.option("parquet.bloom.filter.enabled#digest", "true").parquet(run)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(run)

    def flush(self, batch: DataFrame) -> None:
        """Add a batch of (digest binary, doc_id): each of its tasks is one memtable and writes one sorted run."""
        self._put(batch.select("digest", F.col("doc_id").cast("long").alias("first_id"), F.lit(1).cast("long").alias("copies")), 0)

    def rows(self) -> DataFrame:
        runs = [p for level in self.levels for p in level]
        return self.spark.read.schema("digest binary, first_id bigint, copies bigint").parquet(*runs)

    def compact(self) -> None:
        """Merge all levels into one: smallest identifier, sum of counts, one row per digest."""
        if len(self.levels) and (len(self.levels[0]) or sum(map(len, self.levels)) > 1):
            merged = self.rows().groupBy("digest").agg(F.min("first_id").alias("first_id"), F.sum("copies").alias("copies"))
            level = max(1, len(self.levels))
            self._put(merged, level)
            self.levels = [[] for _ in range(level)] + [self.levels[level][-1:]]

    def probe(self, digests: DataFrame) -> DataFrame:
        """Rows of (digest, doc_id) with the compacted entry of their digest, hot digests dealt into parts."""
        entries = self.rows().groupBy("digest").agg(F.min("first_id").alias("first_id"), F.sum("copies").alias("copies"))
        return attach(digests, "digest", "doc_id", entries)

    def contains(self, digest: bytes) -> bool:
        """Point probe: an equality filter on the digest is pushed to footers and Bloom filters."""
        return not self.rows().where(F.col("digest") == F.lit(digest)).isEmpty()


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Group equal texts; one row per input row.

    Returns ``doc_id, keep_id, group_size, kept, text_sha256``. Null text counts as empty. A null identifier sorts after
    all others: it stays only where its whole group has none, and ``keep_id`` is then null. Rows that repeat both
    identifier and text form one group of which exactly one is kept. An empty table gives an empty result; other columns,
    whatever their names, are not read. Raises if two different texts ever share a digest.
    """
    spark = docs.sparkSession
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), normalised(F.col(text_col)).alias("text"))
    keyed = base.select("doc_id", F.unhex(F.sha2("text", 256)).alias("digest"))
    index = DigestIndex.create(spark)
    index.flush(keyed)
    index.compact()
    found = index.probe(keyed)
    turn = F.row_number().over(W.partitionBy("digest", "doc_id").orderBy(F.lit(1)))
    verify_hits(base, index)
    return found.select(
        "doc_id",
        F.col("first_id").alias("keep_id"),
        F.col("copies").alias("group_size"),
        (F.col("doc_id").eqNullSafe(F.col("first_id")) & (turn == 1)).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def verify_hits(base: DataFrame, index: DigestIndex) -> int:
    """Check byte for byte that the texts of every group of two or more are one text; returns how many were compared.

    Only hits move. The groups are broadcast up to ``BROADCAST_GROUPS`` of them, a bound on bytes, and joined by a shuffle
    beyond. A group is one text if its least and greatest text are the same bytes; both are taken in parts of the group,
    combined inside each task first, so a text with a third of all rows is sent once by a task and part.
    """
    groups = index.rows().where("copies > 1").select("digest")
    if groups.count() <= BROADCAST_GROUPS:
        groups = F.broadcast(groups)
    hits = base.select("doc_id", "text", F.unhex(F.sha2("text", 256)).alias("digest")).join(groups, "digest", "left_semi")
    parts = hits.groupBy("digest", salt(VERIFY_PARTS, F.col("doc_id")).alias("part")).agg(F.min("text").alias("least"), F.max("text").alias("most"), F.count("*").alias("n"))
    whole = parts.groupBy("digest").agg(F.min("least").alias("least"), F.max("most").alias("most"), F.sum("n").alias("n"))
    seen = whole.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count_if(F.encode("least", "UTF-8") != F.encode("most", "UTF-8")).alias("bad")).first()
    if seen["bad"]:
        raise RuntimeError(f"{seen['bad']} digests are shared by different texts")
    return seen["n"]


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all columns. Of rows that repeat identifier and text one stays."""
    found = stored(exact_duplicates(docs, id_col, text_col).select(F.col("doc_id").alias(id_col), "kept", "text_sha256"), "exact-found")
    kept = found.where("kept").select(id_col)
    out = without(docs, found.where("not kept").select(id_col).join(kept, id_col, "left_anti"), id_col)
    # identifiers alone do not tell which rows stay where they repeat or are missing
    if found.where(F.col(id_col).isNull() & ~F.col("kept")).isEmpty() and found.groupBy(id_col).count().where("count > 1").isEmpty():
        return out
    turn = F.row_number().over(W.partitionBy(id_col, normalised(F.col(text_col))).orderBy(F.lit(1)))
    stays = found.where("kept").select(F.col(id_col).alias("__id"), F.col("text_sha256").alias("__digest"))
    out = out.select("*", turn.alias("__turn"), F.sha2(normalised(F.col(text_col)), 256).alias("__sha")).where("__turn = 1")
    return out.join(stays, out[id_col].eqNullSafe(stays["__id"]) & (out["__sha"] == stays["__digest"]), "left_semi").select(*docs.columns)
