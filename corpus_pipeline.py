"""A training corpus from raw documents: toxic texts go, copies and near copies go, sources are mixed, the rest is packed."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.llm import exact, mixing, ngrams, packing, toxicity
from cardest.llm.common import stored, without
from cardest.llm.queries import vocabulary


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.3 or more go; null texts are empty and stay unless empty texts are toxic."""
    model = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return docs.where(toxicity.scorer(spark, model)("text") < 0.3)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the smallest identifier stays."""
    return exact.deduplicate(docs)


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every class of near copies (five-word shingles, similarity 0.8) the smallest identifier stays.

    Rows without identifier go by a key made of their text, above 2^62, so that they come after all identifiers and one of
    a class without any stays. Exact copies are gone before this stage, so no two of them have one text.
    """
    own = F.shiftrightunsigned(F.xxhash64("text"), 2) + F.lit(2**62)
    keyed = docs.withColumn("__key", F.coalesce(F.col("doc_id").cast("long"), own))
    classes = stored(ngrams.near_copies(keyed, n=5, threshold=Fraction(4, 5), id_col="__key").withColumnRenamed("doc_id", "__key"), "near-classes")
    kept = classes.where("__key = component_id").select("__key")
    return without(keyed, classes.where("__key <> component_id").select("__key").join(kept, "__key", "left_anti"), "__key").drop("__key")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it."""
    return mixing.materialise(docs, mixing.mix(docs))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of at most 2048 tokens."""
    return packing.pack(docs, vocabulary("byte_bpe_50k.json"), capacity=2048)


STAGES = [
    ("toxicity", toxicity_filter),
    ("exact dedup", exact_dedup),
    ("n-gram Jaccard join", ngram_jaccard_join),
    ("mixing sources to target weights", mix_sources),
    ("packing", pack_sequences),
]

#: Scores and token ids have no SQL form; run() is tested against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read again by the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name.split()[0]}")
    return STAGES[-1][1](spark, docs, sf_dir)
