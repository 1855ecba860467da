"""Tables in, tables out: Parquet and other formats, views, row positions, the shared folder."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Database(dict):
    """Tables by name, opened when first asked for; columns and filters are pushed to the scan by the optimiser."""

    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        super().__init__()
        self.spark, self.sf_dir = spark, sf_dir

    def __missing__(self, name: str) -> DataFrame:
        self[name] = load(self.spark, self.sf_dir, name)
        return self[name]


def load_db(spark: SparkSession, sf_dir: str) -> Database:
    return Database(spark, sf_dir)


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options: str) -> DataFrame:
    """CSV, JSON, ORC, Parquet or any format Spark knows; never inferred where a schema is given."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def register_views(db: Database, names: tuple[str, ...] = TABLES, prefix: str = "") -> None:
    for n in names:
        db[n].createOrReplaceTempView(prefix + n)


def with_row_position(spark: SparkSession, path: str) -> DataFrame:
    """All columns with ``__file`` and ``__row``, the row's place in its file; positions cost nothing to compute."""
    return spark.read.parquet(path).select("*", F.col("_metadata.file_path").alias("__file"), F.col("_metadata.row_index").alias("__row"))


def numeric_views(db: Database) -> dict[str, DataFrame]:
    """Wide text tables as their lengths; only lengths leave the scan stage."""
    return {
        "documents": db["documents"].select("doc_id", "n_chars", F.length("text").cast("long").alias("text_length")),
        "pages": db["pages"].select("page_id", F.length("html").cast("long").alias("html_length")),
        "benchmark": db["benchmark"].select("item_id", F.length("text").cast("long").alias("text_length")),
        "conversations": db["conversations"].select("conv_id", "turn", F.length("text").cast("long").alias("text_length")),
    }


@lru_cache(maxsize=1)
def _scratch() -> str:
    path = tempfile.mkdtemp(prefix="cardest-")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    return path


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where one machine is the whole cluster."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return _scratch()


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Written to the shared folder and read back: short plans, and nothing to recompute after a lost executor."""
    path = fresh_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
