"""Samples and statistics that follow a stream of rows, and the alarm that asks for a new sample."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.functions.rng import u60
from cardest.sources import fresh_path


def as_files(events: DataFrame, parts: int = 4) -> str:
    """The table as files in time order, a stand-in for what arrives one after another; returns their folder.

    The parts are written together, so their times of writing say nothing; each is given a time after the part before it,
    which is the order in which the stream takes them.
    """
    spark = events.sparkSession
    path = fresh_path(spark, "arrivals")
    events.repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(path)
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    names = sorted(n for n in (f.getPath().getName() for f in fs.listStatus(folder)) if n.startswith("part-"))
    first = int(time.time() * 1000) - 1000 * len(names)
    for k, name in enumerate(names):
        fs.setTimes(spark._jvm.org.apache.hadoop.fs.Path(folder, name), first + 1000 * k, -1)
    return path


def read_events(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def prepare(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Event time as a timestamp (one without zone takes no watermark), with a watermark."""
    return stream.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)


def windowed(stream: DataFrame, kind: str, length: str = "1 hour", slide: str = "30 minutes", by: str = "event_type") -> DataFrame:
    window = {"tumbling": lambda: F.window("at", length), "sliding": lambda: F.window("at", length, slide), "session": lambda: F.session_window("at", length)}[kind]()
    out = stream.groupBy(window.alias("w"), by).agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("stop"), by, "n", "ids")


def dedup(stream: DataFrame, keys: list[str]) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(keys)


def drain(stream: DataFrame, mode: str, name: str) -> DataFrame:
    """Run over all that is there and return the result.

    Appended rows, as many as have arrived, go to files in the shared folder; only totals, which are rewritten, to the driver.
    """
    spark = stream.sparkSession
    if mode == "append":
        path = fresh_path(spark, name)
        query = stream.writeStream.format("parquet").option("path", path).outputMode(mode).option("checkpointLocation", fresh_path(spark, "progress")).trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", fresh_path(spark, "progress")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def each_batch(stream: DataFrame, step: Callable[[DataFrame, int], None]) -> None:
    query = stream.writeStream.foreachBatch(step).option("checkpointLocation", fresh_path(stream.sparkSession, "progress")).trigger(availableNow=True).start()
    query.awaitTermination()


def maintain_sample(stream: DataFrame, k: int, seed: int, key: str) -> DataFrame:
    """The ``k`` rows with the smallest hash seen so far, after every batch: a uniform sample without replacement.

    State is the sample alone, a new version per batch; batches merge in any grouping to the same rows.
    """
    spark = stream.sparkSession
    versions: list[str] = []

    def step(batch: DataFrame, number: int) -> None:
        rows = batch.withColumn("__h", u60(seed, "stream", F.col(key)))
        old = spark.read.parquet(versions[-1]) if versions else None
        merged = (rows if old is None else rows.unionByName(old)).dropDuplicates([key]).orderBy("__h", key).limit(k)
        path = fresh_path(spark, f"sample-v{number}")
        merged.write.parquet(path)
        versions.append(path)

    each_batch(stream, step)
    return spark.read.parquet(versions[-1])


def drift(stream: DataFrame, probes: dict[str, object], eps: float) -> list[dict]:
    """Per batch the selectivity of every probe over all rows so far, and whether any has moved by more than 2 eps since the last alarm."""
    log: list[dict] = []
    seen = {n: 0 for n in probes}
    state = {"rows": 0, "base": None}

    def step(batch: DataFrame, number: int) -> None:
        row = batch.agg(F.count("*").alias("rows"), *[F.count_if(c).alias(n) for n, c in probes.items()]).first()
        state["rows"] += row["rows"]
        for n in probes:
            seen[n] += row[n]
        now = {n: seen[n] / max(1, state["rows"]) for n in probes}
        moved = state["base"] is not None and any(abs(now[n] - state["base"][n]) > 2 * eps for n in probes)
        if state["base"] is None or moved:
            state["base"] = now
        log.append({"batch": number, "rows": state["rows"], "alarm": moved, **{n: float(now[n]) for n in probes}})

    each_batch(stream, step)
    return log


def running_counts(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Rows and value of a key so far, kept as state; the last version of a key is the total."""
    n, total = state.get if state.exists else (0, 0.0)
    for b in batches:
        n += len(b)
        total += float(b["value"].sum())
    state.update((n, total))
    yield pd.DataFrame({"event_type": [key[0]], "n": [n], "total": [total]})


def stateful_totals(stream: DataFrame) -> DataFrame:
    return stream.groupBy("event_type").applyInPandasWithState(running_counts, "event_type string, n long, total double", "n long, total double", "update", "NoTimeout")
