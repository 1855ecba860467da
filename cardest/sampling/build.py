"""One sample table per alias, drawn so that rows with the same index are a uniform draw from the product of the tables.

Draw ``i`` of alias ``a`` depends on seed, alias and ``i`` alone: retries, partitionings and other engines agree, streams
of different aliases are independent, and a sample of size s is the beginning of any larger one.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.functions.rng import draws, u60
from cardest.query.normalize import QueryClass
from cardest.sources import stored
from cardest.theory import capacity

#: Draws that are broadcast to the scan (16 bytes each); beyond, table and draws are joined by a shuffle.
BROADCAST_DRAWS = 4_000_000
INDEX = "sampleindex"


@dataclass
class SampleDB:
    """Samples by alias with what is needed to read estimates off them."""

    tables: dict[str, DataFrame]
    sizes: dict[str, int]  # rows of the base table
    s: int
    seed: int
    source: dict[str, str] = field(default_factory=dict)  # alias to table name
    qclass: QueryClass | None = None
    delta: float = 0.05
    c: float = capacity.C
    replacement: bool = True
    exact: frozenset[str] = frozenset()  # aliases whose sample is the whole table

    def prefix(self, s: int) -> SampleDB:
        """The sample of the first ``s`` draws: one build serves a whole sweep of sizes."""
        if s > self.s:
            raise ValueError(f"the sample has {self.s} draws")
        return replace(self, tables={a: df.where(F.col(INDEX) <= s) for a, df in self.tables.items()}, s=s)

    def kept(self) -> SampleDB:
        """The sample written to the shared folder: drawn once, however many estimates read it."""
        return replace(self, tables={a: stored(df, "sample") for a, df in self.tables.items()})

    def cached(self) -> SampleDB:
        for df in self.tables.values():
            df.cache()
        return self

    def eps(self) -> float | None:
        """Guarantee of the declared class at this size, by the smallest proved bound; None without a class."""
        return None if self.qclass is None else capacity.eps_for_sample(self.s, capacity.best_bound(self.qclass)[0], self.delta, self.c)


def draw_by_key(df: DataFrame, key: str, population: int, s: int, seed: int, alias: str) -> DataFrame:
    """Draws of a table whose ``key`` is its row position (dense, from 0): one scan, the draws are broadcast to it."""
    d = draws(df.sparkSession, s, seed, alias, population)
    d = F.broadcast(d) if s <= BROADCAST_DRAWS else d
    return df.join(d, df[key] == d["pos"]).drop("pos")


def ranked(df: DataFrame, order: list[str]) -> DataFrame:
    """Adds ``pos``, the row's place from 0 in the order of columns, which should be total. No task sorts more than its range.

    Rows are parted by range and sorted within the parts; the sizes of the parts, one row each, give every part its start.
    """
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranged = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    return numbered(stored(placed(ranged), "ranked"))[0]


def placed(df: DataFrame) -> DataFrame:
    """Adds a row's partition, ``__p``, and its place there, ``__i``."""
    return df.withColumn("__p", F.spark_partition_id()).withColumn("__i", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))


def numbered(df: DataFrame) -> tuple[DataFrame, int]:
    """``df`` with ``pos`` instead of partition and place, and its number of rows."""
    counts = df.groupBy("__p").count().orderBy("__p").collect()  # one row per partition
    base, offsets = 0, []
    for r in counts:
        offsets.append((r["__p"], base))
        base += r["count"]
    starts = F.broadcast(df.sparkSession.createDataFrame(offsets, "__p int, __base long"))
    return df.join(starts, "__p").withColumn("pos", F.col("__base") + F.col("__i")).drop("__p", "__i", "__base"), base


def at_positions(df: DataFrame, population: int, s: int, seed: int, alias: str) -> DataFrame:
    """The draws of a table that has its positions in ``pos``."""
    if population == 0:
        return df.drop("pos").withColumn(INDEX, F.lit(0).cast("long")).limit(0)
    d = draws(df.sparkSession, s, seed, alias, population)
    return df.join(F.broadcast(d) if s <= BROADCAST_DRAWS else d, "pos").drop("pos")


def draw_by_rank(df: DataFrame, order: list[str], s: int, seed: int, alias: str) -> DataFrame:
    """Positions by a total order of columns, for tables without a dense key whose draws must not depend on their files."""
    return at_positions(ranked(df, order), df.count(), s, seed, alias)


def draw_by_file_row(spark: SparkSession, path: str, s: int, seed: int, alias: str, columns: list[str] | None = None) -> DataFrame:
    """Draws by place in files: row counts per file, draws mapped to (file, row) by prefix sums, only hit files read.

    The counts are one small row per file; at most ``s`` files are opened, however large the table.
    """
    counts = spark.read.parquet(path).groupBy(F.col("_metadata.file_path").alias("file")).count().toPandas().sort_values("file", ignore_index=True)
    ends = np.cumsum(counts["count"].to_numpy(dtype=np.int64))
    if len(ends) == 0:
        return spark.read.parquet(path).withColumn(INDEX, F.lit(0).cast("long")).limit(0)
    starts = spark.sparkContext.broadcast(ends - counts["count"].to_numpy(dtype=np.int64))

    @F.pandas_udf("struct<file int, row long>")
    def place(pos: pd.Series) -> pd.DataFrame:
        f = np.searchsorted(starts.value, pos.to_numpy(), side="right") - 1
        return pd.DataFrame({"file": f.astype("int32"), "row": pos.to_numpy() - starts.value[f]})

    d = draws(spark, s, seed, alias, int(ends[-1])).select(INDEX, place("pos").alias("at")).select(INDEX, F.col("at.file").alias("__f"), F.col("at.row").alias("__r"))
    hit = [r[0] for r in d.select("__f").distinct().collect()]  # at most one per file
    files = spark.createDataFrame([(int(f), counts["file"][f]) for f in hit], "__f int, __file string")
    d = F.broadcast(d.join(F.broadcast(files), "__f").drop("__f")) if s <= BROADCAST_DRAWS else d.join(files, "__f").drop("__f")
    rows = spark.read.parquet(*[counts["file"][f] for f in hit])
    rows = rows.select(*(columns or rows.columns), F.col("_metadata.file_path").alias("__path"), F.col("_metadata.row_index").alias("__row"))
    return rows.join(d, (F.col("__path") == F.col("__file")) & (F.col("__row") == F.col("__r"))).drop("__path", "__row", "__file", "__r")


def draw_by_partition(df: DataFrame, s: int, seed: int, alias: str) -> DataFrame:
    """Draws from any deterministic input: rows per partition, then place in the partition. Two passes."""
    return at_positions(*numbered(placed(df)), s, seed, alias)


def without_replacement(df: DataFrame, s: int, seed: int, alias: str, key: list[str]) -> DataFrame:
    """The ``s`` rows with the smallest hash, indexed in that order: distinct rows, one pass, bounded heaps."""
    h = u60(seed, alias, *[F.col(k) for k in key])
    low = df.withColumn("__h", h).orderBy("__h", *key).limit(s)
    return low.withColumn(INDEX, F.row_number().over(W.orderBy("__h", *key)).cast("long")).drop("__h")


def bernoulli_sample(df: DataFrame, fraction: float, seed: int) -> DataFrame:
    """Every row with the same chance: a random number of rows and no index, so no estimate of a product."""
    return df.sample(False, fraction, seed)


def create_sample(
    db: dict[str, DataFrame], aliases: dict[str, str], s: int, seed: int, keys: dict[str, str | list[str]], columns: dict[str, list[str]] | None = None, replacement: bool = True, sizes: dict[str, int] | None = None, method: str = "rank"
) -> SampleDB:
    """``s`` draws of every alias. ``keys`` has per table its dense key, or a list of columns in total order.

    Only ``columns`` of a table (all by default) and the index are kept. Sizes are counted unless given; a table is
    counted and, without a dense key, ranked once, however many aliases it has. ``method`` is for tables without a dense key:
    ``rank`` sorts them in parallel and draws the same rows whatever the files; ``partition`` takes rows as the scan gives
    them, reads the wanted columns alone and moves nothing.
    """
    sizes = dict(sizes or {})
    by_rank: dict[str, DataFrame] = {}
    if method not in ("rank", "partition"):
        raise ValueError(f"no such method: {method}")
    tables: dict[str, DataFrame] = {}
    for a, t in aliases.items():
        df = db[t]
        if t not in sizes:
            sizes[t] = df.count()
        key = keys[t]
        if columns and t in columns:
            order = [key] if isinstance(key, str) else key if method == "rank" or not replacement else []
            df = df.select(*dict.fromkeys([*columns[t], *order]))
        if sizes[t] == 0:
            tables[a] = df.withColumn(INDEX, F.lit(0).cast("long")).limit(0)
        elif not replacement:
            tables[a] = without_replacement(df, s, seed, a, [key] if isinstance(key, str) else key)
        elif isinstance(key, str):
            tables[a] = draw_by_key(df, key, sizes[t], s, seed, a)
        else:
            if t not in by_rank:
                by_rank[t] = ranked(df, key) if method == "rank" else numbered(placed(df))[0]
            tables[a] = at_positions(by_rank[t], sizes[t], s, seed, a)
    return SampleDB(tables, {a: sizes[t] for a, t in aliases.items()}, s, seed, dict(aliases), replacement=replacement)


def create_sample_for(db: dict[str, DataFrame], aliases: dict[str, str], qclass: QueryClass, eps: float, delta: float, seed: int, keys: dict, relative_p: float | None = None, whole: tuple[str, ...] = (), **more) -> SampleDB:
    """A sample whose size follows from the class by the smallest proved bound, absolute or relative.

    A one-table class on a table that is smaller than the theorem's size gets the table itself, marked exact. Aliases in
    ``whole`` always get it, however large the table: all rows stand for themselves, so no estimate is needed.
    """
    d, _ = capacity.best_bound(qclass)
    s = capacity.sample_size(d, eps, delta) if relative_p is None else capacity.relative_sample_size(d, relative_p, eps, delta)
    exact = frozenset()
    if whole and qclass.u != 1:
        raise ValueError("only one-table classes keep a table whole")
    if qclass.u == 1:
        exact = frozenset(a for a, t in aliases.items() if a in whole or db[t].count() <= s)
    out = create_sample(db, {a: t for a, t in aliases.items() if a not in exact}, s, seed, keys, **more)
    for a in exact:
        t = aliases[a]
        key = keys[t]
        if isinstance(key, str):
            rows = db[t].withColumn(INDEX, (F.col(key) + 1).cast("long"))
        else:
            rows = ranked(db[t], key).withColumn(INDEX, F.col("pos") + 1).drop("pos")
        out.tables[a], out.sizes[a], out.source[a] = rows, db[t].count(), t
    return replace(out, qclass=qclass, delta=delta, exact=exact)


def product_sample(db: dict[str, DataFrame], aliases: dict[str, str], s: int, seed: int, keys: dict[str, str]) -> DataFrame:
    """Uniform draws from the Cartesian product itself, one wide row each: what the indexed samples stand in for."""
    sdb = create_sample(db, aliases, s, seed, keys)
    out = None
    for a, df in sdb.tables.items():
        wide = df.select(INDEX, *[F.col(c).alias(f"{a}__{c}") for c in df.columns if c != INDEX])
        out = wide if out is None else out.join(wide, INDEX)
    return out


def deterministic_1d(df: DataFrame, col: str, eps: float) -> DataFrame:
    """Every ceil(eps n)-th value in order: each prefix or suffix of the column is off by eps at most, for certain."""
    steps = int(np.ceil(1 / eps))
    return df.agg(F.percentile(col, F.lit([(i + 0.5) / steps for i in range(steps)])).alias("v")).select(F.posexplode("v").alias("i", "value"))
