"""Tables that are kept whole stay so when they outgrow the theorem's size."""

import duckdb
import pytest
from pyspark.sql import functions as F

from cardest.catalog import ORACLE, QUERIES
from cardest.query import QueryClass
from cardest.sampling import build


@pytest.mark.parametrize("name", ["sample_for_class", "est_exact_small_table"])
def test_whole_table_beyond_the_size_equals_sql(spark, sf_dir, tmp_path, name):
    s = spark.read.parquet(f"{sf_dir}/supplier.parquet")
    n = s.count()
    copies = 8000 // n + 1
    s.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("s_suppkey", F.col("s_suppkey") + F.col("i") * n).drop("i").write.parquet(str(tmp_path / "supplier.parquet"))
    spark.read.parquet(f"{sf_dir}/orders.parquet").write.parquet(str(tmp_path / "orders.parquet"))
    con = duckdb.connect()
    for t in ("supplier", "orders"):
        con.execute(f"create view {t} as select * from read_parquet('{tmp_path}/{t}.parquet/*.parquet')")
    cursor = con.execute(ORACLE[name])
    order = [c[0] for c in cursor.description]
    assert sorted(tuple(r[c] for c in order) for r in QUERIES[name](spark, str(tmp_path)).collect()) == sorted(cursor.fetchall())


def test_whole_table_without_dense_key_has_every_index_once(spark):
    df = spark.createDataFrame([(i % 7, i) for i in range(50)], "a long, b long")
    sdb = build.create_sample_for({"t": df}, {"x": "t"}, QueryClass(1, 1, 1), 0.5, 0.5, 1, {"t": ["a", "b"]}, whole=("x",))
    got = sdb.tables["x"].orderBy("a", "b").collect()
    assert sdb.exact == {"x"} and [r["sampleindex"] for r in got] == list(range(1, 51))
