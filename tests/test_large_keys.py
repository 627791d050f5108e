"""Queries on order lines whose keys are those of a table sixty times as large."""

import duckdb
import pytest
from pyspark.sql import functions as F

from cloudlattice.plans import catalogue, regions


@pytest.fixture(scope="module")
def far(spark, sf_dir, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("far"))
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").withColumn("l_orderkey", F.col("l_orderkey") + 9_000_000)
    lines.write.parquet(f"{path}/lineitem.parquet")
    spark.read.parquet(f"{sf_dir}/part.parquet").write.parquet(f"{path}/part.parquet")
    return path


def test_scrambled_ids_of_any_size(spark):
    ids = [0, 1, 9_216_000_001, (1 << 32) - 1, 1 << 32, (1 << 62) + 12345]
    got = spark.createDataFrame([(x,) for x in ids], "pid long").select("pid", regions.scrambled(F.col("pid"))).collect()
    assert [tuple(r) for r in got] == [(x, x * 2654435761 % (1 << 32)) for x in ids]


@pytest.mark.parametrize("name", ["chunk_classes", "skip_report", "radius_interval", "radius_count_full", "radius_count_index", "radius_count_joined", "chunk_skips"])
def test_large_keys_equal_sql_without_overflow(spark, far, name):
    con = duckdb.connect()
    for t in ("lineitem", "part"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{far}/{t}.parquet/*.parquet'")
    df = catalogue.QUERIES[name](spark, far)
    columns = sorted(df.columns)
    sql = catalogue.ORACLES[name].replace("(pid * 2654435761)", "(pid::HUGEINT * 2654435761)")  # the plain product is over 64 bits here
    assert sorted(map(repr, map(tuple, df.select(*columns).collect()))) == sorted(map(repr, con.sql(f"SELECT {', '.join(columns)} FROM ({sql})").fetchall()))
