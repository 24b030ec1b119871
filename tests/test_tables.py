"""Queries that must hold at any number of rows, and that must read the tables they are given."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as driver

DATA = "/root/testdata/sf0.001"


def equals_sql(spark, name, folder, *tables):
    df, db = driver.queries()[name](spark, str(folder)), duckdb.connect()
    for t in tables:
        db.execute(f"create view {t} as select * from '{folder}/{t}.parquet{'/*.parquet' if str(folder) != DATA else ''}'")
    told = db.execute(f"select {', '.join(df.columns)} from ({driver.oracle_sql()[name]})").fetchall()
    mine = [tuple(r) for r in df.collect()]
    assert sorted(mine, key=str) == sorted(told, key=str) and mine
    return df


@pytest.fixture(scope="module")
def many_orders(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("many")
    spark.range(1_200_000).select(F.col("id").alias("o_orderkey"), (F.pmod(F.xxhash64("id"), F.lit(50_000_000)) / 100).alias("o_totalprice")).write.parquet(f"{folder}/orders.parquet")
    return folder


LOSSLESS = ["gap_lossless", "levels_lossless_price"]


@pytest.mark.parametrize("name", LOSSLESS)
def test_lossless_past_a_million_rows(spark, many_orders, name):
    equals_sql(spark, name, many_orders, "orders")


READING = ["example_digest_trees", "example_exact", "example_gap_merge_bound", "example_gap_trace", "example_rsample_ranks", "levels_params", "theory_costs"]


@pytest.mark.parametrize("name", READING)
def test_examples_read_a_table(spark, name):
    df = equals_sql(spark, name, DATA, "lineitem", "orders", "customer")
    assert "parquet" in df._jdf.queryExecution().optimizedPlan().toString().lower()
