"""Plans and queries on Spark, held against DuckDB and against the cycle without Spark."""

import ast
from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from rankspark import engine, exact, local, relational, workloads
from rankspark.params import GRID, ExecutionSpec, MethodSpec
from rankspark.streaming import workloads as streams

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PICKED = ["exact_quantiles_by_flag", "exact_bracket_price", "exact_range_total", "ranks_of_probes", "digest_quantiles_qty", "digest_merge_by_linenumber", "rsample_flat_exact", "rsample_capped_sensor", "gap_batch_z1", "gap_plain_qty", "digest_online_grow_chars", "example_digest_trees", "refresh_quantiles", "trim_p05_p95", "asof_pred_rank", "stream_window_quantiles", "stream_equals_batch", "typed_date_orders", "typed_timestamp_events", "typed_decimal_total", "typed_large_long"]


def canon(v):
    return round(v, 6) if isinstance(v, float) else str(v)[:19] if hasattr(v, "isoformat") else v


@pytest.mark.parametrize("name", PICKED)
def test_query_equals_sql(spark, name):
    query, sql = (workloads.ENTRIES | relational.ENTRIES | streams.ENTRIES)[name]
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    df = query(spark, DATA)
    mine = sorted((tuple(canon(r[c]) for c in sorted(df.columns)) for r in df.collect()), key=str)
    told = db.execute(sql)
    names = [d[0] for d in told.description]
    theirs = sorted((tuple(canon(r[names.index(c)]) for c in sorted(names)) for r in told.fetchall()), key=str)
    assert sorted(names) == sorted(df.columns) and mine == theirs


def test_spark_equals_local(spark):
    values = np.random.default_rng(1).integers(0, 1000, 5000)
    df = spark.createDataFrame([(int(v),) for v in values], "v long").coalesce(1)
    got = engine.quantiles(df, "v", GRID, "0.01", "gap").orderBy("phi_num").collect()
    assert [r["value"] for r in got] == local.run_local(values, MethodSpec.of("gap", "0.01"), 1, GRID)


def test_nulls_nan_and_empty(spark):
    df = spark.createDataFrame([(None,), (float("nan"),), (2.0,), (1.0,)], "v double")
    rows = engine.merge_summaries(engine.summarize(df, "v", MethodSpec.of("gap", "0.1"))).collect()
    assert (rows[0]["n"], rows[0]["n_null"]) == (2, 1)
    none = engine.quantiles(df.where("false"), "v", [(1, 2)], "0.1").collect()
    assert all(r["value"] is None for r in none) and exact.exact_quantiles(df.where("false"), "v", [(1, 2)]).count() == 0
    with pytest.raises(TypeError):
        engine.summarize(spark.createDataFrame([("a",)], "v string"), "v", MethodSpec.of("gap", "0.1"))


def test_plan_prunes_and_does_not_shuffle_rows(spark):
    df = spark.read.parquet(f"{DATA}/lineitem.parquet").where("l_quantity > 10")
    plan = engine.summarize(df, "l_partkey", MethodSpec.of("gap", "0.01"))._jdf.queryExecution().toString()
    physical = plan.split("== Physical Plan ==")[1]
    assert "Exchange" not in physical and "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,10.0)]" in physical
    assert "l_comment" not in physical and "ReadSchema: struct<l_partkey:bigint,l_quantity:double>" in physical


def test_grouped_many_groups(spark):
    df = spark.range(20_000).select((F.col("id") % 500).alias("g"), F.col("id").alias("v"))
    got = engine.quantiles(df, "v", [(1, 2)], "0.05", by=["g"], run=ExecutionSpec(3)).collect()
    assert len(got) == 500 and all(abs((r["value"] - r["g"]) / 500 - 20) <= 3 for r in got)


def test_same_answers_when_repeated(spark):
    df = spark.range(50_000).select(F.pmod(F.xxhash64("id"), F.lit(9973)).alias("v"))
    for method, options in (("levels", {}), ("rsample", {"total": 50_000, "nodes": 4})):
        ask = lambda: sorted(map(tuple, engine.quantiles(df, "v", GRID, "0.02", method, **options).collect()))  # noqa: E731, B023
        assert ask() == ask()


def test_generated_source(spark):
    from rankspark.sources import ZipfSource

    spark.dataSource.register(ZipfSource)
    df = spark.read.format("zipf").options(rows=10_000, exponent="1", range="1000").load()
    assert df.count() == 10_000 and df.agg(F.max("v")).first()[0] <= 1000


def test_library_never_collects_data():
    allowed = {"bench.py"}
    for p in (Path(__file__).parents[1] / "rankspark").rglob("*.py"):
        if "llm" in p.parts or p.name in allowed:
            continue
        names = [n.func.attr for n in ast.walk(ast.parse(p.read_text())) if isinstance(n, ast.Call) and isinstance(n.func, ast.Attribute)]
        assert not {"collect", "toPandas", "localCheckpoint", "crossJoin"} & set(names), p


def test_rows_are_dealt_by_place(spark):
    """A value meets several partials in any order; sorted partials are sorted and cover the whole range."""
    rows = spark.range(4000).select((F.col("id") % 5).alias("v"))
    dealt = engine.shaped(rows, "v", ExecutionSpec(4, 8, "random")).withColumn("p", F.spark_partition_id()).groupBy("v").agg(F.count_distinct("p").alias("parts"))
    assert {r["parts"] for r in dealt.collect()} == {4}
    wide = spark.range(4000).select(F.pmod(F.xxhash64("id"), F.lit(100_000)).alias("v"))
    parts = engine.shaped(wide, "v", ExecutionSpec(4, 8, "sorted")).withColumn("p", F.spark_partition_id()).groupBy("p").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.count(F.lit(1)).alias("c")).collect()
    assert len(parts) == 4 and sum(r["c"] for r in parts) == 4000 and all(r["lo"] < 30_000 and r["hi"] > 70_000 for r in parts)


def test_merge_tree_of_many_partials(spark):
    one = engine.summarize(spark.range(200, numPartitions=1), "id", MethodSpec.of("gap", "0.05"))
    many = spark.range(5000).withColumnRenamed("id", "at").join(F.broadcast(one)).withColumn("node", F.col("at")).drop("at")
    merged = engine.merge_summaries(many)
    plan = merged._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("FlatMapGroupsInArrow") == 4 and engine.NODES <= 32**4  # each level divides the nodes by fan_in
    row = merged.collect()
    assert len(row) == 1 and row[0]["n"] == 1_000_000
    assert all(abs(r["value"] - 200 * r["phi_num"] / 20) <= 0.05 * 200 + 1 for r in engine.answer(merged, GRID).collect())


def test_types_without_an_order_are_refused(spark):
    for kind in ("date", "decimal(9,2)", "timestamp"):
        with pytest.raises(TypeError):
            engine.summarize(spark.createDataFrame([], f"v {kind}"), "v", MethodSpec.of("gap", "0.1"))
    with pytest.raises(TypeError):
        engine.typed_quantiles(spark.createDataFrame([], "v string"), "v", [(1, 2)], "0.1")
    days = spark.read.parquet(f"{DATA}/orders.parquet").where("o_orderkey < 0").select(F.col("o_orderdate").cast("date").alias("v"))
    assert engine.typed_quantiles(days, "v", [(1, 2)], "0.1").collect() == []  # no rows, no summary
