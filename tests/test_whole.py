"""Queries that must cover the whole of what they read."""

import duckdb
import pytest

import __spark_entry__ as driver

DATA = "/root/testdata/sf0.001"


def both(spark, name):
    """The rows of a query and those of its SQL, by the same columns."""
    df = driver.queries()[name](spark, DATA)
    db = duckdb.connect()
    for t in ("supplier", "lineitem", "embeddings", "events"):
        db.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    told = db.execute(f"select {', '.join(df.columns)} from ({driver.oracle_sql()[name]})").fetchall()
    return sorted(tuple(r) for r in df.collect()), sorted(told), db


def test_every_coordinate_has_quantiles(spark):
    mine, theirs, db = both(spark, "embedding_coord_quantiles_all")
    size = db.execute("select max(len(embedding)) from embeddings").fetchone()[0]
    assert mine == theirs and {r[0] for r in mine} == set(range(size)) and size > 4


def test_frames_run_over_all_of_lineitem(spark):
    mine, theirs, db = both(spark, "cumulative_rank_all")
    assert mine == theirs and len(mine) == db.execute("select count(*) from lineitem").fetchone()[0] and max(r[1] for r in mine) >= 3


def test_union_takes_all_of_lineitem(spark):
    mine, theirs, db = both(spark, "union_keys_all")
    assert mine == theirs and sum(r[1] for r in mine) == db.execute("select (select count(*) from lineitem) + (select count(*) from supplier)").fetchone()[0]


def test_experiments_run_the_whole_grids(spark):
    mine, theirs, _ = both(spark, "exp_eps_error_gap_all")
    assert mine == theirs and {(r[1], r[2], r[4]) for r in mine} == {(z, o, e) for z in ("z0", "z5", "z1") for o in ("sorted", "random") for e in (0.1, 0.01, 0.001, 0.0001)}
    sizes = driver.queries()["exp_compare_size"](spark, DATA).select("dist", "parts").distinct().collect()
    assert {tuple(r) for r in sizes} == {(z, k) for z in ("z0", "z5") for k in (1, 2, 4, 8, 16)}
    sql = driver.oracle_sql()["exp_parts_error_gap_all"]
    told = duckdb.sql(f"select dist, ord, parts, eps from ({sql})").fetchall()
    assert {(z, o, k, e) for z in ("z0", "z5") for o in ("sorted", "random") for k in (1, 2, 4, 8, 16) for e in (0.01, 0.0001)} <= set(told)


def test_experiments_run_the_mixed_gap_summary(spark):
    from rankspark import engine, synopsis, workloads
    from rankspark.params import MethodSpec

    mine, theirs, _ = both(spark, "exp_eps_error_gap_mixed")
    assert mine == theirs and {"exp_parts_error_gap_mixed", "exp_parts_size_gap_mixed"} <= set(driver.queries())
    spec = MethodSpec.of(workloads._kind("gap.mixed"), "0.01", **workloads._options("gap.mixed", 6000, 2))
    parts = engine.summarize(workloads.column(spark, DATA, "z0"), "v", spec).collect()
    assert {synopsis.unpack(r["payload"]).mode for r in parts} == {"mixed"}


def _tongues(spark, languages, each):
    letters = [chr(0x4E00 + i) for i in range(languages)]
    rows = [(i * each + j, letters[i] * 5, f"l{i:04d}") for i in range(languages) for j in range(each)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string")


def test_language_id_learns_more_than_256_languages(spark):
    from rankspark.llm import langid

    docs = _tongues(spark, 300, 8)
    model = langid.train(docs, per_language=8)
    assert len(model.languages) == 300
    with pytest.raises(ValueError, match="values of lang"):
        langid.train(docs, most_languages=299)


def test_rank_sample_components_merge_in_two_stages(spark):
    from pyspark.sql import functions as F

    from rankspark import engine, synopsis
    from rankspark.params import GRID, ExecutionSpec, MethodSpec

    rows = spark.range(60_000).select(F.pmod(F.col("id") * 7919, F.lit(60_000)).alias("v"))
    spec, run = MethodSpec.of("rsample", "0.02", mode="components", total=60_000, nodes=12), ExecutionSpec(12, 2)
    merged = engine.merge_components(engine.summarize(rows, "v", spec, run=run), fan_in=2, nodes=12, height=4)
    row = merged.collect()
    held = synopsis.unpack(row[0]["payload"])
    assert len(row) == 1 and held.n == 60_000 and held.mode == "flat"
    assert len(held.samples) == 3 and sum(s.size for s in held.samples) == 60_000
    told = engine.quantiles(rows, "v", GRID, "0.02", "rsample", run=run, mode="components", total=60_000, nodes=12).collect()
    off = [abs(r["value"] - r["phi_num"] * 60_000 / r["phi_den"]) / 60_000 for r in told]
    assert sum(off) / len(off) <= 2 * 0.02


def test_windowed_summaries_hold_the_last_windows(spark):
    rows = driver.queries()["stream_windowed_summaries"](spark, DATA).collect()
    told = duckdb.sql(f"select strftime(ts, '%Y-%m-%d'), count(value) from '{DATA}/events.parquet' group by 1").fetchall()
    assert sorted((r["start"].strftime("%Y-%m-%d"), r["n"]) for r in rows) == sorted(told)


def test_grids_deal_rows_once_for_all_methods(spark, monkeypatch):
    from rankspark import engine, workloads

    deals, shaped = [], engine.shaped
    monkeypatch.setattr(engine, "shaped", lambda *a: (deals.append(1), shaped(*a))[1])
    rows = workloads.error_grid(spark, DATA, list(workloads.GRID_METHODS), ["0.1", "0.01"], ["z0"], ["random"], [2, 4]).collect()
    assert len(rows) == 24 and len(deals) == 2 and all(r["violations"] == 0 for r in rows if r["method"] in workloads.DETERMINISTIC)
    sizes = workloads.size_grid(spark, DATA, list(workloads.GRID_METHODS), "0.01", ["z0"], ["random"], [2, 4]).collect()
    assert len(sizes) == 12 and len(deals) == 4 and {(r["parts"], r["summaries"]) for r in sizes} == {(2, 2), (4, 4)}


def test_grids_pack_rows_once_for_all_partials(spark, monkeypatch):
    from rankspark import engine, workloads

    packs, pack = [], engine.pack
    monkeypatch.setattr(engine, "pack", lambda *a: (packs.append(a[3]), pack(*a))[1])
    before = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch")
    rows = workloads.error_grid(spark, DATA, ["gap.mixed"], ["0.01"], ["z0"], ["sorted", "random"], [1, 2, 4]).collect()
    assert sorted(packs) == ["random", "sorted"] and len(rows) == 6 and not sum(r["violations"] for r in rows)
    sizes = workloads.size_grid(spark, DATA, ["digest.online", "gap"], "0.01", ["z0"], ["random"], [1, 2, 4]).collect()
    assert len(packs) == 3 and {(r["parts"], r["summaries"]) for r in sizes} == {(1, 1), (2, 2), (4, 4)}
    assert spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch") == before


@pytest.mark.parametrize("order", ["sorted", "random"])
def test_packed_rows_hold_all_rows_and_deal_them(spark, order):
    import numpy as np
    from pyspark.sql import functions as F

    from rankspark import engine, exact
    from rankspark.params import ExecutionSpec

    rows = spark.range(5000).select(F.when(F.col("id") % 10 > 0, F.pmod(F.col("id") * 7919, F.lit(700)) - 300 + (F.col("id") == 4999).cast("long") * (1 << 40)).alias("v"))
    packed = engine.pack(rows, "v", 4, order).cache()
    real = sorted(r[0] for r in rows.where("v is not null").collect())
    read = lambda r: np.frombuffer(r["block"], r["held"]).astype(r["kind"]).tolist()
    assert engine.packed_count(packed) == 5000 and sorted(x for r in packed.collect() for x in read(r)) == real
    for k in (1, 2, 4):
        parts = engine.shaped(packed, "v", ExecutionSpec(k, 8, order, 4)).rdd.glom().map(lambda rs: [x for r in rs for x in np.frombuffer(r["block"], r["held"]).astype(r["kind"]).tolist()]).collect()
        assert len(parts) == k and min(len(p) for p in parts) > 3000 / k and sorted(x for p in parts for x in p) == real
        assert order == "random" or all(p == sorted(p) for p in parts)
    probes = [-300.0, 0.5, 17.0, 1e13]
    asked = spark.createDataFrame([(p,) for p in probes], "value double")
    theirs = exact.ranks_of(rows, "v", asked)
    assert sorted(map(tuple, engine.packed_ranks(packed, asked).collect())) == sorted(map(tuple, theirs.collect()))
