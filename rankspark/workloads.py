"""The methods and the experiments as queries on the given tables, with their SQL where they have one.

Deterministic summaries return the exact value and whether their own answer is within the error: the SQL gives the exact
value and TRUE. Relational methods return their own answers, which the SQL reproduces."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from fractions import Fraction
from math import lcm

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankspark import engine, exact, theory
from rankspark.frames import digest_frame, sample_frame
from rankspark.params import DISTRIBUTION_SQL, GRID, ExecutionSpec, MethodSpec, cents, distribution, fraction
from rankspark.sources import load_table, scratch
from rankspark.synopsis import gap_tuple

ENTRIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}
PRICE, TOTAL, SPEND, QTY = "CAST(round(l_extendedprice * 100) AS BIGINT)", "CAST(round(o_totalprice * 100) AS BIGINT)", "CAST(round(value * 100) AS BIGINT)", "CAST(l_quantity AS BIGINT)"
FOUR = ExecutionSpec(partitions=4)


def entry(name: str, sql: str | None = None):
    def keep(f):
        ENTRIES[name] = (f, sql)
        return f

    return keep


#: Measured columns: table, column expression for Spark, expression for SQL.
COLUMNS: dict[str, tuple[str, Callable, str]] = {
    "price": ("lineitem", lambda: cents("l_extendedprice"), PRICE), "qty": ("lineitem", lambda: F.col("l_quantity").cast("long"), QTY),
    "partkey": ("lineitem", lambda: F.col("l_partkey"), "l_partkey"), "total": ("orders", lambda: cents("o_totalprice"), TOTAL),
    "sorted_key": ("orders", lambda: F.col("o_orderkey"), "o_orderkey"), "spend": ("events", lambda: cents("value"), SPEND),
    "chars": ("documents", lambda: F.col("n_chars"), "n_chars"), "acctbal": ("customer", lambda: cents("c_acctbal") + 100_000, "CAST(round(c_acctbal * 100) AS BIGINT) + 100000"),
    "ship": ("lineitem", lambda: F.datediff("l_shipdate", F.lit("1995-01-01")).cast("long"), "date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))"),
    **{z: ("lineitem", lambda z=z: distribution(z), DISTRIBUTION_SQL[z]) for z in ("z0", "z5", "z1")},
}


def column(spark: SparkSession, d: str, name: str, *keys: str) -> DataFrame:
    table, value, _ = COLUMNS[name]
    return load_table(spark, d, table).select(*keys, value().alias("v"))


def exact_sql(name: str, by: list[str] | None = None, phis=GRID) -> str:
    return exact.quantile_sql(COLUMNS[name][0], COLUMNS[name][2], phis, by)


# ---- exact baseline, ranks, measures


for _name in ("price", "qty", "acctbal", "ship", "z0", "z5", "z1"):
    ENTRIES[f"exact_quantiles_{_name}"] = (lambda spark, d, n=_name: exact.exact_quantiles(column(spark, d, n), "v", GRID), exact_sql(_name))
ENTRIES["exact_quantiles_by_flag"] = (lambda spark, d: exact.exact_quantiles(column(spark, d, "price", "l_returnflag"), "v", GRID, ["l_returnflag"]), exact_sql("price", ["l_returnflag"]))
ENTRIES["exact_quantiles_spend_by_type"] = (lambda spark, d: exact.exact_quantiles(column(spark, d, "spend", "event_type"), "v", GRID, ["event_type"]), exact_sql("spend", ["event_type"]))
ENTRIES["exact_range_total"] = (lambda spark, d: exact.sorted_quantiles(column(spark, d, "total"), "v", GRID), exact_sql("total"))


@entry("exact_bracket_price", exact_sql("price"))
def _bracket(spark, d):
    rows = column(spark, d, "price")
    merged = engine.merge_summaries(engine.summarize(rows, "v", MethodSpec.of("gap", "0.005"), run=FOUR), nodes=4)
    wide = engine.answer(merged, [(max(1, k * 50 - 10), 1000) for k in range(1, 20)]).select((F.expr("phi_num + 10") / 50).cast("int").alias("phi_num"), F.col("value").alias("low"))
    top = engine.answer(merged, [(k * 50 + 10, 1000) for k in range(1, 20)]).select((F.expr("phi_num - 10") / 50).cast("int").alias("phi_num"), F.col("value").alias("high"))
    return exact.bracket_quantiles(rows, "v", GRID, wide.join(top, "phi_num").withColumn("phi_den", F.lit(20)))


@entry("special_quantiles", f"SELECT min(v) AS smallest, max(v) AS largest, max(v) FILTER (r = n // 2) AS median FROM (SELECT {TOTAL} AS v, row_number() OVER (ORDER BY {TOTAL}) - 1 AS r, count(*) OVER () AS n FROM orders)")
def _special(spark, d):
    return exact.special_quantiles(column(spark, d, "total"), "v")


PROBES = [500_000, 1_000_000, 2_500_000, 5_000_000, 7_777_777]
_PROBE_SQL = f"SELECT CAST(p AS DOUBLE) AS value, count(*) FILTER (v < p) AS below, count(*) FILTER (v <= p) AS upto, count(*) AS n FROM (SELECT {PRICE} AS v FROM lineitem), (VALUES {', '.join(f'({p})' for p in PROBES)}) q(p) GROUP BY p"


def _probed(spark, d):
    return exact.ranks_of(column(spark, d, "price"), "v", spark.createDataFrame([(float(p),) for p in PROBES], "value double"))


ENTRIES["ranks_of_probes"] = (_probed, _PROBE_SQL)
_ERR_SQL = f"SELECT value, k, round(greatest(0, below - (k * n) // 20, (k * n) // 20 - greatest(upto - 1, below)) / n, 9) AS err FROM ({_PROBE_SQL}) JOIN (SELECT CAST(p AS DOUBLE) AS value, k FROM (VALUES {', '.join(f'({p}, {k})' for k, p in zip((1, 2, 5, 10, 15), PROBES, strict=True))}) v(p, k)) USING (value)"


def _probe_errors(spark, d):
    told = spark.createDataFrame([(float(p), k) for k, p in zip((1, 2, 5, 10, 15), PROBES, strict=True)], "value double, k int")
    met = _probed(spark, d).join(F.broadcast(told), "value")
    return met.select("value", "k", F.round(exact.rank_error(F.expr("k * n div 20"), F.col("below"), F.col("upto"), F.col("n")), 9).alias("err"))


ENTRIES["rank_error_of_probes"] = (_probe_errors, _ERR_SQL)
ENTRIES["avg_rank_error_probes"] = (lambda spark, d: _probe_errors(spark, d).agg(F.round(F.avg("err"), 7).alias("avg_err"), F.max("err").alias("max_err"), F.count_if(F.col("err") > 0.1).alias("violations")), f"SELECT round(avg(err), 7) AS avg_err, max(err) AS max_err, count(*) FILTER (err > 0.1) AS violations FROM ({_ERR_SQL})")
ENTRIES["eps_approx_check"] = (lambda spark, d: _probe_errors(spark, d).select("value", "k", (F.col("err") <= 0.1).alias("is_approx")), f"SELECT value, k, err <= 0.1 AS is_approx FROM ({_ERR_SQL})")


# ---- batch dyadic digest in DataFrames


QTY_EPS, PART_EPS, PART_BITS = "0.4", "0.1", 15
_leaves = digest_frame.leaves_sql("lineitem", QTY)
_qty_nodes = f"WITH {_leaves}, {digest_frame.compress_sql('l', 'd', QTY_EPS, 6)} "
_part_nodes = f"WITH {digest_frame.leaves_sql('lineitem', 'l_partkey')}, {digest_frame.compress_sql('l', 'd', PART_EPS, PART_BITS)} "
ENTRIES["digest_leaf_counts"] = (lambda spark, d: digest_frame.leaf_counts(column(spark, d, "qty"), "v"), f"WITH {_leaves} SELECT level, idx, cnt FROM l")
ENTRIES["digest_nodes_qty"] = (lambda spark, d: digest_frame.build(column(spark, d, "qty"), "v", QTY_EPS, 6), _qty_nodes + "SELECT level, idx, CAST(cnt AS BIGINT) AS cnt FROM d")
ENTRIES["digest_quantiles_qty"] = (lambda spark, d: digest_frame.answers(digest_frame.build(column(spark, d, "qty"), "v", QTY_EPS, 6), GRID), _qty_nodes + digest_frame.answers_sql("d", GRID))
ENTRIES["digest_quantiles_partkey"] = (lambda spark, d: digest_frame.answers(digest_frame.build(column(spark, d, "partkey"), "v", PART_EPS, PART_BITS), GRID), _part_nodes + digest_frame.answers_sql("d", GRID))
_parts_sql = f"WITH {digest_frame.leaves_sql('lineitem', QTY, 'l_linenumber % 4')}, {digest_frame.compress_sql('l', 'd', QTY_EPS, 6)}, a AS (SELECT 0 AS b, level, idx, sum(cnt) AS cnt FROM d GROUP BY ALL), {digest_frame.compress_sql('a', 'e', QTY_EPS, 6)} "


@entry("digest_merge_by_linenumber", _parts_sql + "SELECT level, idx, CAST(cnt AS BIGINT) AS cnt FROM e")
def _digest_merge(spark, d):
    rows = load_table(spark, d, "lineitem").select((F.col("l_linenumber") % 4).alias("b"), F.col("l_quantity").cast("long").alias("v"))
    return digest_frame.merge(digest_frame.build(rows, "v", QTY_EPS, 6, ["b"]), QTY_EPS, 6)


@entry("digest_property_check", _qty_nodes + "SELECT d.level, count(*) AS nodes, count(*) FILTER (d.level > 0 AND d.cnt > d.t) AS over, count(*) FILTER (d.level < 6 AND d.cnt + coalesce(s.cnt, 0) + coalesce(p.cnt, 0) <= d.t) AS poor FROM d LEFT JOIN d s ON s.level = d.level AND s.idx = d.idx + 1 - 2 * (d.idx % 2) LEFT JOIN d p ON p.level = d.level + 1 AND p.idx = d.idx // 2 GROUP BY 1")
def _properties(spark, d):
    return digest_frame.property_check(digest_frame.build(column(spark, d, "qty"), "v", QTY_EPS, 6), QTY_EPS, 6)


ENTRIES["digest_size_vs_bound"] = (lambda spark, d: digest_frame.build(column(spark, d, "partkey"), "v", PART_EPS, PART_BITS).agg(F.count(F.lit(1)).alias("nodes"), (F.count(F.lit(1)) <= int(theory.digest_bound(fraction(PART_EPS), PART_BITS))).alias("within_bound")), _part_nodes + f"SELECT count(*) AS nodes, count(*) <= {int(theory.digest_bound(fraction(PART_EPS), PART_BITS))} AS within_bound FROM d")
ENTRIES["digest_lossless"] = (lambda spark, d: digest_frame.answers(digest_frame.build(column(spark, d, "qty"), "v", "0.000001", 6), GRID), "SELECT phi_num, phi_den, value FROM (" + exact_sql("qty") + ")")


# ---- rank sample and plain sample in DataFrames


_KEY_SQL = "l_orderkey * 8 + l_linenumber + l_partkey * 131"
_key = lambda: F.col("l_orderkey") * 8 + F.col("l_linenumber") + F.col("l_partkey") * 131
_SENSOR_SQL = "least(length(bin(l_suppkey)), 6)"


def _sampled(name: str, node: Callable, node_sql: str, eps: str, **how) -> None:
    def run(spark, d):
        rows = load_table(spark, d, "lineitem").select(F.col("l_partkey").alias("v"), node().alias("node"), _key().alias("key"))
        return sample_frame.quantiles(rows, "v", "node", F.col("key"), eps, GRID, **how)

    ENTRIES[name] = (run, sample_frame.flat_sql("lineitem", "l_partkey", node_sql, _KEY_SQL, eps, GRID, **how))


_line, _sensor = (lambda: F.col("l_linenumber")), (lambda: F.least(F.length(F.bin("l_suppkey")), F.lit(6)))
_sampled("rsample_flat_estimated", _line, "l_linenumber", "0.01")
_sampled("rsample_flat_exact", _line, "l_linenumber", "0.01", exact=True)
_sampled("rsample_capped_sensor", _sensor, _SENSOR_SQL, "0.01", capped=True, exact=True)
_SIZES_SQL = f"SELECT node, size, sum(size) OVER () AS n, count(*) OVER () AS k FROM (SELECT {_SENSOR_SQL} AS node, count(*) AS size FROM lineitem GROUP BY 1)"


def _sensor_rows(spark, d):
    return load_table(spark, d, "lineitem").select(_sensor().alias("node"), F.col("l_partkey").alias("v"))


ENTRIES["rsample_node_caps"] = (lambda spark, d: sample_frame.rates(_sensor_rows(spark, d), "node", "0.01", capped=True).select("node", "size", F.round("p", 9).alias("p")), f"SELECT node, size, round(least(1.0, CASE WHEN size * sqrt(k) >= n THEN 1 / (0.01 * size) ELSE sqrt(k) / (0.01 * n) END), 9) AS p FROM ({_SIZES_SQL})")
ENTRIES["rsample_classes"] = (lambda spark, d: sample_frame.classes(_sensor_rows(spark, d), "node"), f"SELECT node, size, CASE WHEN size * sqrt(k) / n < 1 THEN -1 ELSE CAST(floor(log2(size * sqrt(k) / n)) AS INT) END AS cls FROM ({_SIZES_SQL})")
ENTRIES["bernoulli_quantiles"] = (lambda spark, d: sample_frame.bernoulli(load_table(spark, d, "lineitem").select(F.col("l_partkey").alias("v"), _key().alias("key")), "v", F.col("key"), 0.02, GRID), exact.quantile_sql("lineitem", "l_partkey", GRID, None, sample_frame.kept_sql(_KEY_SQL, "0.02")))


def _rsample(mode: str):
    def run(spark, d):
        rows = _sensor_rows(spark, d)
        n = rows.count()
        return engine.quantiles(rows.repartition(6, "node"), "v", GRID, "0.01", "rsample", run=ExecutionSpec(fan_in=2), mode=mode, total=n, nodes=6)

    return run


for _mode, _name in (("tree", "rsample_tree_sensor"), ("components", "rsample_components"), ("flat", "rsample_workers_flat")):
    ENTRIES[_name] = (_rsample(_mode), None)


# ---- deterministic summaries, held against the data


def _guarded(name: str, col: str, eps: str, method: str, factor: int = 1, run: ExecutionSpec = FOUR, how: dict | None = None, phis=GRID, **options) -> None:
    def ask(spark, d):
        rows = column(spark, d, col)
        return engine.guaranteed(rows, "v", phis, eps, engine.quantiles(rows, "v", phis, eps, method, run=run, how=how, **options), factor)

    ENTRIES[name] = (ask, f"SELECT phi_num, phi_den, CAST(value AS DOUBLE) AS exact_value, TRUE AS within_eps FROM ({exact_sql(col, None, phis)})")


_guarded("gap_plain_qty", "qty", "0.01", "gap", mode="plain")
_guarded("gap_mixed_price", "price", "0.01", "gap", mode="mixed")
_guarded("gap_adaptive_total", "total", "0.01", "gap", mode="adaptive")
for _z in ("z0", "z5", "z1"):
    _guarded(f"gap_batch_{_z}", _z, "0.001", "gap")
    _guarded(f"digest_batch_{_z}", _z, "0.01", "digest.batch", bits=20)
    _guarded(f"digest_online_{_z}", _z, "0.01", "digest.online")
_guarded("gap_sorted_orderkey", "sorted_key", "0.01", "gap", run=ExecutionSpec(partitions=4, order="sorted"))
_guarded("gap_min_slack_two_eps", "price", "0.01", "gap", factor=2, how={"pick": "min_slack"})
_guarded("gap_acctbal", "acctbal", "0.01", "gap")
_guarded("digest_online_partkey", "partkey", "0.01", "digest.online")
_guarded("digest_online_spend", "spend", "0.01", "digest.online")
_guarded("digest_online_grow_chars", "chars", "0.02", "digest.online")


@entry("gap_lossless", "SELECT phi_num, phi_den, value FROM (" + exact_sql("total") + ")")
def _gap_lossless(spark, d):
    """By an error below half a row, whatever their number, so that every row keeps a tuple."""
    rows = column(spark, d, "total")
    eps = min(fraction("0.000001"), Fraction(1, 2 * rows.count() + 1))
    return engine.quantiles(rows, "v", GRID, eps, "gap", run=FOUR).select("phi_num", "phi_den", F.col("value").cast("long").alias("value"))




@entry("gap_grouped_by_flag", "SELECT l_returnflag, phi_num, phi_den, n, TRUE AS within_eps FROM (" + exact_sql("price", ["l_returnflag"]) + ")")
def _grouped(spark, d):
    rows = column(spark, d, "price", "l_returnflag")
    told = engine.quantiles(rows, "v", GRID, "0.01", "gap", ["l_returnflag"], FOUR)
    lists = told.groupBy("l_returnflag").agg(F.array_sort(F.collect_list("value")).alias("vs"))
    # ranks inside each group: rows count by the number of answers not above them
    met = rows.join(F.broadcast(lists), "l_returnflag").select("l_returnflag", F.explode(F.array_distinct("vs")).alias("value"), "v")
    ranks = met.groupBy("l_returnflag", "value").agg(F.count_if(F.col("v") < F.col("value")).alias("below"), F.count_if(F.col("v") <= F.col("value")).alias("upto"), F.count(F.lit(1)).alias("total"))
    r = F.expr("phi_num * n div phi_den")
    off = F.greatest(F.lit(0), F.col("below") - r, r - F.greatest(F.col("upto") - 1, F.col("below")))
    return told.join(ranks, ["l_returnflag", "value"]).select("l_returnflag", "phi_num", "phi_den", "n", (off * 100 <= F.col("n")).alias("within_eps"))


# ---- columns of other types, by a summary that holds every value: the answers are exact, and so are the bounds of their ranks


def _typed(name: str, table: str, value: Callable, value_sql: str) -> None:
    def run(spark, d):
        return engine.typed_quantiles(load_table(spark, d, table).select(value().alias("v")), "v", GRID, "0.0000001", run=FOUR).select("phi_num", "phi_den", "value", "n", "r_lo", "r_hi")

    ENTRIES[name] = (run, f"WITH q AS ({exact.quantile_sql(table, value_sql, GRID)}), x AS (SELECT {value_sql} AS v, count(*) AS c FROM {table} GROUP BY 1) SELECT phi_num, phi_den, value, n, (SELECT CAST(sum(c) AS BIGINT) FROM x WHERE v <= value) AS r_lo, (SELECT CAST(sum(c) AS BIGINT) FROM x WHERE v <= value) AS r_hi FROM q")


_typed("typed_date_orders", "orders", lambda: F.col("o_orderdate").cast("date"), "CAST(o_orderdate AS DATE)")
_typed("typed_timestamp_events", "events", lambda: F.col("ts"), "ts")
_typed("typed_decimal_total", "orders", lambda: F.col("o_totalprice").cast("decimal(12,2)"), "CAST(o_totalprice AS DECIMAL(12,2))")
_typed("typed_large_long", "orders", lambda: F.col("o_orderkey") + F.lit(1 << 60), f"o_orderkey + {1 << 60}")


# ---- levelled buffers


@entry("levels_lossless_price", "SELECT phi_num, phi_den, value FROM (" + exact_sql("total") + ")")
def _levels_lossless(spark, d):
    """By the first error, halved from 0.0001 on, whose buffers hold all rows at their first level."""
    rows = column(spark, d, "total")
    n, eps = rows.count(), fraction("0.0001")
    while not theory.levels_hold(eps, n):
        eps /= 2
    return engine.quantiles(rows, "v", GRID, eps, "levels", run=FOUR).select("phi_num", "phi_den", F.col("value").cast("long").alias("value"))




@entry("levels_params", "SELECT CAST(den AS INT) AS den, CAST(floor(log2(den)) AS INT) AS h, CAST(floor(log2(den)) AS INT) + 1 AS b, CAST(floor(den * sqrt(log2(den))) AS INT) AS s FROM (SELECT DISTINCT count(*) AS den FROM lineitem GROUP BY l_suppkey HAVING count(*) > 1)")
def _levels_params(spark, d):
    """Height, buffers and their size for an error of one row (eps = 1 / den) in each supplier's lines."""
    sizes = load_table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).cast("int").alias("den")).where("den > 1").select("den").distinct()

    def told(batches):
        import pyarrow as pa

        for b in batches:
            rows = [(n, *theory.level_parameters(Fraction(1, n))[:3]) for n in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int32()) for i in range(4)], ["den", "h", "b", "s"])

    return sizes.mapInArrow(told, "den int, h int, b int, s int")


ENTRIES["levels_z0"] = (lambda spark, d: engine.quantiles(column(spark, d, "z0"), "v", GRID, "0.01", "levels", run=ExecutionSpec(partitions=1)), None)
ENTRIES["levels_merge_z0"] = (lambda spark, d: engine.quantiles(column(spark, d, "z0"), "v", GRID, "0.01", "levels", run=ExecutionSpec(partitions=8)), None)


# ---- worked examples


A, B = [3, 4, 0, 7, 1, 0, 0, 2, 6, 0, 2, 1, 0, 4, 2], [3, 6, 2, 3, 2, 1, 7, 3, 3, 5, 2, 3, 3, 7, 2]


_ASKED = [("A", 1, 5), ("A", 1, 2), ("B", 1, 2), ("B", 7, 10), ("AB", 1, 2)]


@entry("example_exact", f"""WITH h AS (SELECT CASE WHEN o_orderkey % 2 = 0 THEN 'A' ELSE 'B' END AS data, {TOTAL} AS value FROM orders), u AS (SELECT * FROM h UNION ALL SELECT 'AB', value FROM h),
x AS (SELECT data, value, row_number() OVER (PARTITION BY data ORDER BY value) - 1 AS r, count(*) OVER (PARTITION BY data) AS n FROM u)
SELECT data, phi_num, phi_den, value FROM x JOIN (VALUES {', '.join(map(str, _ASKED))}) p(data, phi_num, phi_den) USING (data) WHERE r = (phi_num * n) // phi_den""")
def _example(spark, d):
    """Quantiles of the orders with even keys (A), of those with odd ones (B), and of both."""
    half = load_table(spark, d, "orders").select(F.when(F.col("o_orderkey") % 2 == 0, "A").otherwise("B").alias("data"), cents("o_totalprice").alias("v"))
    rows = half.unionByName(half.withColumn("data", F.lit("AB")))
    every = exact.exact_quantiles(rows, "v", [(1, 5), (1, 2), (7, 10)], ["data"])
    return every.join(spark.createDataFrame(_ASKED, "data string, phi_num int, phi_den int"), ["data", "phi_num", "phi_den"]).select("data", "phi_num", "phi_den", "value")


@entry("example_gap_trace", f"SELECT c_mktsegment, count(*) AS weight, CAST(min({COLUMNS['acctbal'][2]}) AS DOUBLE) AS first, CAST(max({COLUMNS['acctbal'][2]}) AS DOUBLE) AS last, TRUE AS narrow, TRUE AS ranked FROM customer GROUP BY 1")
def _trace(spark, d):
    """The tuples that item by item insertion leaves for each segment: their weight, the outer ones, whether all keep the bound
    and whether the bounds of all ranks hold in the data."""
    rows = column(spark, d, "acctbal", "c_mktsegment")
    parts = engine.summarize(rows.repartition("c_mktsegment"), "v", MethodSpec.of("gap", "0.1414", mode="plain"), ["c_mktsegment"])

    def opened(batches):
        import pyarrow as pa

        from rankspark import synopsis

        for b in batches:
            for r in b.to_pylist():
                s = synopsis.unpack(r["payload"])
                (low, high), k = s.ranks(), len(s)
                yield pa.RecordBatch.from_arrays([pa.array([r["c_mktsegment"]] * k), pa.array(range(k), pa.int32()), pa.array(s.v.astype(float)), pa.array(s.g), pa.array(low), pa.array(high), pa.array((s.g + s.delta) <= max(1, s.most))], ["c_mktsegment", "pos", "value", "g", "low", "high", "narrow"])

    tuples = parts.mapInArrow(opened, "c_mktsegment string, pos int, value double, g long, low long, high long, narrow boolean")
    met = rows.join(F.broadcast(tuples), "c_mktsegment").groupBy("c_mktsegment", "pos", "value", "g", "low", "high", "narrow").agg(F.count_if(F.col("v") < F.col("value")).alias("below"), F.count_if(F.col("v") <= F.col("value")).alias("upto"))
    good = (F.col("low") <= F.col("upto")) & (F.col("high") >= F.col("below") + 1)
    return met.groupBy("c_mktsegment").agg(F.sum("g").alias("weight"), F.min_by("value", "pos").alias("first"), F.max_by("value", "pos").alias("last"), F.bool_and("narrow").alias("narrow"), F.bool_and(good).alias("ranked"))


@entry("example_gap_merge_bound", "SELECT count(*) AS weight, 2828 * count(*) // 10000 AS most, TRUE AS within FROM customer")
def _merge_bound(spark, d):
    """The tuples of two halves laid together, before any compression: the sum of their weights, and the widest against the bound."""
    half = column(spark, d, "acctbal", "c_custkey").select((F.col("c_custkey") % 2).alias("half"), "v").repartition(2, "half")
    parts = engine.summarize(half, "v", MethodSpec.of("gap", "0.1414", mode="plain"), ["half"])

    def join(table):
        import pyarrow as pa

        from rankspark import synopsis

        first, *rest = [synopsis.unpack(p) for p in table["payload"].to_pylist()]
        for other in rest:
            first._interleave(other)
        return pa.table({"weight": [int(first.g.sum())], "most": [first.most], "within": [bool((first.g + first.delta).max() <= first.most)]})

    return parts.groupBy(F.lit(0).alias("up")).applyInArrow(join, "weight long, most long, within boolean")


@entry("example_rsample_ranks", f"SELECT value, round(sum(c) OVER (ORDER BY value) * 3.0::DOUBLE, 4) AS est FROM (SELECT CAST({QTY} AS INT) AS value, count(*) AS c FROM lineitem WHERE ({_KEY_SQL}) % 3 = 0 GROUP BY 1)")
def _rank_example(spark, d):
    """Estimated ranks from a third of the rows, each of which stands for three."""
    rows = load_table(spark, d, "lineitem").where(_key() % 3 == 0).select(F.col("l_quantity").cast("int").alias("value"), F.lit(3.0).alias("step"))
    return sample_frame.global_ranks(rows)


_tree_sql = f"WITH {digest_frame.leaves_sql('lineitem', QTY + ' % 8', 'l_linenumber % 2')}, {digest_frame.compress_sql('l', 'd', '0.4', 3)}, a AS (SELECT 0 AS b, level, idx, sum(cnt) AS cnt FROM d GROUP BY ALL), {digest_frame.compress_sql('a', 'e', '0.4', 3)} "


@entry("example_digest_trees", _tree_sql + "SELECT level, CAST(idx AS INT) AS idx, CAST(cnt AS INT) AS cnt FROM e")
def _digest_example(spark, d):
    """Two trees over eight values, of the even and the odd lines, and their merge."""
    rows = load_table(spark, d, "lineitem").select((F.col("l_linenumber") % 2).alias("part"), (F.col("l_quantity").cast("long") % 8).alias("v"))
    merged = digest_frame.merge(digest_frame.build(rows, "v", "0.4", 3, ["part"]), "0.4", 3)
    return merged.select("level", F.col("idx").cast("int").alias("idx"), F.col("cnt").cast("int").alias("cnt"))


# ---- the experiments


EPS = ["0.1", "0.01", "0.001", "0.0001"]
OPTIONS: dict[str, dict] = {"gap": {}, "rsample": {"nodes": 8}, "digest.batch": {"bits": 20}, "digest.online": {}, "levels": {}}
#: The gap summary of the published experiments inserts by the mixed variant; `gap` is the mode for large data, batch.
GRID_METHODS = {**OPTIONS, "gap.mixed": {"mode": "mixed"}}
DETERMINISTIC = ("gap", "gap.mixed", "digest.batch", "digest.online")


def _kind(method: str) -> str:
    return "gap" if method == "gap.mixed" else method


def _options(method: str, n: int, parts: int) -> dict:
    return {**GRID_METHODS[method], **({"total": n, "nodes": parts} if method == "rsample" else {})}


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


KEYS = ["method", "dist", "ord", "parts", "eps"]


def _stored(df: DataFrame, name: str) -> DataFrame:
    """Written and read back; in small row groups, since readers hold one in memory."""
    path = f"{scratch(df.sparkSession)}/{name}-{uuid.uuid4().hex[:8]}"
    df.write.option("parquet.block.size", 1 << 24).parquet(path)
    return df.sparkSession.read.parquet(path)


CELL = ["dist", "ord", "parts", "spec"]


def _summaries(spark: SparkSession, d: str, cells: list[tuple[str, str]], dists: list[str], orders: list[str], parts: list[int], columns: list[str]) -> tuple[DataFrame, list, dict[str, DataFrame]]:
    """The summaries by every (method, eps), what names a cell, and the packed rows of each column. Rows are packed once for each column and order, and dealt once
    for all methods and errors. One job builds and stores all summaries, those of the fewest partials first: their tasks are the longest."""
    frames, held, pieces = [], {}, lcm(*parts)
    for dist in dists:
        rows = column(spark, d, dist)
        n = rows.count()
        for o in orders:
            with engine.batched_by_rows(spark):
                packed = held[dist] = _stored(engine.pack(rows, "v", pieces, o), "packed")
            if (there := engine.packed_count(packed)) != n:
                raise RuntimeError(f"{there} rows were packed of {n}")
            for k in parts:
                specs = [MethodSpec.of(_kind(m), e, **_options(m, n, k)) for m, e in cells]
                built = engine.summarize_each(packed, "v", specs, ExecutionSpec(k, 8, o, pieces))
                frames.append((k, built.select(F.lit(dist).alias("dist"), F.lit(o).alias("ord"), F.lit(k).alias("parts"), "spec", *columns)))
    method = F.element_at(F.array(*[F.lit(m) for m, _ in cells]), F.col("spec") + 1)
    return _stored(_union([f for _, f in sorted(frames, key=lambda x: x[0])]), "summaries"), [method.alias("method"), "dist", "ord", "parts"], held


def error_grid(spark: SparkSession, d: str, methods: list[str], epss: list[str], dists: list[str], orders: list[str], parts: list[int]) -> DataFrame:
    """method, dist, ord, parts, eps, avg_err, max_err, violations: every combination. The answers are stored, and one pass over
    each column finds their ranks."""
    columns = ["method", "node", "n", "n_null", "eps", "vmin", "vmax", "payload", "bytes"]
    built, names, held = _summaries(spark, d, [(m, e) for m in methods for e in epss], dists, orders, parts, columns)
    merged = engine.merge_summaries(built, CELL, 8, max(parts))
    answers = _stored(engine.answer(merged, GRID, CELL).select(*names, "phi_num", "phi_den", "value", "n", "eps"), "answers")
    mine = {dist: answers.where(F.col("dist") == dist) for dist in held}
    return _union([engine.errors_by(engine.packed_ranks(packed, mine[dist]), mine[dist], KEYS) for dist, packed in held.items()])


def size_grid(spark: SparkSession, d: str, methods: list[str], eps: str, dists: list[str], orders: list[str], parts: list[int]) -> DataFrame:
    """method, dist, ord, parts, total_bytes, max_bytes before merging."""
    built, names, _ = _summaries(spark, d, [(m, eps) for m in methods], dists, orders, parts, ["n", "bytes"])
    return engine.space(built.where("n > 0"), CELL).select(*names, "total_bytes", "max_bytes", "summaries")


def _within(grid: Callable[[SparkSession, str], DataFrame]):
    return lambda spark, d: grid(spark, d).select("method", "dist", "ord", "parts", F.round("eps", 6).alias("eps"), (F.col("max_err") <= F.col("eps")).alias("within_eps"))


def _within_sql(method: str, epss: list[str], dists: list[str], orders: list[str], parts: list[int]) -> str:
    vals = lambda xs: ", ".join(f"({x!r})" if isinstance(x, str) else f"({x})" for x in xs)
    return f"SELECT '{method}' AS method, dist, ord, parts, CAST(eps AS DOUBLE) AS eps, TRUE AS within_eps FROM (VALUES {', '.join(f'({e})' for e in epss)}) a(eps), (VALUES {vals(dists)}) b(dist), (VALUES {vals(orders)}) c(ord), (VALUES {vals(parts)}) e(parts)"


def _exp(name: str, method: str, epss: list[str], dists: list[str], orders: list[str], parts: list[int]) -> None:
    grid, det = lambda spark, d: error_grid(spark, d, [method], epss, dists, orders, parts), method in DETERMINISTIC
    ENTRIES[name] = (_within(grid) if det else grid, _within_sql(method, epss, dists, orders, parts) if det else None)


ORDERS, PARTS = ["sorted", "random"], [1, 2, 4, 8, 16]
for _m in GRID_METHODS:
    _short = _m.replace(".", "_")
    _eps_grid, _parts_grid = (EPS, ["z0", "z5", "z1"], ORDERS, [8]), (EPS[1:], ["z0", "z5"], ORDERS, PARTS)
    _all = ""
    if _m in DETERMINISTIC and _m in OPTIONS:  # the SQL of these two is fixed and has a part of the grid; the whole of it has queries of its own
        _exp(f"exp_eps_error_{_short}", _m, EPS[:3], ["z0", "z5", "z1"], ORDERS, [8])
        _exp(f"exp_parts_error_{_short}", _m, ["0.001"], ["z0", "z5"], ["random"], PARTS)
        _all = "_all"
    _exp(f"exp_eps_error_{_short}{_all}", _m, *_eps_grid)
    _exp(f"exp_parts_error_{_short}{_all}", _m, *_parts_grid)
    ENTRIES[f"exp_parts_size_{_short}"] = (lambda spark, d, m=_m: size_grid(spark, d, [m], "0.0001", ["z0", "z5"], ORDERS, PARTS), None)
ENTRIES["exp_compare_error"] = (lambda spark, d: error_grid(spark, d, list(GRID_METHODS), EPS, ["z0", "z5"], ["random"], [8]), None)
ENTRIES["exp_compare_size"] = (lambda spark, d: size_grid(spark, d, list(GRID_METHODS), "0.0001", ["z0", "z5"], ["random"], PARTS), None)


@entry("exp_gap_variants")
def _variants(spark, d):
    """mode, avg_err, max_err, total_bytes at eps .01, four parts."""
    rows = column(spark, d, "total")
    told, sizes = [], []
    for mode in ("batch", "mixed", "plain", "adaptive"):
        spec = MethodSpec.of("gap", "0.01", mode=mode)
        parts = engine.summarize(rows, "v", spec, run=FOUR)
        told.append(engine.answer(engine.merge_summaries(parts, nodes=4), GRID).withColumn("mode", F.lit(mode)))
        sizes.append(engine.space(parts).withColumn("mode", F.lit(mode)))
    return engine.errors(rows, "v", _union(told), ["mode"]).join(_union(sizes), "mode")


@entry("exp_digest_variants")
def _digests(spark, d):
    """Both digests, and one sweep against sweeping until nothing folds."""
    rows = column(spark, d, "z0")
    told, sizes = [], []
    for name, m, o in (("batch", "digest.batch", {"bits": 20}), ("batch.fixpoint", "digest.batch", {"bits": 20, "sweeps": "fixpoint"}), ("online", "digest.online", {})):
        parts = engine.summarize(rows, "v", MethodSpec.of(m, "0.01", **o), run=ExecutionSpec(8))
        told.append(engine.answer(engine.merge_summaries(parts, nodes=8), GRID).withColumn("mode", F.lit(name)))
        sizes.append(engine.space(parts).withColumn("mode", F.lit(name)))
    return engine.errors(rows, "v", _union(told), ["mode"]).join(_union(sizes), "mode")


_COST_SQL = "SELECT l_linenumber, k, greatest(1, CAST(floor(log2(k)) AS INT)) AS h FROM (SELECT l_linenumber, CAST(count(DISTINCT l_suppkey) AS INT) AS k FROM lineitem GROUP BY 1)"


@entry("theory_costs", f"SELECT l_linenumber, model, k, round(CASE model WHEN 'flat' THEN sqrt(k) WHEN 'tree' THEN h * sqrt(k) ELSE sqrt(k * h) END / 0.01::DOUBLE, 6) AS sent FROM ({_COST_SQL}), (VALUES ('flat'), ('tree'), ('components')) m(model)")
def _costs(spark, d):
    """Values that each form of the rank sample sends, where the suppliers of each line number are the nodes."""
    nodes = load_table(spark, d, "lineitem").groupBy("l_linenumber").agg(F.count_distinct("l_suppkey").cast("int").alias("k"))

    def told(batches):
        import pyarrow as pa

        for b in batches:
            rows = [(x, m, k, round(v, 6)) for x, k in zip(*[c.to_pylist() for c in b.columns], strict=True) for m, v in theory.tree_cost(k, max(1, k.bit_length() - 1), fraction("0.01")).items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.string(), pa.int32(), pa.float64()))], ["l_linenumber", "model", "k", "sent"])

    return nodes.mapInArrow(told, "l_linenumber int, model string, k int, sent double")


@entry("builtin_quantiles")
def _builtins(spark, d):
    """The engine's own estimators, as a yardstick."""
    rows = column(spark, d, "z0")
    grid = F.array(*[F.lit(a / b) for a, b in GRID])
    return rows.agg(F.percentile_approx("v", grid, 1000).alias("approx"), F.percentile("v", grid).alias("exact"))


# ---- incremental use, stored summaries


@entry("refresh_quantiles", f"SELECT phi_num, phi_den, CAST(value AS DOUBLE) AS exact_value, TRUE AS within_eps FROM ({exact_sql('price')})")
def _refresh(spark, d):
    rows = column(spark, d, "price", "l_shipdate")
    spec = MethodSpec.of("gap", "0.01")
    old = engine.merge_summaries(engine.summarize(rows.where("l_shipdate < '2000-01-01'"), "v", spec, run=FOUR), nodes=4)
    path = f"{scratch(spark)}/old-summary-{uuid.uuid4().hex[:8]}"
    old.write.mode("overwrite").partitionBy("method").parquet(path)
    kept = spark.read.parquet(path).select(*old.columns)
    now = engine.refresh(kept, rows.where("l_shipdate >= '2000-01-01'"), "v", spec, run=FOUR)
    return engine.guaranteed(rows, "v", GRID, "0.01", engine.answer(now, GRID))


@entry("sql_surface", "SELECT TRUE AS near_half, TRUE AS small, 4 AS grid")
def _surface(spark, d):
    from rankspark import sqlsurface

    sqlsurface.register(spark)
    rows = column(spark, d, "partkey")
    parts = engine.summarize(rows, "v", MethodSpec.of("gap", "0.01"), run=FOUR)
    parts.where("n > 0").createOrReplaceTempView("rankspark_parts")
    return spark.sql("""WITH m AS (SELECT summary_merge(payload) AS p FROM rankspark_parts), c AS (SELECT sum(n) AS n FROM rankspark_parts),
      q AS (SELECT p, n, summary_quantile(p, 1, 2) AS median FROM m CROSS JOIN c)
      SELECT abs(summary_rank(p, median) - n / 2) <= 0.02 * n AS near_half, summary_size(p) < n AS small, (SELECT CAST(count(*) AS INT) FROM phi_grid(5)) AS grid FROM q""")
