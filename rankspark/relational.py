"""The operators that users of quantiles need around them, one query each, with the SQL that checks it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rankspark import exact
from rankspark.params import cents
from rankspark.sources import load_table, round_trip

PHIS = [(1, 4), (1, 2), (3, 4)]
ENTRIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}
CENTS = "CAST(round({} * 100) AS BIGINT)"
PRICE, TOTAL, SPEND = CENTS.format("l_extendedprice"), CENTS.format("o_totalprice"), CENTS.format("value")


def entry(name: str, sql: str | None = None):
    def keep(f):
        ENTRIES[name] = (f, sql)
        return f

    return keep


def t(spark: SparkSession, d: str, *names: str):
    out = [load_table(spark, d, n) for n in names]
    return out[0] if len(out) == 1 else out


@entry("scan_lineitem", f"SELECT l_returnflag, count(*) AS rows, CAST(sum({PRICE}) AS BIGINT) AS price FROM lineitem WHERE l_shipdate < TIMESTAMP '1997-01-01' GROUP BY l_returnflag")
def _scan(spark, d):
    rows = t(spark, d, "lineitem").where(F.col("l_shipdate") < "1997-01-01")
    return rows.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("rows"), F.sum(cents("l_extendedprice")).alias("price"))


for _kind in ("csv", "json", "orc", "text"):
    ENTRIES[f"roundtrip_{_kind}"] = (
        lambda spark, d, kind=_kind: round_trip(t(spark, d, "orders").select("o_orderkey", *(["o_orderstatus"] if kind != "text" else [])), kind, "orders").groupBy(*(["o_orderstatus"] if kind != "text" else [])).agg(F.count(F.lit(1)).alias("rows"), F.sum("o_orderkey").alias("keys")),
        "SELECT o_orderstatus, count(*) AS rows, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders GROUP BY 1" if _kind != "text" else "SELECT count(*) AS rows, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders",
    )


@entry("hash_sample", "SELECT count(*) AS rows, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM lineitem WHERE ((l_orderkey % 2147483648) * 1103515245 + 12345) % 2147483648 < 107374182")
def _hash_sample(spark, d):
    from rankspark.frames.sample_frame import kept

    return t(spark, d, "lineitem").where(kept(F.col("l_orderkey"), F.lit(0.05))).agg(F.count(F.lit(1)).alias("rows"), F.sum("l_orderkey").alias("keys"))


@entry("project_cents", f"SELECT l_linenumber, CAST(sum({PRICE}) AS BIGINT) AS price, CAST(sum(CASE WHEN l_quantity > 25 THEN 1 ELSE 0 END) AS BIGINT) AS large FROM lineitem GROUP BY 1")
def _project(spark, d):
    return t(spark, d, "lineitem").select("l_linenumber", cents("l_extendedprice").alias("p"), F.when(F.col("l_quantity") > 25, 1).otherwise(0).alias("b")).groupBy("l_linenumber").agg(F.sum("p").alias("price"), F.sum("b").cast("long").alias("large"))


@entry("filter_predicates", "SELECT c_mktsegment, count(*) AS rows FROM customer WHERE (c_acctbal BETWEEN 0 AND 5000 OR c_nationkey IN (1, 2, 3)) AND NOT c_name LIKE '%9' AND c_name IS NOT NULL AND regexp_matches(c_name, '[0-9]') AND c_mktsegment IS NOT DISTINCT FROM c_mktsegment GROUP BY 1")
def _filters(spark, d):
    c = F.col
    return t(spark, d, "customer").where((c("c_acctbal").between(0, 5000) | c("c_nationkey").isin(1, 2, 3)) & ~c("c_name").like("%9") & c("c_name").isNotNull() & c("c_name").rlike("[0-9]") & c("c_mktsegment").eqNullSafe(c("c_mktsegment"))).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("rows"))


@entry("trim_p05_p95", f"WITH x AS (SELECT {PRICE} AS v, row_number() OVER (ORDER BY {PRICE}) - 1 AS r, count(*) OVER () AS n FROM lineitem), c AS (SELECT min(v) AS lo, max(v) AS hi FROM x WHERE r IN (n // 20, 19 * n // 20)) SELECT count(*) AS rows, CAST(sum(v) AS BIGINT) AS total FROM x, c WHERE v BETWEEN lo AND hi")
def _trim(spark, d):
    rows = t(spark, d, "lineitem").select(cents("l_extendedprice").alias("v"))
    cuts = exact.exact_quantiles(rows, "v", [(1, 20), (19, 20)]).agg(F.min("value").alias("lo"), F.max("value").alias("hi"))
    return rows.join(F.broadcast(cuts), F.col("v").between(F.col("lo"), F.col("hi"))).agg(F.count(F.lit(1)).alias("rows"), F.sum("v").alias("total"))


def _cut_array(rows: DataFrame) -> DataFrame:
    return exact.exact_quantiles(rows, "v", [(k, 10) for k in range(1, 10)]).agg(F.array_sort(F.collect_list("value")).alias("cuts"))  # nine values


@entry("equi_depth_histogram", f"WITH x AS (SELECT {PRICE} AS v, row_number() OVER (ORDER BY {PRICE}) - 1 AS r, count(*) OVER () AS n FROM lineitem), c AS (SELECT v AS cut FROM x, range(1, 10) k(k) WHERE r = (k * n) // 10), b AS (SELECT v, (SELECT count(*) FROM c WHERE cut <= v) AS bucket FROM x) SELECT bucket, count(*) AS rows, min(v) AS low, max(v) AS high FROM b GROUP BY 1")
def _equi_depth(spark, d):
    rows = t(spark, d, "lineitem").select(cents("l_extendedprice").alias("v"))
    bucket = F.size(F.filter("cuts", lambda c: c <= F.col("v"))).cast("long")
    return rows.join(F.broadcast(_cut_array(rows))).groupBy(bucket.alias("bucket")).agg(F.count(F.lit(1)).alias("rows"), F.min("v").alias("low"), F.max("v").alias("high"))


@entry("equi_width_histogram", "SELECT least(10, CAST(floor((l_quantity - 1) / 4.9) AS BIGINT) + 1) AS bucket, count(*) AS rows FROM lineitem GROUP BY 1")
def _equi_width(spark, d):
    return t(spark, d, "lineitem").groupBy(F.least(F.lit(10), F.width_bucket("l_quantity", F.lit(1.0), F.lit(50.0), F.lit(10))).cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("rows"))


@entry("join_orders_customer", f"SELECT c_mktsegment, count(*) AS orders, CAST(sum({TOTAL}) AS BIGINT) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _join(spark, d):
    o, c = t(spark, d, "orders", "customer")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"), F.sum(cents("o_totalprice")).alias("total"))


for _hint, _name in (("merge", "smj"), ("shuffle_hash", "shj")):
    ENTRIES[f"join_lineitem_orders_{_name}"] = (
        lambda spark, d, hint=_hint: (lambda li, o: li.join(o.hint(hint), li["l_orderkey"] == o["o_orderkey"]).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.sum(F.col("l_quantity").cast("long")).alias("qty")))(*t(spark, d, "lineitem", "orders")),
        "SELECT o_orderpriority, count(*) AS lines, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    )
for _how in ("left", "right", "full"):
    ENTRIES[f"join_outer_{_how}"] = (
        lambda spark, d, how=_how: (lambda o, c: o.where("o_orderstatus = 'F'").join(c.where("c_nationkey < 5"), F.col("o_custkey") == F.col("c_custkey"), how).agg(F.count(F.lit(1)).alias("rows"), F.count("o_orderkey").alias("orders"), F.count("c_custkey").alias("customers")))(*t(spark, d, "orders", "customer")),
        f"SELECT count(*) AS rows, count(o_orderkey) AS orders, count(c_custkey) AS customers FROM (SELECT * FROM orders WHERE o_orderstatus = 'F') o {_how.upper()} JOIN (SELECT * FROM customer WHERE c_nationkey < 5) c ON o_custkey = c_custkey",
    )
for _kind, _word in (("left_semi", ""), ("left_anti", "NOT ")):
    ENTRIES["customers_with_orders" if not _word else "customers_without_orders"] = (
        lambda spark, d, kind=_kind: (lambda c, o: c.join(o.where("o_totalprice > 400000"), F.col("o_custkey") == F.col("c_custkey"), kind).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("customers")))(*t(spark, d, "customer", "orders")),
        f"SELECT c_mktsegment, count(*) AS customers FROM customer WHERE {_word}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000) GROUP BY 1",
    )


@entry("theta_price_cutoffs", "SELECT cut, count(*) AS rows FROM lineitem, (VALUES (10), (20), (30), (40)) v(cut) WHERE l_quantity > cut GROUP BY 1")
def _theta(spark, d):
    cuts = spark.createDataFrame([(10,), (20,), (30,), (40,)], "cut int")
    return t(spark, d, "lineitem").join(F.broadcast(cuts), F.col("l_quantity") > F.col("cut")).groupBy("cut").agg(F.count(F.lit(1)).alias("rows"))


@entry("range_join_buckets", f"WITH x AS (SELECT {TOTAL} AS v, row_number() OVER (ORDER BY {TOTAL}) - 1 AS r, count(*) OVER () AS n FROM orders), c AS (SELECT k, v AS cut FROM x, range(0, 5) k(k) WHERE r = (k * n) // 5), b AS (SELECT k, cut AS lo, lead(cut) OVER (ORDER BY k) AS hi FROM c) SELECT k, lo, count(*) AS rows FROM b JOIN x ON v >= lo AND (hi IS NULL OR v < hi) GROUP BY 1, 2")
def _range_join(spark, d):
    rows = t(spark, d, "orders").select(cents("o_totalprice").alias("v"))
    cut = exact.exact_quantiles(rows, "v", [(k, 5) for k in range(5)])
    b = cut.select(F.col("phi_num").cast("long").alias("k"), F.col("value").alias("lo"), F.lead("value").over(W.Window.partitionBy("phi_den").orderBy("phi_num")).alias("hi"))
    return rows.join(F.broadcast(b), (F.col("v") >= F.col("lo")) & (F.col("hi").isNull() | (F.col("v") < F.col("hi")))).groupBy("k", "lo").agg(F.count(F.lit(1)).alias("rows"))


@entry("asof_pred_rank", "WITH s AS (SELECT l_suppkey, l_partkey AS v, count(*) OVER (PARTITION BY l_suppkey ORDER BY l_partkey RANGE UNBOUNDED PRECEDING) - 1 AS rank FROM lineitem WHERE l_linenumber = 1), q AS (SELECT DISTINCT l_suppkey, l_partkey AS x FROM lineitem WHERE l_linenumber = 2) SELECT q.l_suppkey, CAST(sum(coalesce(s.rank, -1)) AS BIGINT) AS ranks FROM q ASOF LEFT JOIN (SELECT DISTINCT * FROM s) s ON q.l_suppkey = s.l_suppkey AND q.x >= s.v GROUP BY 1")
def _asof(spark, d):
    rows = t(spark, d, "lineitem")
    by = W.Window.partitionBy("l_suppkey").orderBy("l_partkey")
    s = rows.where("l_linenumber = 1").select("l_suppkey", F.col("l_partkey").alias("x"), (F.count(F.lit(1)).over(by.rangeBetween(W.Window.unboundedPreceding, 0)) - 1).alias("rank"), F.lit(0).alias("asks"))
    q = rows.where("l_linenumber = 2").select("l_suppkey", F.col("l_partkey").alias("x"), F.lit(None).cast("long").alias("rank"), F.lit(1).alias("asks")).distinct()
    # one sorted union instead of a range join: the last rank seen is the predecessor's
    last = F.last("rank", ignorenulls=True).over(W.Window.partitionBy("l_suppkey").orderBy("x", "asks").rowsBetween(W.Window.unboundedPreceding, 0))
    return s.unionByName(q).withColumn("found", last).where("asks = 1").groupBy("l_suppkey").agg(F.sum(F.coalesce("found", F.lit(-1))).alias("ranks"))


@entry("star_price_quantiles_by_region", exact.quantile_sql(f"(SELECT r_name, {PRICE} AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)", "v", PHIS, ["r_name"]))
def _star(spark, d):
    li, o, c, n, r = t(spark, d, "lineitem", "orders", "customer", "nation", "region")
    places = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "r_name")
    rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(places, F.col("o_custkey") == F.col("c_custkey"))
    return exact.exact_quantiles(rows.select("r_name", cents("l_extendedprice").alias("v")), "v", PHIS, ["r_name"])


@entry("basic_aggregates", "SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS total, round(avg(l_quantity), 4) AS mean, min(l_quantity) AS low, max(l_quantity) AS high, round(stddev_samp(l_quantity), 4) AS spread, median(l_quantity) AS middle FROM lineitem GROUP BY 1")
def _aggregates(spark, d):
    q = "l_quantity"
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(q).cast("long").alias("total"), F.round(F.avg(q), 4).alias("mean"), F.min(q).alias("low"), F.max(q).alias("high"), F.round(F.stddev_samp(q), 4).alias("spread"), F.median(q).alias("middle"))


@entry("distinct_counts", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT (l_returnflag, l_linestatus)) AS states FROM lineitem")
def _distinct(spark, d):
    return t(spark, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_returnflag", "l_linestatus").alias("states"))


@entry("approx_distinct")
def _approx(spark, d):
    return t(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@entry("rollup_counts", "SELECT l_returnflag, l_linestatus, count(*) AS rows FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _rollup(spark, d):
    return t(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("rows"))


@entry("cube_medians", "SELECT l_returnflag, l_linestatus, median(l_quantity) AS middle, count(*) AS rows FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _cube(spark, d):
    return t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.median("l_quantity").alias("middle"), F.count(F.lit(1)).alias("rows"))


@entry("grouping_sets_counts", "SELECT l_returnflag, l_linenumber, count(*) AS rows FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber))")
def _sets(spark, d):
    return t(spark, d, "lineitem").groupingSets([["l_returnflag"], ["l_linenumber"]], "l_returnflag", "l_linenumber").agg(F.count(F.lit(1)).alias("rows"))


@entry("quantile_map_by_flag", "SELECT l_returnflag, string_agg(phi_num * 100 // phi_den || '=' || value, ',' ORDER BY phi_num * 100 // phi_den) AS quantiles FROM (" + exact.quantile_sql("lineitem", "CAST(l_quantity AS BIGINT)", PHIS, ["l_returnflag"]) + ") GROUP BY 1")
def _map(spark, d):
    q = exact.exact_quantiles(t(spark, d, "lineitem").select("l_returnflag", F.col("l_quantity").cast("long").alias("v")), "v", PHIS, ["l_returnflag"])
    m = F.map_from_entries(F.array_sort(F.collect_list(F.struct(F.expr("phi_num * 100 div phi_den").alias("q"), "value"))))
    pairs = F.transform(F.map_entries("m"), lambda e: F.concat_ws("=", e["key"].cast("string"), e["value"].cast("string")))
    return q.groupBy("l_returnflag").agg(m.alias("m")).select("l_returnflag", F.array_join(pairs, ",").alias("quantiles"))


@entry("pivot_quantiles", "SELECT l_returnflag, max(value) FILTER (phi_num = 1 AND phi_den = 4) AS q25, max(value) FILTER (phi_num = 1 AND phi_den = 2) AS q50, max(value) FILTER (phi_num = 3) AS q75 FROM (" + exact.quantile_sql("lineitem", PRICE, PHIS, ["l_returnflag"]) + ") GROUP BY 1")
def _pivot(spark, d):
    q = exact.exact_quantiles(t(spark, d, "lineitem").select("l_returnflag", cents("l_extendedprice").alias("v")), "v", PHIS, ["l_returnflag"])
    return q.withColumn("q", F.concat(F.lit("q"), F.expr("phi_num * 100 div phi_den"))).groupBy("l_returnflag").pivot("q", ["q25", "q50", "q75"]).agg(F.max("value"))


@entry("conditional_aggs", f"SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS finished, min_by(o_orderkey, ({TOTAL}, o_orderkey)) AS cheapest, max_by(o_orderkey, ({TOTAL}, o_orderkey)) AS dearest, bool_and(o_totalprice > 0) AS positive FROM orders GROUP BY 1")
def _conditional(spark, d):
    key = F.struct(cents("o_totalprice").alias("p"), "o_orderkey")
    return t(spark, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.min_by("o_orderkey", key).alias("cheapest"), F.max_by("o_orderkey", key).alias("dearest"), F.bool_and(F.col("o_totalprice") > 0).alias("positive"))


@entry("rank_functions", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_nationkey, c_custkey), v AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)")
def _ranks(spark, d):
    w, v = W.Window.partitionBy("c_mktsegment").orderBy("c_nationkey", "c_custkey"), W.Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    return t(spark, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@entry("analytic_functions", "SELECT o_orderkey, lag(o_orderkey) OVER w AS prev, lead(o_orderkey, 2) OVER w AS next2, first_value(o_orderkey) OVER w AS head, nth_value(o_orderkey, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, last_value(o_orderkey) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS tail FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _analytic(spark, d):
    w = W.Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    every, k = w.rowsBetween(W.Window.unboundedPreceding, W.Window.unboundedFollowing), "o_orderkey"
    return t(spark, d, "orders").select(k, F.lag(k).over(w).alias("prev"), F.lead(k, 2).over(w).alias("next2"), F.first(k).over(w).alias("head"), F.nth_value(k, 2).over(every).alias("second"), F.last(k).over(every).alias("tail"))


@entry("cumulative_rank_all", "SELECT l_orderkey, l_linenumber, CAST(sum(CAST(l_quantity AS BIGINT)) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey RANGE UNBOUNDED PRECEDING) AS BIGINT) AS upto, count(*) OVER (PARTITION BY l_suppkey ORDER BY l_quantity RANGE UNBOUNDED PRECEDING) - 1 AS rank FROM lineitem")
def _cumulative_all(spark, d):
    """Frames over all rows of a supplier."""
    w = W.Window.partitionBy("l_suppkey")
    return t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.sum(F.col("l_quantity").cast("long")).over(w.orderBy("l_orderkey").rangeBetween(W.Window.unboundedPreceding, 0)).alias("upto"), (F.count(F.lit(1)).over(w.orderBy("l_quantity").rangeBetween(W.Window.unboundedPreceding, 0)) - 1).alias("rank"))


@entry("moving_median", f"SELECT event_id, median({SPEND}) OVER (PARTITION BY event_type ORDER BY event_id ROWS 4 PRECEDING) AS middle FROM events")
def _moving(spark, d):
    w = W.Window.partitionBy("event_type").orderBy("event_id").rowsBetween(-4, 0)
    return t(spark, d, "events").select("event_id", F.percentile(cents("value"), F.lit(0.5)).over(w).alias("middle"))


@entry("top_k_orders", f"SELECT o_orderkey, {TOTAL} AS total FROM orders ORDER BY total DESC NULLS LAST, o_orderkey LIMIT 20 OFFSET 5")
def _top(spark, d):
    return t(spark, d, "orders").select("o_orderkey", cents("o_totalprice").alias("total")).orderBy(F.desc_nulls_last("total"), "o_orderkey").offset(5).limit(20)


@entry("top_k_per_segment", f"SELECT c_mktsegment, c_custkey, r FROM (SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY {CENTS.format('c_acctbal')} DESC, c_custkey) AS r FROM customer) WHERE r <= 3")
def _top_each(spark, d):
    w = W.Window.partitionBy("c_mktsegment").orderBy(F.desc(cents("c_acctbal")), "c_custkey")
    return t(spark, d, "customer").select("c_mktsegment", "c_custkey", F.row_number().over(w).alias("r")).where("r <= 3")


@entry("sorted_partitions", "SELECT count(*) AS rows, TRUE AS increasing FROM orders")
def _sorted_parts(spark, d):
    rows = t(spark, d, "orders").select("o_totalprice").repartitionByRange(8, "o_totalprice").sortWithinPartitions("o_totalprice").withColumn("part", F.spark_partition_id())
    ends = rows.groupBy("part").agg(F.count(F.lit(1)).alias("c"), F.min("o_totalprice").alias("lo"), F.max("o_totalprice").alias("hi"))
    ends = ends.withColumn("before", F.lag("hi").over(W.Window.partitionBy(F.lit(1)).orderBy("part")))  # eight rows
    return ends.agg(F.sum("c").alias("rows"), F.bool_and(F.coalesce(F.col("before") <= F.col("lo"), F.lit(True))).alias("increasing"))


@entry("union_keys_all", "SELECT k, count(*) AS rows FROM (SELECT l_suppkey AS k FROM lineitem UNION ALL SELECT s_suppkey FROM supplier) GROUP BY k")
def _union_all(spark, d):
    """A union over all rows of both tables."""
    li, s = t(spark, d, "lineitem", "supplier")
    return li.select(F.col("l_suppkey").alias("k")).unionByName(s.select(F.col("s_suppkey").alias("k"))).groupBy("k").agg(F.count(F.lit(1)).alias("rows"))


@entry("intersect_keys", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT c_custkey FROM customer WHERE c_nationkey < 10")
def _intersect(spark, d):
    o, c = t(spark, d, "orders", "customer")
    return o.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k")).intersect(c.where("c_nationkey < 10").select("c_custkey"))


@entry("except_keys", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'")
def _except(spark, d):
    o, c = t(spark, d, "orders", "customer")
    return c.select(F.col("c_custkey").alias("k")).subtract(o.where("o_orderstatus = 'F'").select("o_custkey"))


@entry("except_all_keys", "SELECT l_suppkey AS k FROM lineitem WHERE l_linenumber = 1 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_linenumber = 2")
def _except_all(spark, d):
    li = t(spark, d, "lineitem")
    return li.where("l_linenumber = 1").select(F.col("l_suppkey").alias("k")).exceptAll(li.where("l_linenumber = 2").select("l_suppkey"))


@entry("drop_duplicate_rows", "SELECT DISTINCT l_returnflag, l_linestatus, l_linenumber FROM lineitem")
def _dedupe(spark, d):
    return t(spark, d, "lineitem").select("l_returnflag", "l_linestatus", "l_linenumber").dropDuplicates()


@entry("string_functions", "SELECT c_custkey, length(c_name) AS size, substring(c_name, 1, 4) AS head, split_part(c_name, '#', 2) AS tail, upper(c_name) AS big, concat_ws('-', c_mktsegment, c_custkey) AS tag, regexp_extract(c_name, '([0-9]+)', 1) AS digits FROM customer")
def _strings(spark, d):
    n = "c_name"
    return t(spark, d, "customer").select("c_custkey", F.length(n).alias("size"), F.substring(n, 1, 4).alias("head"), F.coalesce(F.get(F.split(n, "#"), F.lit(1)), F.lit("")).alias("tail"), F.upper(n).alias("big"), F.concat_ws("-", "c_mktsegment", F.col("c_custkey").cast("string")).alias("tag"), F.regexp_extract(n, "([0-9]+)", 1).alias("digits"))


@entry("math_functions", "SELECT l_linenumber, CAST(sum(floor(l_quantity / 7)) AS BIGINT) AS f, CAST(sum(ceil(l_quantity / 7)) AS BIGINT) AS c, round(sum(log2(l_quantity)), 3) AS l, round(sum(sqrt(l_quantity)), 3) AS s, CAST(sum(1::BIGINT << l_linenumber) AS BIGINT) AS b, max(greatest(l_partkey, l_suppkey)) AS g, CAST(sum(abs(l_partkey - l_suppkey)) AS BIGINT) AS a FROM lineitem GROUP BY 1")
def _math(spark, d):
    q = F.col("l_quantity")
    return t(spark, d, "lineitem").groupBy("l_linenumber").agg(F.sum(F.floor(q / 7)).alias("f"), F.sum(F.ceil(q / 7)).alias("c"), F.round(F.sum(F.log2(q)), 3).alias("l"), F.round(F.sum(F.sqrt(q)), 3).alias("s"), F.sum(F.expr("shiftleft(1L, l_linenumber)")).alias("b"), F.max(F.greatest("l_partkey", "l_suppkey")).alias("g"), F.sum(F.abs(F.col("l_partkey") - F.col("l_suppkey"))).alias("a"))


@entry("array_functions", "SELECT vec_id, len(embedding) AS dim, round(CAST(list_sort(embedding)[1] AS DOUBLE), 5) AS low, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def _arrays(spark, d):
    e = "embedding"
    return t(spark, d, "embeddings").select("vec_id", F.size(e).cast("long").alias("dim"), F.round(F.get(F.sort_array(e), F.lit(0)).cast("double"), 5).alias("low"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


@entry("null_functions", "SELECT count(*) AS rows, count(nullif(l_linenumber, 1)) AS later, CAST(sum(coalesce(nullif(l_linenumber, 1), 100)) AS BIGINT) AS total FROM lineitem")
def _nulls(spark, d):
    n = F.nullif(F.col("l_linenumber"), F.lit(1))
    return t(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("rows"), F.count(n).alias("later"), F.sum(F.coalesce(n, F.lit(100))).alias("total"))


@entry("hash_functions", "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS s FROM customer")
def _hashes(spark, d):
    return t(spark, d, "customer").select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s"))


def quantile_entry(name: str, table: str, value_sql: str, value: Callable, by: list[str] | None = None, keys: Callable | None = None, key_sql: str = "", where: str | None = None, where_sql: str = "TRUE"):
    """An exact quantile query over one table, by keys that both engines compute."""
    inner = f"(SELECT {key_sql + ', ' if key_sql else ''}{value_sql} AS v FROM {table} WHERE {where_sql})"

    def run(spark, d):
        rows = t(spark, d, table)
        rows = rows.where(where) if where else rows
        return exact.exact_quantiles(rows.select(*(keys() if keys else by or []), value().alias("v")), "v", PHIS, by)

    ENTRIES[name] = (run, exact.quantile_sql(inner, "v", PHIS, by))


quantile_entry("price_quantiles_by_month", "lineitem", PRICE, lambda: cents("l_extendedprice"), ["month"], lambda: [F.date_format(F.date_trunc("month", "l_shipdate"), "yyyy-MM").alias("month")], "strftime(l_shipdate, '%Y-%m') AS month")
quantile_entry("price_quantiles_by_weekday", "lineitem", PRICE, lambda: cents("l_extendedprice"), ["day"], lambda: [(F.dayofweek("l_shipdate") - 1).alias("day")], "CAST(dayofweek(l_shipdate) AS INT) AS day")
quantile_entry("purchase_quantiles_by_day", "events", SPEND, lambda: cents("value"), ["day"], lambda: [F.date_format("ts", "yyyy-MM-dd").alias("day")], "strftime(ts, '%Y-%m-%d') AS day", "event_type = 'purchase'", "event_type = 'purchase'")
quantile_entry("text_length_quantiles", "documents", "length(text)", lambda: F.length("text").cast("long"), ["lang"], None, "lang")
quantile_entry("props_k_quantiles", "events", "CAST(json_extract_string(props, '$.k') AS BIGINT)", lambda: F.get_json_object("props", "$.k").cast("long"), ["event_type"], None, "event_type", None, "json_extract_string(props, '$.k') IS NOT NULL")
quantile_entry("spend_quantiles_by_user", "events", SPEND, lambda: cents("value"), ["user_id"], None, "user_id")


@entry("shop_quantiles_by_segment", exact.quantile_sql(f"(SELECT c_mktsegment, {TOTAL} AS v FROM orders JOIN customer ON o_custkey = c_custkey)", "v", PHIS, ["c_mktsegment"]))
def _shop(spark, d):
    o, c = t(spark, d, "orders", "customer")
    return exact.exact_quantiles(o.join(c, F.col("o_custkey") == F.col("c_custkey")).select("c_mktsegment", cents("o_totalprice").alias("v")), "v", PHIS, ["c_mktsegment"])


@entry("shipping_delay_quantiles", exact.quantile_sql("(SELECT l_returnflag, date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey)", "v", PHIS, ["l_returnflag"]))
def _delay(spark, d):
    li, o = t(spark, d, "lineitem", "orders")
    return exact.exact_quantiles(li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("l_returnflag", F.datediff("l_shipdate", "o_orderdate").cast("long").alias("v")), "v", PHIS, ["l_returnflag"])


@entry("embedding_coord_quantiles_all", exact.quantile_sql("(SELECT i, CAST(floor(x * 1000000) AS BIGINT) AS v FROM (SELECT unnest(range(0, len(embedding))) AS i, unnest(embedding) AS x FROM embeddings))", "v", PHIS, ["i"]))
def _coords_all(spark, d):
    """Every component of the vectors."""
    rows = t(spark, d, "embeddings").select(F.posexplode("embedding").alias("i", "x"))
    return exact.exact_quantiles(rows.select(F.col("i").cast("long").alias("i"), F.floor(F.col("x") * F.lit(1000000).cast("float")).cast("long").alias("v")), "v", PHIS, ["i"])
