"""Exact quantiles and ranks, the baseline and the yardstick.

Values are counted first (map-side), so ties never meet as rows. The counts are dealt to buckets by approximate
cut-points, bucket totals give offsets, and only the bucket that holds a target is searched. No window spans all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

CUTS = 64


def phi_rows(df: DataFrame, phis: list[tuple[int, int]]) -> DataFrame:
    return df.sparkSession.createDataFrame([(a, b) for a, b in phis], "phi_num int, phi_den int")


def exact_quantiles(df: DataFrame, value: str, phis: list[tuple[int, int]], by: list[str] | None = None, cuts: int = CUTS) -> DataFrame:
    """by..., phi_num, phi_den, value, n: the element at place floor(phi n) of each group."""
    by = by or []
    counts = df.where(F.col(value).isNotNull()).groupBy(*by, F.col(value).alias("value")).agg(F.count(F.lit(1)).alias("c"))
    cut_points = counts.agg(F.percentile_approx("value", F.array(*[F.lit(k / cuts) for k in range(1, cuts)])).alias("cut"))  # one row of constant size
    dealt = counts.join(F.broadcast(cut_points)).withColumn("bucket", F.size(F.filter(F.coalesce("cut", F.array().cast(counts.select(F.array("value")).schema[0].dataType)), lambda p: p <= F.col("value")))).drop("cut")
    totals = dealt.groupBy(*by, "bucket").agg(F.sum("c").alias("t"))
    group = W.Window.partitionBy(*by) if by else W.Window.partitionBy(F.lit(1))  # totals: at most `cuts` rows a group
    totals = totals.withColumn("n", F.sum("t").over(group)).withColumn("start", F.sum("t").over(group.orderBy("bucket").rowsBetween(W.Window.unboundedPreceding, 0)) - F.col("t"))
    wanted = totals.join(F.broadcast(phi_rows(df, phis))).withColumn("r", F.least(F.expr("phi_num * n div phi_den"), F.col("n") - 1)).where("start <= r and r < start + t")
    inside = W.Window.partitionBy(*by, "bucket").orderBy("value").rowsBetween(W.Window.unboundedPreceding, 0)
    running = dealt.join(wanted.select(*by, "bucket").distinct(), [*by, "bucket"], "left_semi").withColumn("upto", F.sum("c").over(inside))
    found = running.join(wanted, [*by, "bucket"]).where("start + upto - c <= r and r < start + upto")
    return found.select(*by, "phi_num", "phi_den", "value", "n")


def sorted_quantiles(df: DataFrame, value: str, phis: list[tuple[int, int]]) -> DataFrame:
    """Sort and pick: values dealt by range, sorted in their partitions, offsets from the partitions' sizes."""
    rows = df.where(F.col(value).isNotNull()).select(F.col(value).alias("value"))
    cut = rows.agg(F.percentile_approx("value", F.array(*[F.lit(k / CUTS) for k in range(1, CUTS)])).alias("cut"))
    dealt = rows.join(F.broadcast(cut)).select("value", F.size(F.filter("cut", lambda p: p <= F.col("value"))).alias("part"))
    sizes = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("t"))
    one = W.Window.partitionBy(F.lit(1))
    offsets = sizes.select("part", "t", F.sum("t").over(one).alias("n"), (F.sum("t").over(one.orderBy("part").rowsBetween(W.Window.unboundedPreceding, 0)) - F.col("t")).alias("start"))
    wanted = offsets.join(F.broadcast(phi_rows(df, phis))).withColumn("r", F.expr("phi_num * n div phi_den")).where("start <= r and r < start + t")
    placed = dealt.join(F.broadcast(wanted.select("part").distinct()), "part", "left_semi").withColumn("at", F.row_number().over(W.Window.partitionBy("part").orderBy("value")) - 1)
    return placed.join(F.broadcast(wanted), (placed["part"] == wanted["part"]) & (F.col("at") == F.col("r") - F.col("start"))).select("phi_num", "phi_den", "value", "n")


def bracket_quantiles(df: DataFrame, value: str, phis: list[tuple[int, int]], answers: DataFrame) -> DataFrame:
    """Two passes: a summary's answers (phi_num, phi_den, low, high) bracket each quantile; rows below a bracket are counted
    and only rows inside it are sorted. `answers` has a row for each quantile."""
    rows = df.where(F.col(value).isNotNull()).select(F.col(value).alias("value"))
    met = rows.join(F.broadcast(answers), F.col("value") <= F.col("high"))  # broadcast: one row a quantile
    counts = met.groupBy("phi_num", "phi_den", F.when(F.col("value") >= F.col("low"), F.col("value")).alias("v")).agg(F.count(F.lit(1)).alias("c"))
    n = rows.agg(F.count(F.lit(1)).alias("n"))
    per = W.Window.partitionBy("phi_num", "phi_den").orderBy(F.col("v").asc_nulls_first()).rowsBetween(W.Window.unboundedPreceding, 0)
    run = counts.withColumn("upto", F.sum("c").over(per)).join(F.broadcast(n)).withColumn("r", F.expr("phi_num * n div phi_den"))
    return run.where("v is not null and upto - c <= r and r < upto").select("phi_num", "phi_den", F.col("v").alias("value"), "n")


def ranks_of(df: DataFrame, value: str, probes: DataFrame) -> DataFrame:
    """value, below, upto, n for each distinct probe: how many rows are smaller, and how many are smaller or equal.

    One pass: the sorted probes (a few hundred at most) travel as one array, rows count by the number of probes not above
    them, found among every w-th probe and then among w (their square root), and a running sum over that many counts gives ranks."""
    ordered = probes.select(F.col("value").cast("double").alias("p")).distinct().agg(F.array_sort(F.collect_set("p")).alias("ps"))
    width = F.greatest(F.lit(1), F.ceil(F.sqrt(F.size("ps"))).cast("int"))
    rows = df.where(F.col(value).isNotNull()).select(F.col(value).cast("double").alias("x")).join(F.broadcast(ordered.select("ps", width.alias("w"), F.filter("ps", lambda _, i: i % width == 0).alias("cs"))))
    rows = rows.withColumn("k", F.size(F.filter("cs", lambda p: p <= F.col("x"))))
    inside = F.filter(F.slice("ps", (F.col("k") - 1) * F.col("w") + 1, F.col("w")), lambda p: p <= F.col("x"))
    rows = rows.withColumn("b", F.when(F.col("k") > 0, (F.col("k") - 1) * F.col("w") + F.size(inside)).otherwise(0))
    bucket = F.col("b")
    hit = rows.select(bucket.alias("b"), F.coalesce(F.get("ps", bucket - 1) == F.col("x"), F.lit(False)).alias("eq"))
    counts = hit.groupBy("b").agg(F.count(F.lit(1)).alias("c"), F.count_if("eq").alias("e"))
    spots = ordered.select(F.posexplode("ps").alias("i", "value")).withColumn("b", F.col("i") + 1).join(counts.withColumnRenamed("b", "k"), F.col("k") <= F.col("b"), "left")
    total = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"))
    by = spots.groupBy("value", "b").agg(F.coalesce(F.sum(F.when(F.col("k") < F.col("b"), F.col("c"))), F.lit(0)).alias("below"), F.coalesce(F.sum(F.when(F.col("k") == F.col("b"), F.col("e"))), F.lit(0)).alias("same"))
    return by.join(F.broadcast(total)).select("value", "below", (F.col("below") + F.col("same")).alias("upto"), "n")


def special_quantiles(df: DataFrame, value: str) -> DataFrame:
    median = exact_quantiles(df, value, [(1, 2)]).select(F.col("value").alias("median"))
    return df.agg(F.min(value).alias("smallest"), F.max(value).alias("largest")).join(F.broadcast(median))


def quantile_sql(table: str, value: str, phis: list[tuple[int, int]], by: list[str] | None = None, where: str = "TRUE") -> str:
    """The same by sorting, for DuckDB."""
    keys = "".join(f"{b}, " for b in by or [])
    part = f"PARTITION BY {', '.join(by)}" if by else ""
    grid = ", ".join(f"({a}, {b})" for a, b in phis)
    return f"""WITH x AS (SELECT {keys}{value} AS value, row_number() OVER ({part} ORDER BY {value}) - 1 AS r, count(*) OVER ({part}) AS n FROM {table} WHERE {where}),
p AS (SELECT * FROM (VALUES {grid}) v(phi_num, phi_den)) SELECT {keys}phi_num, phi_den, value, n FROM x, p WHERE r = (phi_num * n) // phi_den"""


def rank_error(row_rank: Column, below: Column, upto: Column, n: Column) -> Column:
    """Distance of the wanted place to the places that the answer holds, as a share of n; 0 inside."""
    return F.greatest(F.lit(0), below - row_rank, row_rank - F.greatest(upto - 1, below)) / n
