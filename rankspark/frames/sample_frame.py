"""The rank sample and the Bernoulli sample as plain DataFrames. Sampling is a hash filter in the scan, so it can be replayed
in any engine; only the sample reaches a window.

With estimated local ranks (1/p apart) a value's global rank is one cumulative weight. With exact ones, each node's rank
sequence becomes increments at its sampled values, and the sum over nodes is again one cumulative sum."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rankspark.exact import phi_rows
from rankspark.params import fraction


def kept(key: Column, share: Column) -> Column:
    """Whether the hash of a key falls under a share: the same integers in every engine."""
    return F.pmod(F.pmod(key, F.lit(1 << 31)) * F.lit(1103515245) + F.lit(12345), F.lit(1 << 31)) < F.floor(share * F.lit(float(1 << 31)))


def kept_sql(key: str, share: str) -> str:
    return f"((({key}) % {1 << 31}) * 1103515245 + 12345) % {1 << 31} < floor(({share}) * {float(1 << 31)})"


def node_sizes(df: DataFrame, node: str) -> DataFrame:
    """node, size, n, k, one row a node."""
    sizes = df.groupBy(node).agg(F.count(F.lit(1)).alias("size"))
    total = sizes.agg(F.sum("size").alias("n"), F.count(F.lit(1)).alias("k"))
    return sizes.join(F.broadcast(total))


def rates(df: DataFrame, node: str, eps, capped: bool = False) -> DataFrame:
    """node, size, n, k, p: sqrt(k) / (eps n); with `capped` a node of n / sqrt(k) values or more gets 1 / (eps size)."""
    e = float(fraction(eps))
    flat = F.sqrt(F.col("k").cast("double")) / (F.lit(e) * F.col("n"))
    p = flat if not capped else F.when(F.col("size") * F.sqrt(F.col("k").cast("double")) >= F.col("n"), 1 / (F.lit(e) * F.col("size"))).otherwise(flat)
    return node_sizes(df, node).withColumn("p", F.least(F.lit(1.0), p))


def rank_sample(df: DataFrame, value: str, node: str, key: Column, eps, capped: bool = False, exact: bool = False) -> DataFrame:
    """node, value, p, step: the sampled values with the increments of their node's rank function."""
    rows = df.select(F.col(value).alias("value"), F.col(node).alias("node"), key.alias("key"))
    rate = F.broadcast(rates(rows, "node", eps, capped).select("node", "p"))
    if not exact:
        return rows.join(rate, "node").where(kept(F.col("key"), F.col("p"))).select("node", "value", "p", (1 / F.col("p")).alias("step"))
    # exact ranks: the rank of the last duplicate in the node, known before the sampling filter
    order = W.Window.partitionBy("node").orderBy("value")
    ranked = rows.withColumn("rank", F.count(F.lit(1)).over(order.rangeBetween(W.Window.unboundedPreceding, 0)) - 1).join(rate, "node")
    chosen = ranked.where(kept(F.col("key"), F.col("p")))
    last = F.lag("rank").over(W.Window.partitionBy("node").orderBy("value", "key"))
    return chosen.select("node", "value", "p", F.when(last.isNull(), F.col("rank") + 1 / F.col("p")).otherwise(F.col("rank") - last).cast("double").alias("step"))


def global_ranks(sample: DataFrame) -> DataFrame:
    """value, est: one window over the sample."""
    steps = sample.groupBy("value").agg(F.sum("step").alias("step")).withColumn("one", F.lit(1))
    return steps.select("value", F.round(F.sum("step").over(W.Window.partitionBy("one").orderBy("value").rowsBetween(W.Window.unboundedPreceding, 0)), 4).alias("est"))


def answers(sample: DataFrame, n: DataFrame, phis: list[tuple[int, int]]) -> DataFrame:
    """phi_num, phi_den, value: the sampled value whose global rank is nearest to the target, the smaller of equals."""
    met = global_ranks(sample).join(F.broadcast(n)).join(F.broadcast(phi_rows(sample, phis)))
    off = F.abs(F.col("est") - F.expr("phi_num * n div phi_den"))
    return met.groupBy("phi_num", "phi_den").agg(F.min_by("value", F.struct(F.round(off, 4), "value")).alias("value"))


def quantiles(df: DataFrame, value: str, node: str, key: Column, eps, phis: list[tuple[int, int]], capped: bool = False, exact: bool = False) -> DataFrame:
    n = df.agg(F.count(F.lit(1)).alias("n"))
    return answers(rank_sample(df, value, node, key, eps, capped, exact), n, phis)


def classes(df: DataFrame, node: str) -> DataFrame:
    """node, size, cls: -1 for small nodes, else floor(log2(size sqrt(k) / n))."""
    x = F.col("size") * F.sqrt(F.col("k").cast("double")) / F.col("n")
    return node_sizes(df, node).select(F.col(node).alias("node"), "size", F.when(x < 1, -1).otherwise(F.floor(F.log2(x))).cast("int").alias("cls"))


def bernoulli(df: DataFrame, value: str, key: Column, p: float, phis: list[tuple[int, int]]) -> DataFrame:
    """Quantiles of a plain sample."""
    from rankspark.exact import exact_quantiles

    return exact_quantiles(df.where(kept(key, F.lit(p))).select(value), value, phis)


def flat_sql(table: str, value: str, node: str, key: str, eps, phis: list[tuple[int, int]], capped: bool = False, exact: bool = False) -> str:
    e, grid = float(fraction(eps)), ", ".join(f"({a}, {b})" for a, b in phis)
    flat = f"sqrt(k) / ({e} * n)"
    p = flat if not capped else f"CASE WHEN size * sqrt(k) >= n THEN 1 / ({e} * size) ELSE {flat} END"
    step = "CASE WHEN lag(rank) OVER w IS NULL THEN rank + 1 / p ELSE rank - lag(rank) OVER w END" if exact else "1 / p"
    return f"""WITH x AS (SELECT {value} AS value, {node} AS node, {key} AS key FROM {table}),
z AS (SELECT node, size, sum(size) OVER () AS n, count(*) OVER () AS k FROM (SELECT node, count(*) AS size FROM x GROUP BY node)),
r AS (SELECT node, least(1.0, {p}) AS p FROM z),
s AS (SELECT x.*, p, count(*) OVER (PARTITION BY x.node ORDER BY value RANGE UNBOUNDED PRECEDING) - 1 AS rank FROM x JOIN r ON x.node = r.node),
c AS (SELECT value, {step} AS step FROM (SELECT * FROM s WHERE {kept_sql("key", "p")}) WINDOW w AS (PARTITION BY node ORDER BY value, key)),
g AS (SELECT value, round(sum(step) OVER (ORDER BY value ROWS UNBOUNDED PRECEDING), 4) AS est FROM (SELECT value, sum(step) AS step FROM c GROUP BY value)),
m AS (SELECT phi_num, phi_den, value, row_number() OVER (PARTITION BY phi_num, phi_den ORDER BY round(abs(est - (phi_num * n) // phi_den), 4), value) AS best FROM g, (SELECT count(*) AS n FROM x), (VALUES {grid}) v(phi_num, phi_den))
SELECT phi_num, phi_den, value FROM m WHERE best = 1"""
