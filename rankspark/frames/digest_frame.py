"""The batch dyadic digest as plain DataFrames: leaf counts, folding level by level, merging by sums, answers by a window.

A level is one aggregation: a parent and its children meet under the parent's key, and the group either folds or stays."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rankspark.exact import phi_rows
from rankspark.params import fraction


def leaf_counts(df: DataFrame, value: str, by: list[str] | None = None) -> DataFrame:
    """by..., level 0, idx, cnt: partial and final hash aggregation, so counts meet and not rows."""
    return df.where(F.col(value).isNotNull()).groupBy(*(by or []), F.lit(0).alias("level"), F.col(value).cast("long").alias("idx")).agg(F.count(F.lit(1)).alias("cnt"))


def with_threshold(nodes: DataFrame, eps, bits: int, by: list[str] | None = None) -> DataFrame:
    e = fraction(eps)
    totals = nodes.groupBy(*(by or [])).agg(F.sum("cnt").alias("n"))
    limit = totals.withColumn("t", F.expr(f"{e.numerator} * n div {e.denominator * bits}")).drop("n")
    return nodes.join(limit, by) if by else nodes.join(F.broadcast(limit))  # a row for each digest: one without keys


def compress(nodes: DataFrame, eps, bits: int, by: list[str] | None = None) -> DataFrame:
    """One sweep from the leaves to the root. The plan's depth is `bits`, known beforehand."""
    by = by or []
    now = with_threshold(nodes, eps, bits, by)
    for lv in range(bits):
        child, parent = F.col("level") == lv, F.col("level") == lv + 1
        key_level = F.when(child, lv + 1).otherwise(F.col("level"))
        key = F.when(child, F.expr("idx div 2")).otherwise(F.col("idx"))
        add = lambda cond: F.sum(F.when(cond, F.col("cnt")).otherwise(0))
        met = now.groupBy(*by, "t", key_level.alias("kl"), key.alias("k")).agg(
            add(child & (F.col("idx") % 2 == 0)).alias("left"), add(child & (F.col("idx") % 2 == 1)).alias("right"), add(~child).alias("own")
        )
        fold = (F.col("left") + F.col("right") > 0) & (F.col("left") + F.col("right") + F.col("own") <= F.col("t"))
        node = lambda lvl, i, c: F.struct(F.lit(lvl).cast("int").alias("level") if isinstance(lvl, int) else lvl.cast("int").alias("level"), i.cast("long").alias("idx"), c.cast("long").alias("cnt"))
        stay = F.array(node(lv, F.col("k") * 2, F.col("left")), node(lv, F.col("k") * 2 + 1, F.col("right")), node(F.col("kl"), F.col("k"), F.col("own")))
        one = F.array(node(F.col("kl"), F.col("k"), F.col("left") + F.col("right") + F.col("own")))
        now = met.select(*by, "t", F.explode(F.filter(F.when(fold, one).otherwise(stay), lambda x: x["cnt"] > 0)).alias("x")).select(*by, "t", "x.*")
    return now.select(*by, "level", "idx", "cnt")


def build(df: DataFrame, value: str, eps, bits: int, by: list[str] | None = None) -> DataFrame:
    return compress(leaf_counts(df, value, by), eps, bits, by)


def merge(parts: DataFrame, eps, bits: int) -> DataFrame:
    """Counters of all parts add up node by node in one shuffle, then one sweep with the new total."""
    return compress(parts.groupBy("level", "idx").agg(F.sum("cnt").alias("cnt")), eps, bits)


def answers(nodes: DataFrame, phis: list[tuple[int, int]], largest: int | None = None) -> DataFrame:
    """phi_num, phi_den, value: in post-order (right ends, children before parents), the first node whose running count
    exceeds the target. The window spans a digest, whose size is bounded, never the data."""
    high = F.expr("shiftleft(idx + 1, level) - 1")
    run = nodes.select(high.alias("high"), "level", "cnt").withColumn("one", F.lit(1))
    run = run.withColumn("upto", F.sum("cnt").over(W.Window.partitionBy("one").orderBy("high", "level").rowsBetween(W.Window.unboundedPreceding, 0)))
    run = run.withColumn("n", F.sum("cnt").over(W.Window.partitionBy("one")))
    met = run.join(F.broadcast(phi_rows(nodes, phis))).where("upto * phi_den > least(phi_num * n div phi_den, n - 1) * phi_den")
    value = F.min("high") if largest is None else F.least(F.min("high"), F.lit(largest))
    return met.groupBy("phi_num", "phi_den").agg(value.cast("long").alias("value"))


def property_check(nodes: DataFrame, eps, bits: int) -> DataFrame:
    """Per level: nodes, inner nodes above the threshold, triples (node, sibling, parent) not above it."""
    told = with_threshold(nodes, eps, bits)
    other = nodes.select(F.col("level").alias("ol"), F.col("idx").alias("oi"), F.col("cnt").alias("sibling"))
    up = nodes.select(F.col("level").alias("pl"), F.col("idx").alias("pi"), F.col("cnt").alias("parent"))
    met = told.join(other, (F.col("ol") == F.col("level")) & (F.col("oi") == F.expr("idx + 1 - 2 * (idx % 2)")), "left")
    met = met.join(up, (F.col("pl") == F.col("level") + 1) & (F.col("pi") == F.expr("idx div 2")), "left")
    triple = F.col("cnt") + F.coalesce("sibling", F.lit(0)) + F.coalesce("parent", F.lit(0))
    return met.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.count_if((F.col("level") > 0) & (F.col("cnt") > F.col("t"))).alias("over"), F.count_if((F.col("level") < bits) & (triple <= F.col("t"))).alias("poor"))


# ---- the same for DuckDB: a chain of CTEs, one for each level


def leaves_sql(table: str, value: str, by: str = "") -> str:
    key = f"{by} AS b, " if by else "0 AS b, "
    return f"l AS (SELECT {key}0 AS level, CAST({value} AS BIGINT) AS idx, count(*) AS cnt FROM {table} GROUP BY ALL)"


def compress_sql(source: str, name: str, eps, bits: int) -> str:
    """CTEs that end in `name`(b, level, idx, cnt), from `source` of the same columns."""
    e = fraction(eps)
    out = [f"{name}_0 AS (SELECT s.*, t FROM {source} s JOIN (SELECT b, {e.numerator} * sum(cnt) // {e.denominator * bits} AS t FROM {source} GROUP BY b) USING (b))"]
    for lv in range(bits):
        met = f"""SELECT b, t, CASE WHEN level = {lv} THEN {lv + 1} ELSE level END AS kl, CASE WHEN level = {lv} THEN idx // 2 ELSE idx END AS k,
 sum(CASE WHEN level = {lv} AND idx % 2 = 0 THEN cnt ELSE 0 END) AS a, sum(CASE WHEN level = {lv} AND idx % 2 = 1 THEN cnt ELSE 0 END) AS z, sum(CASE WHEN level <> {lv} THEN cnt ELSE 0 END) AS o FROM {name}_{lv} GROUP BY ALL"""
        out.append(f"{name}_m{lv} AS ({met})")
        out.append(f"""{name}_{lv + 1} AS (SELECT b, kl AS level, k AS idx, a + z + o AS cnt, t FROM {name}_m{lv} WHERE a + z > 0 AND a + z + o <= t
 UNION ALL SELECT b, level, idx, cnt, t FROM (SELECT b, t, {lv} AS level, k * 2 AS idx, a AS cnt, a, z, o FROM {name}_m{lv} UNION ALL SELECT b, t, {lv}, k * 2 + 1, z, a, z, o FROM {name}_m{lv} UNION ALL SELECT b, t, kl, k, o, a, z, o FROM {name}_m{lv}) WHERE cnt > 0 AND NOT (a + z > 0 AND a + z + o <= t))""")
    out.append(f"{name} AS (SELECT b, level, idx, cnt, t FROM {name}_{bits})")
    return ", ".join(out)


def answers_sql(source: str, phis: list[tuple[int, int]]) -> str:
    grid = ", ".join(f"({a}, {b})" for a, b in phis)
    return f"""SELECT phi_num, phi_den, CAST(min(high) AS BIGINT) AS value FROM (SELECT high, sum(cnt) OVER (ORDER BY high, level ROWS UNBOUNDED PRECEDING) AS upto, sum(cnt) OVER () AS n
 FROM (SELECT ((idx + 1) << level::INT) - 1 AS high, level, cnt FROM {source})), (VALUES {grid}) v(phi_num, phi_den) WHERE upto > least((phi_num * n) // phi_den, n - 1) GROUP BY ALL"""
