"""Sharding by proportional stratified interleaving.

Rows of each source are shuffled by a seeded hash and ranked; (rank + 1/2) / rows of the source is a row's place in
[0, 1). Sorted by place, every stretch of the order holds the sources in the proportions of the whole, and equal cuts
give shards that match the mixture with row counts at most one apart.

No source meets in one task: a rank is the count of the source's rows in earlier hash ranges, from a small table of
counts, plus the rank inside one range. The order by place is found in the same way, over ranges of places.

Defined cases: a null source is a source of its own; null text has size 1 and the checksum of no bytes; repeated rows
are ranked one after another and lie in shards like any rows; an empty table gives no rows; other columns are
ignored. Equal texts are no groups under this law: rows of one text may lie in several shards."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

#: Rows that one range of hashes or places holds on average.
RANGE_ROWS = 20_000


def _offsets(df: DataFrame, by: list[str], bucket: str) -> DataFrame:
    """Rows of each (by, bucket), with the rows in earlier buckets and in all. The window runs over counts only."""
    counts = df.groupBy(*by, bucket).agg(F.count(F.lit(1)).alias("__n"))
    part = W.Window.partitionBy(*by) if by else W.Window.partitionBy(F.lit(0))
    before = F.coalesce(F.sum("__n").over(part.orderBy(bucket).rowsBetween(W.Window.unboundedPreceding, -1)), F.lit(0))
    return counts.withColumn("__before", before).withColumn("__all", F.sum("__n").over(part))


def assign(docs: DataFrame, shards: int = 16, seed: int = 42, ranges: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, source, shard, slot. ranges: how many ranges, by default one for each RANGE_ROWS rows."""
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select("doc_id", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("null")).alias("source"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    rows = rows.withColumn("__h", F.xxhash64(F.lit(seed), "doc_id", "text_crc32", "size"))
    ranges = ranges or max(16, docs.count() // RANGE_ROWS)
    # unsigned place of the hash among equal ranges of its 2**64 values
    rows = rows.withColumn("__b", F.floor((F.col("__h") / F.lit(2.0**64) + 0.5) * ranges))
    within = W.Window.partitionBy("source", "__b").orderBy("__h", "doc_id", "text_crc32", "size")
    ranked = rows.join(_offsets(rows, ["source"], "__b"), ["source", "__b"])
    ranked = ranked.withColumn("__r", F.col("__before") + F.row_number().over(within) - 1)
    place = (2 * F.col("__r") + 1) / (2 * F.col("__all"))
    placed = ranked.select("doc_id", "source", "size", "text_crc32", "__h", place.alias("__f"))
    placed = placed.withColumn("__c", F.floor(F.col("__f") * ranges))
    order = W.Window.partitionBy("__c").orderBy("__f", F.xxhash64("source"), "source", "__h", "doc_id", "text_crc32", "size")
    numbered = placed.join(_offsets(placed, [], "__c"), "__c")
    numbered = numbered.withColumn("__at", F.col("__before") + F.row_number().over(order) - 1)
    cut = lambda at: (at * shards - at * shards % F.col("__all")) / F.col("__all")
    shard = F.floor(cut(F.col("__at"))).cast("int")
    first = F.floor((shard.cast("long") * F.col("__all") + shards - 1) / shards)
    return numbered.select("doc_id", "size", "text_crc32", F.when(F.col("source") != "null", F.substring("source", 2, 1 << 30)).alias("source"), shard.alias("shard"), (F.col("__at") - first).cast("long").alias("slot"))
