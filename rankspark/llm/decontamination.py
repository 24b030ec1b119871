"""Benchmark decontamination by winnowing, in DataFrame operations only.

A window is WINDOW words. Of the hashes of its K-grams, the least (the rightmost of equals) is its fingerprint, so equal
windows have equal fingerprints, and every shared span of WINDOW words or more has at least one in common. Windows that follow
each other mostly share one: a document keeps it once, at the first of them. Document fingerprints that the benchmark lacks go
at once. The others are extended to the windows that may share them, at most WINDOW - K + 1 places, and those are compared
with the items' windows word by word. Neighbouring hits merge into spans, and hit words are counted over them.

One scan hashes all words and probes windows and short items together: an item of fewer words than a window is a window of its
own length, probed by the hash of all its words. With at most `broadcast_rows` item windows these are broadcast and only hits are
grouped. With more, fingerprints (no words) are shuffled to the items' by salted keys, and the words of documents with a
common fingerprint are fetched by one join.

Defined cases: null or empty texts have no words and no hits; items without words are in no document; repeated items
count once by id and repeated document rows each get their row; a null item_id is left out of the item list; an empty
benchmark or table leaves every document clean or gives no rows; other columns are ignored."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from .common import stored
from .native import fixed, gram, run_of, word_hashes, words

WINDOW, K = 10, 6
#: Parts that the rows of one shuffled key are dealt to, so that a frequent passage or word is no single task.
SALTS = 16


def fingerprint(hashes: Column, at: Column, window: int = WINDOW, k: int = K) -> Column:
    return F.least(*[gram(hashes, at + i, k) for i in range(window - k + 1)])


def item_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """item_id, key (the window's words), size, print, for every window of every item."""
    rows = benchmark.where("item_id is not null").select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0)
    rows = rows.withColumn("n", F.least(F.size("w"), F.lit(window))).withColumn("h", word_hashes(F.col("w")))
    rows = rows.select("item_id", "w", "h", "n", F.explode(F.sequence(F.lit(0), F.size("w") - F.col("n"))).alias("at"))
    whole = F.when(F.col("n") == window, fingerprint(F.col("h"), F.col("at"), window)).otherwise(F.xxhash64(F.col("n"), F.slice("h", F.col("at") + 1, F.col("n"))))
    return rows.select("item_id", run_of(F.col("w"), F.col("at"), F.col("n")).alias("key"), F.col("n").alias("size"), whole.alias("print")).distinct()


def _known(rows: DataFrame, wanted: DataFrame, on: list[str], small: bool) -> DataFrame:
    """The rows whose key is wanted: by broadcast, or by a shuffle with each key in SALTS parts."""
    if small:
        return rows.join(F.broadcast(wanted), on, "left_semi")
    parts = wanted.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "th", "at"), F.lit(SALTS)).cast("int")).join(parts, [*on, "salt"], "left_semi").drop("salt")


def anchors(docs: DataFrame, sizes: list[int], window: int) -> DataFrame:
    """doc_id, th, w, at, size, print: the winnowed fingerprints of every document and the probes for shorter items. One scan.

    A window's fingerprint is new if the gram that enters is not larger than the grams shared with the window before, or the
    gram that left was smaller than those. Each gram is hashed once a place, in code small enough to be compiled."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("th"), words(F.col("text")).alias("w")).withColumn("h", fixed(word_hashes(F.col("w"))))
    spread = rows.select("doc_id", "th", "w", "h", F.posexplode("h").alias("at", "one")).where(F.col("at") + min(sizes) <= F.size("w"))
    out = None
    if window in sizes:
        grams = [gram(F.col("h"), F.col("at") + i, K) for i in range(-1, window - K + 1)]
        parts = spread.select("doc_id", "th", "w", fixed(F.col("at")).alias("at"), F.least(*grams[1:-1]).alias("mid"), grams[0].alias("left"), grams[-1].alias("enters"), *(["h"] if len(sizes) > 1 else []))
        new = (F.col("at") + window <= F.size("w")) & ((F.col("at") == 0) | (F.col("enters") <= F.col("mid")) | (F.col("left") < F.col("mid")))
        now = F.least("mid", "enters")
        if len(sizes) == 1:
            return parts.where(new).select("doc_id", "th", "w", "at", F.lit(window).alias("size"), now.alias("print"))
        spread, out = parts, F.struct(F.lit(window).alias("size"), F.when(new, now).alias("print"))
    short = [F.struct(F.lit(n).alias("size"), F.when(F.col("at") + n <= F.size("w"), F.xxhash64(F.lit(n), F.slice("h", F.col("at") + 1, n))).alias("print")) for n in sizes if n != window]
    return spread.select("doc_id", "th", "w", "at", F.inline(F.array(*([] if out is None else [out]), *short))).where("print is not null")


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, broadcast_rows: int = 1_000_000) -> tuple[DataFrame, DataFrame]:
    """(doc_id, th, at, size, key) for each place of a document where an item's window stands, and the item windows."""
    items = stored(item_windows(benchmark, window), "items")
    sizes = {r["size"]: r["n"] for r in items.groupBy("size").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `window` rows
    small = sum(sizes.values()) <= broadcast_rows
    near, prints = anchors(docs, sorted(sizes) or [window], window), items.select("size", "print").distinct()
    if small:
        near = _known(near, prints, ["size", "print"], small)
    else:
        near = _known(near.drop("w"), prints, ["size", "print"], small)
        places = near.groupBy("doc_id", "th").agg(F.collect_set(F.struct("at", "size")).alias("places"))
        places = places.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "places")
        texts = docs.select("doc_id", "text", F.xxhash64("text").alias("th")).join(places, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t")))
        near = texts.select("doc_id", "th", words(F.col("text")).alias("w"), "places").select("doc_id", "th", "w", F.inline("places"))
    reach = F.least(F.col("at") + (window - K), F.size("w") - window)
    near = near.select("doc_id", "th", "w", "size", F.explode(F.when(F.col("size") == window, F.sequence("at", reach)).otherwise(F.array("at"))).alias("at"))
    near = near.select("doc_id", "th", "at", "size", run_of(F.col("w"), F.col("at"), F.col("size")).alias("key"))
    return _known(near, items.select("key", "size").distinct(), ["key", "size"], small).distinct(), items


def spans(found: DataFrame) -> DataFrame:
    """Hits of each document merged into disjoint spans [start, stop) of words."""
    by = W.Window.partitionBy("doc_id", "th").orderBy("at", "size")
    reach = F.max(F.col("at") + F.col("size")).over(by.rowsBetween(W.Window.unboundedPreceding, -1))
    apart = found.select("doc_id", "th", "at", "size").withColumn("new", F.coalesce((F.col("at") > reach).cast("int"), F.lit(1)))
    apart = apart.withColumn("span", F.sum("new").over(by.rowsBetween(W.Window.unboundedPreceding, 0)))
    return apart.groupBy("doc_id", "th", "span").agg(F.min("at").alias("start"), F.max(F.col("at") + F.col("size")).alias("stop"))


def report(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, broadcast_rows: int = 1_000_000) -> DataFrame:
    """doc_id, th, n_words, n_hit, n_items, items_sha256, contaminated, for every row of docs."""
    found, items = hits(docs, benchmark, window, broadcast_rows)
    found = stored(found, "hits")  # read twice below
    covered = spans(found).groupBy("doc_id", "th").agg(F.sum(F.col("stop") - F.col("start")).alias("n_hit"))
    named = found.select("doc_id", "th", "key").distinct().join(items.select("key", "item_id").distinct(), "key")
    named = named.groupBy("doc_id", "th").agg(F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("items"))
    base = docs.select("doc_id", F.xxhash64("text").alias("th"), F.size(words(F.col("text"))).cast("long").alias("n_words"))
    known = covered.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "n_hit")
    known = known.join(named, F.col("d").eqNullSafe(F.col("doc_id")) & (F.col("t") == F.col("th"))).select("d", "t", "n_hit", "items")
    out = base.join(known, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t")), "left")
    listed = F.coalesce("items", F.array().cast("array<string>"))
    return out.select(
        "doc_id", "th", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.size(listed).cast("long").alias("n_items"),
        F.sha2(F.array_join(listed, ","), 256).alias("items_sha256"), (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )


def clean(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, broadcast_rows: int = 1_000_000) -> DataFrame:
    """The rows of docs that hold no window of the benchmark, all columns kept."""
    found, _ = hits(docs, benchmark, window, broadcast_rows)
    bad = found.select(F.col("doc_id").alias("__d"), F.col("th").alias("__t")).distinct()
    return docs.join(bad, F.col("doc_id").eqNullSafe(F.col("__d")) & (F.xxhash64("text") == F.col("__t")), "left_anti")


#: The report in plain SQL, for small tables.
SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, n, array_to_string(w[i + 1:i + n], ' ') AS k FROM (SELECT item_id, w, least(len(w), 10) AS n, unnest(range(0, len(w) - least(len(w), 10) + 1)) AS i FROM b WHERE len(w) > 0)),
dw AS (SELECT r, n, i, array_to_string(w[i + 1:i + n], ' ') AS k FROM (SELECT r, w, n, unnest(range(0, len(w) - n + 1)) AS i FROM d, (SELECT DISTINCT n FROM bw) WHERE len(w) >= n)),
h AS (SELECT dw.r, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.k = bw.k),
c AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS p FROM h) GROUP BY r),
t AS (SELECT r, list_sort(list(DISTINCT CAST(item_id AS VARCHAR))) AS items FROM h GROUP BY r)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(c.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(len(t.items), 0) AS BIGINT) AS n_items,
       sha256(coalesce(array_to_string(t.items, ','), '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c ON c.r = d.r LEFT JOIN t ON t.r = d.r"""
