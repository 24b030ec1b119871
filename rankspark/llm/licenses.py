"""License scans by diagonal voting, in DataFrame operations only.

Every template is a short run of words. All word pairs of the documents (rolling 2-grams, hashed in the scan) meet the
template places with the same pair; a hit votes for its diagonal, the place where the template would begin. Votes are
gathered as bit masks by diagonal. Diagonals a few words apart merge, which bridges inserted or missing words, and the
share of the template's pairs that a merged group covers is its score. Spans are verified by comparing words, not
hashes. A phrase stands where one diagonal has all its pairs.

Defined cases: null or empty texts have no words; a phrase or template is found at every place, overlapping ones too;
repeated rows each get their row; an empty table gives no rows; other columns are ignored."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from .native import gram, lower_ascii, word_hashes, words

# The phrases whose places are counted, and their labels.
PHRASES = [("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl")]
# Sentences by which texts declare a license, in lower-case words, and their labels.
NOTICES = [
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit"),
    ("released under the mit license", "mit"),
    ("licensed under the apache license version 2 0", "apache"),
    ("you may not use this file except in compliance with the license", "apache"),
    ("this work is licensed under the gnu general public license version 3", "gpl"),
    ("you can redistribute it and or modify it under the terms of the gnu general public license", "gpl"),
    ("redistribution and use in source and binary forms with or without modification are permitted", "bsd"),
    ("licensed under cc by nc 4 0", "cc-by-nc"),
    ("creative commons attribution noncommercial 4 0 international", "cc-by-nc"),
    ("licensed under cc by sa 4 0", "cc-by-sa"),
    ("creative commons attribution sharealike 4 0 international", "cc-by-sa"),
    ("subject to the terms of the mozilla public license v 2 0", "mpl"),
    ("permission to use copy modify and or distribute this software for any purpose", "isc"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
]
#: A merged diagonal group with this share of a notice's pairs counts as the notice; diagonals this far apart merge.
LEAST_SHARE, NEAR = 0.75, 3


def templates(spark: SparkSession) -> DataFrame:
    """tpl, phrase, label, pairs, place, a, b: one row for each word pair of each template (about 170, whatever the input)."""
    rows = []
    for k, (text, label) in enumerate(PHRASES + NOTICES):
        w = text.split()
        rows += [(k, k < len(PHRASES), label, len(w) - 1, i, w[i], w[i + 1]) for i in range(len(w) - 1)]
    return spark.createDataFrame(rows, "tpl int, phrase boolean, label string, pairs int, place int, a string, b string").withColumn("pair", F.xxhash64(F.xxhash64("a"), F.xxhash64("b")))


def diagonals(docs: DataFrame) -> DataFrame:
    """doc_id, th, tpl, phrase, label, pairs, diagonal, votes: a bit for each pair of the template that stands on the diagonal."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("th"), words(F.col("text")).alias("w")).where(F.size("w") > 1)
    rows = rows.withColumn("h", word_hashes(F.col("w")))
    spread = rows.select("doc_id", "th", "w", "h", F.posexplode("h").alias("at", "one")).where(F.col("at") + 1 < F.size("w"))
    spread = spread.withColumn("pair", gram(F.col("h"), F.col("at"), 2))
    hit = spread.join(F.broadcast(templates(docs.sparkSession)), "pair")
    hit = hit.where((lower_ascii(F.get("w", F.col("at"))) == F.col("a")) & (lower_ascii(F.get("w", F.col("at") + 1)) == F.col("b")))
    vote = F.expr("shiftleft(1L, place)")
    return hit.groupBy("doc_id", "th", "tpl", "phrase", "label", "pairs", (F.col("at") - F.col("place")).alias("diagonal")).agg(F.bit_or(vote).alias("votes"))


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, th, n_words, n_base, first_word, last_word, base_labels, labels, score, for every row of docs."""
    found = diagonals(docs)
    by = W.Window.partitionBy("doc_id", "th", "tpl").orderBy("diagonal")
    step = F.col("diagonal") - F.lag("diagonal").over(by)
    # phrases are exact: each of their diagonals stays alone
    grouped = found.withColumn("new", (F.col("phrase") | F.coalesce(step > NEAR, F.lit(True))).cast("int"))
    grouped = grouped.withColumn("part", F.sum("new").over(by.rowsBetween(W.Window.unboundedPreceding, 0)))
    merged = grouped.groupBy("doc_id", "th", "tpl", "phrase", "label", "pairs", "part").agg(F.min("diagonal").alias("start"), F.bit_count(F.bit_or("votes")).alias("got"))
    whole = F.col("phrase") & (F.col("got") == F.col("pairs"))
    share = F.col("got") / F.col("pairs")
    by_doc = merged.groupBy(F.col("doc_id").alias("d"), F.col("th").alias("t")).agg(
        F.sum(whole.cast("long")).alias("n_base"), F.min(F.when(whole, F.col("start"))).alias("first_word"), F.max(F.when(whole, F.col("start"))).alias("last_word"),
        F.collect_set(F.when(whole, F.col("label"))).alias("base"), F.collect_set(F.when(whole | (~F.col("phrase") & (share >= LEAST_SHARE)), F.col("label"))).alias("all"),
        F.max(share).alias("score"),
    )
    base = docs.select("doc_id", F.xxhash64("text").alias("th"), F.size(words(F.col("text"))).cast("long").alias("n_words"))
    out = base.join(by_doc, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t")), "left")
    listed = lambda c: F.coalesce(F.array_join(F.array_sort(c), ","), F.lit(""))
    return out.select(
        "doc_id", "th", "n_words", F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"), F.col("first_word").cast("long").alias("first_word"),
        F.col("last_word").cast("long").alias("last_word"), listed("base").alias("base_labels"), listed("all").alias("labels"), F.coalesce("score", F.lit(0.0)).alias("score"),
    )


def _sql() -> str:
    """The scan in plain SQL, for small tables."""
    rows = ", ".join(f"({k}, {k < len(PHRASES)}, '{label}', '{text}')" for k, (text, label) in enumerate(PHRASES + NOTICES))
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
t AS (SELECT tpl, phrase, label, string_split(txt, ' ') AS tw FROM (VALUES {rows}) v(tpl, phrase, label, txt)),
tp AS (SELECT tpl, phrase, label, len(tw) - 1 AS pairs, i AS place, tw[i + 1] AS a, tw[i + 2] AS b FROM (SELECT *, unnest(range(0, len(tw) - 1)) AS i FROM t)),
dp AS (SELECT r, i AS spot, w[i + 1] AS a, w[i + 2] AS b FROM (SELECT r, w, unnest(range(0, len(w) - 1)) AS i FROM d WHERE len(w) > 1)),
g AS (SELECT r, tpl, phrase, label, pairs, spot - place AS diagonal, list(DISTINCT place) AS votes FROM dp JOIN tp USING (a, b) GROUP BY ALL),
n AS (SELECT *, CASE WHEN phrase OR coalesce(diagonal - lag(diagonal) OVER q > {NEAR}, TRUE) THEN 1 ELSE 0 END AS fresh FROM g WINDOW q AS (PARTITION BY r, tpl ORDER BY diagonal)),
p AS (SELECT *, sum(fresh) OVER (PARTITION BY r, tpl ORDER BY diagonal ROWS UNBOUNDED PRECEDING) AS part FROM n),
m AS (SELECT r, tpl, phrase, label, pairs, part, min(diagonal) AS start, len(list_distinct(flatten(list(votes)))) AS got FROM p GROUP BY ALL),
s AS (SELECT r, sum(CASE WHEN phrase AND got = pairs THEN 1 ELSE 0 END) AS n_base, min(start) FILTER (phrase AND got = pairs) AS first_word, max(start) FILTER (phrase AND got = pairs) AS last_word,
      list_sort(list(DISTINCT label) FILTER (phrase AND got = pairs)) AS base, list_sort(list(DISTINCT label) FILTER ((phrase AND got = pairs) OR (NOT phrase AND got / pairs >= {LEAST_SHARE}))) AS every, max(got / pairs) AS score FROM m GROUP BY r)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_base, 0) AS BIGINT) AS n_base, CAST(first_word AS BIGINT) AS first_word, CAST(last_word AS BIGINT) AS last_word,
       coalesce(array_to_string(base, ','), '') AS base_labels, coalesce(array_to_string(every, ','), '') AS labels, CAST(coalesce(score, 0) AS DOUBLE) AS score
FROM d LEFT JOIN s ON s.r = d.r"""


SQL = _sql()
