"""Quality classifier: histogram gradient-boosted trees over document statistics, flattened into arrays.

Fitted on a bounded sample of labelled documents (`sample_rows`); every whole text is scored.

Defined cases: null and empty texts get the score of an empty text; an empty table gives no rows; repeated rows
each get their score; without labels of both classes every score is the share of the class (0.5 without any);
other columns are ignored; a null doc_id is not held out."""

from __future__ import annotations

from collections import Counter
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, gbdt
from .toxicity import BLANK, DIGIT, LOWER, MARKS, SYMBOLS, UPPER

# Frequent function words of four languages.
FUNCTION_WORDS = frozenset(
    """the of and to in a is that it for on with as was be by are this from or an at not he which
    der die das und ist in zu den von mit ein eine auf für nicht des im sich dem auch
    le la les de des et en un une du est que qui pour dans par au sur pas ou
    el los las del y al se por con no una su para es lo como""".split()
)
WIDTH = 24


def features(text: str | None) -> list[float]:
    text = text or ""
    raw = np.bincount(np.frombuffer(text.encode("utf-8", "replace"), dtype=np.uint8), minlength=256)
    size = max(1, int(raw.sum()))
    words = text.split()
    n = max(1, len(words))
    count = Counter(words)
    top = count.most_common(3)
    lines = [x for x in text.split("\n") if x.strip()]
    line_count = Counter(lines)
    share = raw[raw > 0] / size
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words)) if words else np.zeros(1)
    function = sum(count[w] for w in FUNCTION_WORDS.intersection(count))
    return [
        float(np.log1p(len(words))), lengths.mean(), lengths.std(), lengths.max(), len(count) / n,
        (top[0][1] / n) if top else 0.0, sum(c for _, c in top) / n, sum(map(eq, words, words[1:])) / n,
        len(set(zip(words, words[1:], strict=False))) / n, function / n, len(lines), len(line_count) / max(1, len(lines)),
        max(line_count.values(), default=0) / max(1, len(lines)), size / max(1, len(lines)), raw[UPPER].sum() / max(1, raw[UPPER].sum() + raw[LOWER].sum()),
        raw[DIGIT].sum() / size, raw[MARKS].sum() / n, raw[SYMBOLS].sum() / n, raw[124] / n, raw[33] / n, raw[BLANK].sum() / size,
        raw[128:].sum() / size, float(-(share * np.log2(share)).sum()) if len(share) else 0.0, raw[46] / n,
    ]


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = 16_000) -> gbdt.Trees:
    x, y, _ = common.gathered(common.labelled_sample(docs, labels, "quality", sample_rows), features, WIDTH)
    return gbdt.fit(x, y)


def score(docs: DataFrame, labels: DataFrame, sample_rows: int = 16_000, trained_on: DataFrame | None = None, cut: float = 0.3) -> DataFrame:
    """trained_on: where the labelled texts are, if not in docs."""
    return common.scored(docs, features, WIDTH, train(docs if trained_on is None else trained_on, labels, sample_rows).probability, cut)


def rated(docs: DataFrame, model: gbdt.Trees, keep: list[str], cut: float = 0.3) -> DataFrame:
    """score and predicted beside the columns `keep` of each row. A text that is kept travels once."""
    within = "text" in keep
    kept = docs.select(F.struct(*keep).alias("row"), *[F.col("text").alias("__text")][within:])

    def run(batches):
        for b in common.slices(batches):
            texts = b.column(0).field("text") if within else b.column(1)
            x = np.array([features(t) for t in texts.to_pylist()], dtype=np.float64).reshape(b.num_rows, WIDTH)
            p = model.probability(x)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(p), pa.array((p >= cut).astype(np.int32))], ["row", "score", "predicted"])

    return common.mapped(kept, run, f"row {kept.schema['row'].dataType.simpleString()}, score double, predicted int").select("row.*", "score", "predicted")
