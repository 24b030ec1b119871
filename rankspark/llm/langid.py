"""Language identification: averaged hashed subword embeddings with a linear softmax, trained by SGD in numpy.

A text is lower-cased, everything but letters becomes a blank, and each run of 1 to 3 characters without an inner
blank is hashed to one of 2**15 rows of an embedding table. The mean of the rows goes through a linear softmax.
For scoring, table and softmax are multiplied once, so a document costs one gather per subword. The temperature
and the rejection threshold are set on documents that the training did not see.

Every value of lang is learned. The training sample is bounded: `per_language` documents of each, and fewer past 256
languages, so that no more than 256 times as many are drawn in all, however many rows share an id. Counts per language and scores cover all rows. The
model has a column for each language in every worker, so `train` raises a ValueError beyond `most_languages`.

Defined cases: null texts and texts without a letter get `und`, score 0 and accepted false; an empty table gives no
rows; without any training language every row gets `und`; repeated rows each get their row; other columns are
ignored; a null doc_id is not held out. Texts of any length count as one; subwords are hashed a piece at a time."""

from __future__ import annotations

import sys
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from . import common

BITS, WIDTH, PIECE = 15, 16, 1 << 17
#: Languages of `per_language` training documents each that the sample may hold; scores that calibration works on at once.
FULL, SCORES = 256, 1 << 22


@lru_cache(1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(sys.maxunicode + 1)), dtype=bool, count=sys.maxunicode + 1)


def subwords(text: str) -> Iterator[np.ndarray]:
    """Hashed ids of all runs of 1 to 3 characters, PIECE starting places at a time; runs reach over a piece's edge as if the
    text were one. Nothing without a letter."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    letter = _letters()[c]
    if not letter.any():
        return
    c = np.concatenate([[np.uint32(32)], np.where(letter, c, np.uint32(32)), [np.uint32(32)]]).astype(np.uint32)
    mix = lambda h: (h * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS)
    for at in range(0, len(c), PIECE):
        part = c[at : at + PIECE + 2]
        letter = part != 32
        two = part[:-1] * np.uint32(0x85EBCA6B) + part[1:]
        three = (two[:-1] ^ (two[:-1] >> np.uint32(13))) * np.uint32(0xC2B2AE35) + part[2:]
        one, pair = letter[:PIECE], (letter[:-1] | letter[1:])[:PIECE]
        yield np.concatenate([mix(part[:PIECE][one] + np.uint32(77)), mix(two[:PIECE][pair] ^ np.uint32(0x5BD1E995)), mix(three[:PIECE][letter[1:-1][:PIECE]])])


def bag(text: str) -> tuple[np.ndarray, np.ndarray]:
    """The distinct subwords of a text and how often each occurs."""
    n = np.zeros(1 << BITS, dtype=np.int64)
    for ids in subwords(text):
        n += np.bincount(ids, minlength=1 << BITS)
    ids = np.flatnonzero(n)
    return ids, n[ids]


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # (2**BITS, languages): embedding times softmax weights
    bias: np.ndarray
    temperature: float
    least: float  # confidence below which a document is rejected

    def logits(self, text: str) -> np.ndarray | None:
        total, n = np.zeros(len(self.languages)), 0
        for ids in subwords(text):
            total += self.table.take(ids, axis=0).sum(axis=0, dtype=np.float64)
            n += len(ids)
        return total / n + self.bias if n else None

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        z = self.logits(text) if text and self.languages else None
        if z is None:
            return "und", 0.0, False
        p = softmax(z / self.temperature)
        k = int(p.argmax())
        return self.languages[k], float(p[k]), bool(p[k] >= self.least)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def fit(bags: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, languages: list[str], epochs: int = 4, rate: float = 0.5, seed: int = 11) -> Model:
    """bags: the distinct subwords of each document and their shares."""
    n, k, rng = len(bags), len(languages), np.random.default_rng(seed)
    table, weight, bias = rng.normal(0, 0.1, (1 << BITS, WIDTH)).astype(np.float32), np.zeros((WIDTH, k)), np.zeros(k)
    weight += rng.normal(0, 0.3, weight.shape)
    apart = np.arange(n) % 5 == 0 if n >= 20 * k else np.zeros(n, dtype=bool)
    rows = np.flatnonzero(~apart)
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for i in rng.permutation(rows):
            ids, share = bags[i]
            h = share @ table[ids]
            d = softmax(h @ weight + bias)
            d[y[i]] -= 1
            back = weight @ d
            weight -= step * np.outer(h, d)
            bias -= step * 0.1 * d
            table[ids] -= (step * 8 * share)[:, None] * back[None, :]
    seen = np.flatnonzero(apart) if apart.any() else np.arange(n)
    scale, loss, at = np.geomspace(0.3, 20, 60), np.zeros(60), y[seen]
    z = np.array([bags[i][1] @ table[bags[i][0]] @ weight + bias for i in seen]).reshape(len(seen), k)
    for part in np.array_split(np.arange(len(seen)), len(seen) * k // SCORES + 1) if n else []:
        loss += [-np.log(np.maximum(softmax(z[part] / t)[np.arange(len(part)), at[part]], 1e-12)).sum() for t in scale]
    t = float(scale[int(np.argmin(loss))]) if n else 1.0
    p = softmax(z / t) if n else np.zeros((0, k))
    right = p.max(axis=1)[p.argmax(axis=1) == at] if n else np.zeros(0)
    least = min(0.5, 0.5 * float(right.min())) if len(right) else 0.0  # half the lowest confidence of a right answer
    return Model(languages, (table @ weight).astype(np.float32), bias, t, least)


def train(docs: DataFrame, per_language: int = 600, folds: int = 3, held: int = 1, most_languages: int = 1024) -> Model:
    """The `per_language` documents of each language with the smallest hashes of their ids, none from the held-out fold. Equal
    rows of one id count once."""
    usable = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.coalesce(common.crc() % folds != held, F.lit(False)))
    # about how many different rows each language has, so that few more than wanted are ranked
    counts = {r["lang"]: r["n"] for r in usable.groupBy("lang").agg(F.approx_count_distinct("doc_id").alias("n")).limit(most_languages + 1).collect()}
    if len(counts) > most_languages:
        raise ValueError(f"more than {most_languages} values of lang to learn; raise most_languages if a worker has the memory for 2**{BITS} weights of each")
    languages = sorted(counts)
    if not languages:
        return Model([], np.zeros((1 << BITS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    per_language = max(1, min(per_language, FULL * per_language // len(languages)))
    share = F.create_map(*[F.lit(v) for lang in languages for v in (lang, min(1.0, (1.5 * per_language + 50) / max(1, counts[lang])))])
    near = usable.where(F.xxhash64("doc_id") / F.lit(2.0**64) + 0.5 < F.get(F.array(share[F.col("lang")]), F.lit(0)))
    first = W.Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id", "th")
    picked = near.select("doc_id", "lang", F.xxhash64("text").alias("th")).distinct().withColumn("place", F.row_number().over(first)).where(F.col("place") <= per_language)
    texts = near.select("doc_id", "lang", "text", F.xxhash64("text").alias("th")).join(F.broadcast(picked.drop("place")), ["doc_id", "lang", "th"], "left_semi")
    sample = texts.dropDuplicates(["doc_id", "lang", "th"])

    def run(batches):
        for b in common.slices(batches, 64):
            bags = [bag(t) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([i.astype(np.int32) for i, _ in bags], pa.list_(pa.int32())), pa.array([c.astype(np.int32) for _, c in bags], pa.list_(pa.int32()))], ["doc_id", "lang", "ids", "counts"])

    got = common.mapped(sample.select("doc_id", "lang", "text"), run, "doc_id long, lang string, ids array<int>, counts array<int>").toArrow()
    got = got.sort_by([("doc_id", "ascending"), ("lang", "ascending")])
    bags, y = [], []
    for lang, ids, counts in zip(got["lang"].to_pylist(), got["ids"], got["counts"], strict=True):
        i, c = ids.values.to_numpy(), counts.values.to_numpy().astype(np.float32)
        if len(i):
            bags.append((i, c / c.sum()))
            y.append(languages.index(lang))
    return fit(bags, np.array(y, dtype=np.int64), languages)


def predict(docs: DataFrame, model: Model, keep: list[str] | None = None) -> DataFrame:
    """lang_pred, score and accepted beside the columns `keep` (default: doc_id) of each row. One pass, no shuffle; a
    text that is kept travels once."""
    keep = ["doc_id"] if keep is None else keep
    n, at = len(keep), keep.index("text") if "text" in keep else len(keep)
    kept = docs.select(*keep, *[F.col("text").alias("__text")][: at == n])

    def run(batches):
        for b in common.slices(batches):
            out = [model.predict(t) for t in b.column(at).to_pylist()]
            cols = [pa.array([r[i] for r in out], kind) for i, kind in enumerate((pa.string(), pa.float64(), pa.bool_()))]
            yield pa.RecordBatch.from_arrays([*b.columns[:n], *cols], [*b.schema.names[:n], "lang_pred", "score", "accepted"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema[:n])
    return common.mapped(kept, run, f"{fields}, lang_pred string, score double, accepted boolean")
