"""Toxicity: gradient-boosted trees over dense features with isotonic calibration.

The features of a text are lexicon densities, distances of insults to second-person words, and rates of
capitals, punctuation and obfuscated words. One lexicon is fixed; a second one, of word beginnings with a weight
each, is learned from labelled documents, so that languages without a fixed list are covered. Lexicon, trees and
calibration are fitted on disjoint parts of a bounded sample of labelled documents (`sample_rows`). The whole text
is read once; nothing else is bounded.

Defined cases: null and empty texts get the score of an empty text; an empty table gives no rows; repeated rows
each get their score; without labels of both classes every score is the share of the class (0.5 without any);
columns other than doc_id and text are ignored; a null doc_id is not held out."""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from functools import lru_cache, partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, gbdt

# Words that insult, threaten or demean, and words of the second person, in four languages.
INSULTS = """idiot idiots moron morons stupid dumb dumbass fool fools loser losers scum trash garbage worthless pathetic
disgusting clown clowns imbecile cretin retard retarded jerk bastard bitch whore slut asshole shit fuck fucking
creep freak pig swine vermin parasite filth filthy ugly coward liar ignorant brainless useless hateful
idiota imbécil estúpido estúpida tonto basura inútil asqueroso payaso escoria
idiote imbécile stupide crétin ordure minable dégoûtant déchet connard salaud
dumm dummkopf idiotin trottel abschaum wertlos erbärmlich ekelhaft versager arschloch""".split()
THREATS = "kill die hurt destroy burn hang shoot hate punch murder stab töten hassen tuer haïr matar odio".split()
SECOND_PERSON = "you your yours yourself u ur du dich dir dein deine tu te toi ton ta tes vous votre tú ti usted ustedes vosotros su".split()
LEET = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i", "*": "", "+": "t", "_": "", "-": "", ".": ""})
MIXED = re.compile(r"[A-Za-z][0134578@$!*+]+[A-Za-z]|(?<![A-Za-z])[A-Za-z](?:[._*\-][A-Za-z]){3,}")
REST = re.compile(r"\S*")
WIDTH = 32
#: Lengths of the word beginnings that the learned lexicon is drawn from.
BEGINNINGS = range(4, 9)
WORD = re.compile(r"[^\W\d_]{4,}")


@lru_cache(2)
def _automaton(terms: tuple[tuple[str, float], ...]):
    """Each word with the kinds it belongs to; kind 3 holds the learned beginnings."""
    import ahocorasick

    kinds: dict[str, list[tuple[int, float]]] = {}
    for kind, words in enumerate((INSULTS, THREATS, SECOND_PERSON)):
        for w in words:
            kinds.setdefault(w, []).append((kind, 1.0))
    for w, weight in terms:
        kinds.setdefault(w, []).append((3, weight))
    found = ahocorasick.Automaton()
    for w, known in kinds.items():
        found.add_word(w, (len(w), w, tuple(known)))
    found.make_automaton()
    return found


def _class(spec: str) -> np.ndarray:
    return np.array([ord(c) for c in spec])


UPPER, LOWER, DIGIT, BLANK = _class("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _class("abcdefghijklmnopqrstuvwxyz"), _class("0123456789"), _class(" \t\n\r\v\f")
MARKS, SYMBOLS = _class(".,;:'\"()"), _class("#$%&*@^~|<>=+\\/_[]{}`")


def features(terms: tuple[tuple[str, float], ...], text: str | None) -> list[float]:
    """32 numbers; all rates are per byte, per word or per thousand words, so that length alone says little."""
    text = text or ""
    low = text.lower()
    raw = np.bincount(np.frombuffer(text.encode("utf-8", "replace"), dtype=np.uint8), minlength=256)
    size = max(1, int(raw.sum()))
    words = max(1, int(raw[BLANK].sum()) + 1)
    upper, lower = int(raw[UPPER].sum()), int(raw[LOWER].sum())
    at: tuple[list[int], list[int], list[int]] = ([], [], [])
    kinds: set[str] = set()
    end = len(low)
    learned: dict[int, float] = {}
    for stop, (length, word, known) in _automaton(terms).iter(low):
        start = stop - length + 1
        if start == 0 or not low[start - 1].isalnum():
            whole = stop + 1 == end or not low[stop + 1].isalnum()
            for kind, weight in known:
                if kind == 3:
                    learned[start] = max(weight, learned.get(start, 0.0))
                elif whole:
                    at[kind].append(start)
                    if kind == 0:
                        kinds.add(word)
    near = [min((abs(p - s) for s in at[2][max(0, bisect_left(at[2], p) - 1) :][:2]), default=10_000) for p in at[0]]
    close = [b - a for a, b in zip(at[0], at[0][1:], strict=False)]
    mixed = hidden = reach = 0
    insult = False
    for m in MIXED.finditer(text):
        mixed += 1
        if m.start() >= reach:  # a word not looked at yet; a word's matches share its answer
            first = m.start()
            while first > reach and not text[first - 1].isspace():
                first -= 1
            reach = REST.match(text, m.end()).end()
            plain = text[first:reach].lower().strip(",;:?\"'()").translate(LEET)
            insult = plain in INSULT_SET or plain.rstrip("i") in INSULT_SET
        hidden += insult
    hits = len(at[0])
    thousand = 1000.0 / words
    return [
        hits, hits * thousand, len(kinds), len(at[1]), len(at[1]) * thousand, len(at[2]) * thousand,
        min(near, default=10_000), sum(d <= 60 for d in near), min(close, default=10_000), sum(d <= 200 for d in close),
        hidden, hidden * thousand, mixed * thousand, upper / max(1, upper + lower), (raw[UPPER].sum() / words),
        raw[33] / size, raw[63] / size, raw[MARKS].sum() / size, raw[SYMBOLS].sum() / size, raw[DIGIT].sum() / size,
        raw[124] / words, raw[10] / words, float(np.log1p(words)), size / words, raw[128:].sum() / size, hits / np.sqrt(words),
        len(learned), len(learned) * thousand, sum(learned.values()) * thousand, max(learned.values(), default=0.0),
        len(learned) / np.sqrt(words), sum(w > 3 for w in learned.values()) * thousand,
    ]


INSULT_SET = frozenset(INSULTS)


class Calibrated:
    """Trees, then the isotonic fit read between its knots; a thousandth of the raw score keeps the order inside flat parts."""

    def __init__(self, trees: gbdt.Trees, knots: tuple[np.ndarray, np.ndarray]):
        self.trees, self.knots = trees, knots

    def __call__(self, x: np.ndarray) -> np.ndarray:
        p = self.trees.probability(x)
        return p if len(self.knots[0]) < 2 else 0.999 * np.interp(p, *self.knots) + 0.001 * p


def learned_terms(sample: DataFrame, most: int = 300) -> tuple[tuple[str, float], ...]:
    """Beginnings of words that labelled toxic documents hold far more often: the `most` surest, with log ratios
    of their rates as weights. Counted by Spark; the driver gets the chosen terms only."""

    def run(batches):
        for b in common.slices(batches, 64):
            terms, ys, counts = [], [], []
            for y, text in zip(b.column(1).to_pylist(), b.column(0).to_pylist(), strict=True):
                words = Counter(WORD.findall((text or "").lower()))
                c: Counter[str] = Counter({"": sum(words.values())})
                for w, k in words.items():
                    for n in BEGINNINGS:
                        if n <= len(w):
                            c[w[:n]] += k
                terms += c.keys()
                counts += c.values()
                ys += [y] * len(c)
            yield pa.RecordBatch.from_arrays([pa.array(terms, pa.string()), pa.array(ys, pa.int32()), pa.array(counts, pa.int64())], ["term", "y", "k"])

    of = lambda y, v: F.sum(F.when(F.col("y") == y, v).otherwise(0))
    counted = common.mapped(sample.select("text", "y"), run, "term string, y int, k long").groupBy("term")
    counted = counted.agg(of(1, F.col("k")).alias("k1"), of(0, F.col("k")).alias("k0"), of(1, F.lit(1)).alias("d1"), of(0, F.lit(1)).alias("d0"))
    counted = counted.where("d1 >= 3")
    total = counted.where("term = ''").select(*[F.col(c).cast("double").alias(f"t{c}") for c in ("k1", "k0", "d1", "d0")])
    share = (F.col("d1") + F.col("d0")) / (F.col("td1") + F.col("td0"))
    sure = (F.col("d1") / F.col("td1") - F.col("d0") / F.col("td0")) / F.sqrt(share * (1 - share) * (1 / F.col("td1") + 1 / F.col("td0")) + F.lit(1e-9))
    weight = F.log(((F.col("k1") + 0.5) / F.col("tk1")) / ((F.col("k0") + 0.5) / F.col("tk0")))
    rows = counted.where("term != ''").join(F.broadcast(total.where("tk1 > 0 and tk0 > 0 and td0 > 0"))).select("term", weight.alias("w"), sure.alias("z"))
    chosen = rows.where("z >= 3.5 and w >= 1").orderBy(F.desc("z"), "term").limit(most).toArrow()
    return tuple(sorted(zip(chosen["term"].to_pylist(), chosen["w"].to_pylist(), strict=True)))


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = 10_000) -> tuple[tuple, Calibrated]:
    """Each half of the sample gets its features from the lexicon that the other half chose; texts to be scored
    get theirs from the lexicon of both. Scores of left-out fifths fit the calibration, all rows grow the trees."""
    sample = common.labelled_sample(docs, labels, "toxic", sample_rows)
    sample = sample.withColumn("half", F.pmod(F.xxhash64(F.lit(7), "doc_id"), F.lit(2)))
    parts = []
    for half in (0, 1):
        terms = learned_terms(sample.where(F.col("half") != half))
        parts.append(common.gathered(sample.where(F.col("half") == half), partial(features, terms), WIDTH))
    x, y, ids = (np.concatenate([p[i] for p in parts]) for i in range(3))
    fold = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)) % np.uint64(5)
    left_out = np.zeros(len(y))
    for k in range(5):
        left_out[fold == k] = gbdt.fit(x[fold != k], y[fold != k], least=6).probability(x[fold == k])
    return learned_terms(sample), Calibrated(gbdt.fit(x, y, least=6), gbdt.isotonic(left_out, y))


def score(docs: DataFrame, labels: DataFrame, sample_rows: int = 10_000) -> DataFrame:
    terms, model = train(docs, labels, sample_rows)
    return common.scored(docs, partial(features, terms), WIDTH, model, 0.5)
