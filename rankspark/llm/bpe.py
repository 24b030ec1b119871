"""BPE encoding by backtracking, and decoding by an offset table.

A word is cut from the left into its longest tokens, which an Aho-Corasick automaton finds. A cut is kept while the
new token may stand after the one before it: in a pair-compatibility test, no merge across the border of the two may
have come before the merges that built them. Where no token fits, the encoder steps back and takes the next shorter
one. Every place that has once failed is remembered, so a word is done in linear time, and the result is that of
applying all merges in order.

The vocabulary is a tokenizer file of the `tokenizers` library: BPE over byte characters with an end-of-word suffix,
normalised by NFC, white space and lower case, split by a pattern. A text with characters that this Python's version of
Unicode does not know is normalised and split by the library's own tables, which are newer; all others without it. The driver reads the file, and executors get it as a
broadcast: its size is that of the vocabulary, whatever the input.

Defined cases: null text counts as empty and has no tokens; the special tokens in a text become their ids; an empty table
gives no rows; repeated rows each get their row; other columns are ignored. Texts are encoded whole."""

from __future__ import annotations

import hashlib
import json
import struct
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Stands for the end-of-word suffix inside this module; no byte character has this code.
END = "\ue000"
#: Finished words, and tested pairs, that a worker remembers; each memory starts anew when full. Affects speed only.
REMEMBERED, PAIRS = 150_000, 250_000
BLANK = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"


def byte_characters() -> list[str]:
    """The character for each byte in byte-level vocabularies: printable Latin-1 stands for itself, the rest follows from 256."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


def unassigned(text: str) -> bool:
    """Whether a character of `text` is unassigned in this Python's version of Unicode."""
    return any(unicodedata.category(c) == "Cn" for c in set(text) if not c.isprintable())


class Codec:
    def __init__(self, source: str):
        import ahocorasick
        import regex

        spec = json.loads(source)
        model, suffix = spec["model"], spec["model"]["end_of_word_suffix"] or ""
        swap = lambda t: t[: -len(suffix)] + END if suffix and t.endswith(suffix) and t != suffix else t
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names = model["vocab"] | self.special
        self.ids = {swap(t): i for t, i in model["vocab"].items()}
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}  # of a token: rank of the merge that makes it, left, right
        for r, (a, b) in enumerate(model["merges"]):
            left, right = self.ids[swap(a)], self.ids[swap(b)]
            if (made := self.ids.get(swap(a + b))) is not None:
                self.rank.setdefault((left, right), r)
                self.parts.setdefault(made, (r, left, right))
        self.lefts: dict[int, list] = {}
        self.rights: dict[int, list] = {}
        self.fits: dict[int, bool] = {}
        self.automaton = ahocorasick.Automaton()
        self.length: dict[int, int] = {}
        single = lambda t: len(t.rstrip(END)) == 1
        usable = {i: t for t, i in self.ids.items() if single(t) or i in self.parts}
        for i, t in usable.items():
            if single(t) or self.sound(*self.parts[i][1:]):
                self.automaton.add_word(t, (len(t) - 1, i))
                self.length[i] = len(t)
        self.automaton.make_automaton()
        self.shorter = {i: self._longest_beginning(t) for i, t in usable.items() if i in self.length}
        self.bytes = byte_characters()
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.split = regex.compile(split["pattern"]["Regex"].replace(r"[^\s", f"[^{BLANK}")).findall
        # the file's rules for words, with an empty vocabulary
        bare = {"model": {"type": "BPE", "vocab": {}, "merges": []}, "added_tokens": [], "pre_tokenizer": split, "post_processor": None, "decoder": None}
        self.rules, self.library = json.dumps(spec | bare), None
        self.cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")").split if self.special else None
        # the offset table: all token strings in one array of bytes, with the place where each begins
        strings = [""] * (max(self.names.values()) + 1)
        for t, i in self.names.items():
            strings[i] = t
        coded = [(t + " ").encode() for t in strings]
        self.pool = np.frombuffer(b"".join(coded), dtype=np.uint8)
        self.offset = np.concatenate([[0], np.cumsum([len(c) for c in coded])])
        self.known = _Known(self)
        del self.names, self.ids

    # ---- which tokens may stand side by side

    def _spine(self, token: int, side: int) -> list[tuple[int, int, int]]:
        """The tokens at one end of `token` while it is built: (token, made at, swallowed at), in ranks."""
        memo = self.rights if side == 2 else self.lefts
        if token not in memo:
            out, until = [], 1 << 60
            while True:
                made = self.parts[token][0] if token in self.parts else -1
                out.append((token, made, until))
                if made < 0:
                    break
                token, until = self.parts[token][side], made
            memo[out[0][0]] = out
            return out
        return memo[token]

    def sound(self, a: int, b: int) -> bool:
        """Whether the merges that build a and b from a word's characters leave the border between them alone, or
        for the two halves of a token, whether nothing but their own merge crosses it."""
        own = self.rank.get((a, b))
        for x, made_x, until_x in self._spine(a, 2):
            for y, made_y, until_y in self._spine(b, 1):
                r = self.rank.get((x, y))
                if r is not None and (x, y) != (a, b) and r < until_x and r <= until_y and max(made_x, made_y) < min(until_x, until_y):
                    return False
        return own is None or own >= 0

    def compatible(self, a: int, b: int) -> bool:
        pair = a << 20 | b
        known = self.fits.get(pair)
        if known is None:
            if len(self.fits) >= PAIRS:
                self.fits.clear()
            known = self.fits[pair] = (a, b) not in self.rank and self.sound(a, b)
        return known

    def _longest_beginning(self, t: str) -> int | None:
        for n in range(len(t) - 1, 0, -1):
            if (i := self.ids.get(t[:n])) in self.length:
                return i
        return None

    # ---- encoding

    def word(self, w: str) -> list[int]:
        """Token ids of one word of byte characters that ends with END."""
        # by last character, so the longest match of a place is the one that stays
        longest = {last - before: i for last, (before, i) in self.automaton.iter(w)}
        n, size, fits = len(w), self.length, self.fits
        out: list[int] = []
        dead: set[int] = set()
        at, token, last = 0, longest.get(0), -1
        while at < n:
            while token is not None:
                after = at + size[token]
                if after not in dead:
                    if last < 0:
                        break
                    good = fits.get(last << 20 | token)
                    if good is None:
                        good = self.compatible(last, token)
                    if good:
                        break
                token = self.shorter[token]
            if token is None:
                if not out:
                    raise ValueError("a word has characters outside the vocabulary")
                dead.add(at)
                gone = out.pop()
                at -= size[gone]
                token = self.shorter[gone]
                last = out[-1] if out else -1
                continue
            out.append(token)
            last, at = token, after
            token = longest.get(at)
        return out

    def piece(self, w: str) -> bytes:
        plain = w.isascii() and w.isprintable()  # then its bytes stand for themselves
        ids = self.word((w if plain else "".join(map(self.bytes.__getitem__, w.encode("utf-8", "replace")))) + END)
        return struct.pack(f"<{len(ids)}I", *ids)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        for k, part in enumerate(self.cut(text) if self.cut and "<|" in text else [text]):
            if k % 2:
                out.append(np.array([self.special[part]], dtype="<u4").tobytes())
                continue
            if not part.isascii():
                if unassigned(part):
                    out += map(self.known.__getitem__, self.words_of_library(part))
                    continue
                part = unicodedata.normalize("NFC", part).replace("Σ", "σ")
            out += map(self.known.__getitem__, self.split(part.lower()))
        return b"".join(out)

    def words_of_library(self, part: str) -> list[str]:
        """The words of a text that has characters newer than this Python's Unicode. Which of them are letters, have a
        lower case or compose is told by the library's own tables; merging stays with `word`."""
        if self.library is None:
            from tokenizers import Tokenizer

            self.library = Tokenizer.from_str(self.rules)
        return [w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(part))]

    # ---- decoding

    def decode(self, ids: np.ndarray) -> bytes:
        """The token strings with a blank between them, gathered from the pool in one step."""
        if not len(ids):
            return b""
        start, size = self.offset[ids], self.offset[ids.astype(np.int64) + 1] - self.offset[ids]
        ends = np.cumsum(size)
        return self.pool[np.arange(ends[-1]) + np.repeat(start - (ends - size), size)].tobytes()[:-1]


class _Known(dict):
    """Finished words of a codec; others are encoded when asked for."""

    def __init__(self, codec: Codec):
        super().__init__()
        self.codec = codec

    def __missing__(self, w: str) -> bytes:
        got = self.codec.piece(w)
        if len(w) <= 64:
            if len(self) >= REMEMBERED:
                self.clear()
            self[w] = got
        return got


def codec_of(shared) -> Codec:
    """One codec for each worker process and broadcast."""
    return common.held(f"bpe {shared.id}", lambda: Codec(shared.value))


class _Shared:
    def __init__(self, broadcast):
        self.broadcast, self.id = broadcast, str(broadcast._jbroadcast.id()) if broadcast._jbroadcast is not None else "0"

    @property
    def value(self) -> str:
        return self.broadcast.value

    def __getstate__(self):
        return {"broadcast": self.broadcast, "id": self.id}


PIECE_IDS = 1 << 20


def encoded(docs: DataFrame, path: str, keep: list[str] | None = None, with_ids: bool = False) -> DataFrame:
    """n_tokens, ids_sha256, decoded_sha256 (and ids, as bytes) beside the columns `keep` (default: doc_id)."""
    keep = ["doc_id"] if keep is None else keep
    with open(path, encoding="utf-8") as f:
        shared = _Shared(docs.sparkSession.sparkContext.broadcast(f.read()))
    kept = docs.select(*keep, F.coalesce("text", F.lit("")).alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]):
        codec = codec_of(shared)
        for b in common.slices(batches, owner=f"bpe {shared.id}"):
            out = []
            for text in b.column(b.num_columns - 1).to_pylist():
                coded = codec.encode(text)
                ids, back = np.frombuffer(coded, dtype="<u4"), hashlib.sha256()
                for at in range(0, len(ids), PIECE_IDS):
                    back.update((b" " if at else b"") + codec.decode(ids[at : at + PIECE_IDS]))
                out.append((len(ids), hashlib.sha256(coded).hexdigest(), back.hexdigest(), coded if with_ids else None))
            kinds = (pa.int64(), pa.string(), pa.string(), pa.binary())
            names = ("n_tokens", "ids_sha256", "decoded_sha256", "ids")[: 4 if with_ids else 3]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *[pa.array([r[i] for r in out], kinds[i]) for i in range(len(names))]], [*b.schema.names[:-1], *names])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema[:-1])
    return common.mapped(kept, run, f"{fields}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * with_ids)
