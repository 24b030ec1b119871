"""The five summaries. `new` builds an empty one, `unpack` reads one back from bytes."""

from __future__ import annotations

from fractions import Fraction

from rankspark.params import MethodSpec

from .base import Synopsis, read_header
from .dyadic import DyadicDigest, OnlineDigest
from .gap_tuple import GapSummary
from .level_buffers import LevelBuffers
from .rank_sample import RankSampleSet

KINDS: dict[str, type[Synopsis]] = {c.method: c for c in (GapSummary, RankSampleSet, DyadicDigest, OnlineDigest, LevelBuffers)}


def new(spec: MethodSpec, node: int = 0) -> Synopsis:
    options = dict(spec.options)
    if spec.method in ("rsample", "levels"):
        options["seed"] = options.get("seed", 0) * 1_000_003 + node
    return KINDS[spec.method](spec.eps, **options)


def unpack(payload: bytes) -> Synopsis:
    head, arrays = read_header(payload)
    s = KINDS[head["m"]](Fraction(*head["e"]))
    s.restore(head, arrays)
    return s
