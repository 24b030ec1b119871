"""The whole cycle without Spark: deal values to parts, build, merge along a tree, ask. Tests hold Spark against it."""

from __future__ import annotations

import numpy as np

from rankspark import synopsis
from rankspark.params import MethodSpec


def build_parts(values: np.ndarray, spec: MethodSpec, parts: int, batch: int = 65_536) -> list[synopsis.Synopsis]:
    out = []
    for node, piece in enumerate(np.array_split(values, parts)):
        s = synopsis.new(spec, node)
        s.begin_chunk()
        for at in range(0, len(piece), batch):
            s.absorb(piece[at : at + batch])
        s.end_chunk()
        s.local_finalize()
        out.append(s)
    return out


def merged(parts: list[synopsis.Synopsis], fan_in: int = 2) -> synopsis.Synopsis:
    while len(parts) > 1:
        up = []
        for at in range(0, len(parts), fan_in):
            first, *others = parts[at : at + fan_in]
            for s in others:
                first.merge(s)
            up.append(first)
        parts = up
    return parts[0]


def run_local(values: np.ndarray, spec: MethodSpec, parts: int, phis: list[tuple[int, int]], fan_in: int = 2) -> list:
    return merged(build_parts(values, spec, parts), fan_in).query(phis)


def rank_errors(values: np.ndarray, phis: list[tuple[int, int]], answers: list) -> list[float]:
    data, n = np.sort(values), len(values)
    out = []
    for (a, b), x in zip(phis, answers, strict=True):
        r, low, high = min(n - 1, a * n // b), int(np.searchsorted(data, x, "left")), int(np.searchsorted(data, x, "right")) - 1
        out.append(max(0, low - r, r - max(high, low)) / n)
    return out
