"""Histogram gradient-boosted trees for log loss, in numpy, kept as flat arrays.

A model is four arrays: per tree and inner node (numbered as in a heap) a feature and a threshold, per tree and
leaf a value, and one base score. A document walks all trees at once: `at = 2 at + 1 + (x > threshold)`."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Trees:
    feature: np.ndarray  # (trees, 2**depth - 1) int32
    threshold: np.ndarray  # (trees, 2**depth - 1) float64; +inf where a node has no split
    leaf: np.ndarray  # (trees, 2**depth) float64
    base: float

    def margin(self, x: np.ndarray) -> np.ndarray:
        n, trees = len(x), len(self.feature)
        if not n or not trees:
            return np.full(n, self.base)
        depth, row, tree = self.leaf.shape[1].bit_length() - 1, np.arange(n)[:, None], np.arange(trees)[None, :]
        at = np.zeros((n, trees), dtype=np.int64)
        for _ in range(depth):
            at = 2 * at + 1 + (x[row, self.feature[tree, at]] > self.threshold[tree, at])
        return self.base + self.leaf[tree, at - (self.leaf.shape[1] - 1)].sum(axis=1)

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-self.margin(x)))


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 80, depth: int = 4, rate: float = 0.1, bins: int = 64, l2: float = 1.0, least: int = 12) -> Trees:
    """No rows or a single class give a constant model (0 rows: probability 0.5)."""
    n, width = x.shape if x.ndim == 2 else (0, 0)
    share = float(np.clip(y.mean(), 1e-4, 1 - 1e-4)) if n else 0.5
    base = float(np.log(share / (1 - share)))
    inner, leaves = 2**depth - 1, 2**depth
    if n < 2 * least or y.min() == y.max():
        return Trees(np.zeros((0, inner), np.int32), np.zeros((0, inner)), np.zeros((0, leaves)), base)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    code = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)  # code <= b  <=>  x <= edge[b]
    cell = code + np.arange(width) * bins
    usable = np.array([[b < len(e) for b in range(bins)] for e in edges])
    margin = np.full(n, base)
    feature, threshold, leaf = [], [], []
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-margin))
        g, h, node = y - p, p * (1 - p), np.zeros(n, dtype=np.int64)
        f_of, t_of = np.zeros(inner, np.int32), np.full(inner, np.inf)
        for level in range(depth):
            many = 2**level
            flat = (node[:, None] * (width * bins) + cell).ravel()
            size = many * width * bins
            sums = [np.bincount(flat, np.repeat(v, width), size).reshape(many, width, bins).cumsum(axis=2) for v in (g, h, np.ones(n))]
            left_g, left_h, left_n = sums
            all_g, all_h, all_n = (s[:, :, -1:] for s in sums)
            gain = left_g**2 / (left_h + l2) + (all_g - left_g) ** 2 / (all_h - left_h + l2) - all_g**2 / (all_h + l2)
            gain[~(usable[None] & (left_n >= least) & (all_n - left_n >= least))] = 0
            best = gain.reshape(many, -1).argmax(axis=1)
            worth = gain.reshape(many, -1)[np.arange(many), best] > 1e-6
            j, b = best // bins, best % bins
            at = many - 1 + np.arange(many)
            f_of[at] = np.where(worth, j, 0)
            t_of[at] = [edges[jj][bb] if w else np.inf for jj, bb, w in zip(j, b, worth, strict=True)]
            node = 2 * node + (x[np.arange(n), f_of[many - 1 + node]] > t_of[many - 1 + node])
        value = rate * np.bincount(node, g, leaves) / (np.bincount(node, h, leaves) + l2)
        margin += value[node]
        feature.append(f_of)
        threshold.append(t_of)
        leaf.append(value)
    return Trees(np.array(feature), np.array(threshold), np.array(leaf), base)


def isotonic(score: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the increasing step fit (pool adjacent violators), as centres of the pooled blocks."""
    order = np.argsort(score, kind="stable")
    blocks: list[list[float]] = []  # mean of y, weight, mean of score
    for s, v in zip(score[order], y[order], strict=True):
        blocks.append([float(v), 1.0, float(s)])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            (m1, w1, s1), (m0, w0, s0) = blocks.pop(), blocks.pop()
            w = w0 + w1
            blocks.append([(m0 * w0 + m1 * w1) / w, w, (s0 * w0 + s1 * w1) / w])
    return np.array([b[2] for b in blocks]), np.array([b[0] for b in blocks])
