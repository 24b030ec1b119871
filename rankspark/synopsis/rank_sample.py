"""Rank sample: each node samples its values with a rate p and sends them with their local ranks; the rank of any value in
a node is its sampled predecessor's plus 1/p, and nodes add up. The answer is the sampled value whose global rank is nearest.

Samples merge flat, along a tree by size classes (small ones pool, equal classes carry like binary digits), or in components:
along a tree inside each component of the tree, and flat across components (`engine.merge_components`)."""

from __future__ import annotations

import numpy as np

from rankspark import theory
from rankspark.params import target

from .base import Synopsis


class Sample:
    """One node's sample: values in order, their local ranks (0-based), the rate, and how many values it stands for."""

    def __init__(self, values: np.ndarray, ranks: np.ndarray, p: float, size: int):
        self.values, self.ranks, self.p, self.size = values, ranks, p, size

    def rank(self, x: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.values, x, side="right")
        return np.where(at > 0, self.ranks[np.maximum(at - 1, 0)] + 1 / self.p, 0.0) if len(self.values) else np.zeros(len(x))


def pooled(samples: list[Sample], p: float, rng: np.random.Generator) -> Sample:
    """Rank all values in the pool first, then thin each sample from its own rate to p."""
    values = np.concatenate([s.values for s in samples])
    keep = np.concatenate([rng.random(len(s.values)) < min(1.0, p / s.p) for s in samples])
    values = np.sort(values[keep])
    ranks = sum(s.rank(values) for s in samples) - 1 / min(1.0, p) if len(values) else np.zeros(0)
    return Sample(values, np.maximum(ranks, 0), min(1.0, p), sum(s.size for s in samples))


class RankSampleSet(Synopsis):
    """The samples that one place of the tree holds."""

    method = "rsample"
    parts = ("values", "ranks", "lengths", "rates", "sizes")
    scalars = ("p", "total", "nodes", "rank_mode", "mode", "seed")

    def __init__(self, eps, p: float | None = None, total: int = 0, nodes: int = 1, rank_mode: str = "exact", mode: str = "flat", seed: int = 0):
        super().__init__(eps)
        self.p, self.total, self.nodes, self.rank_mode, self.mode, self.seed = p, total, nodes, rank_mode, mode, seed
        self.samples: list[Sample] = []
        self._values: list[np.ndarray] = []
        self._seen, self._draw = 0, None

    @property
    def _early(self) -> float | None:
        """The rate, where it is known before the data and nothing but the sample is needed."""
        if self.rank_mode == "exact" or not (self.p or (self.mode == "flat" and self.total)):
            return None
        return self.p or theory.sample_rate(self.total, self.nodes, self.eps)

    def absorb(self, batch: np.ndarray) -> None:
        values = np.asarray(batch)
        self.n += len(values)
        self._seen += len(values)
        if (p := self._early) is not None and len(values):
            self._draw = self._draw or np.random.default_rng([self.seed, len(values), int(abs(float(values[0])) * 100) % (1 << 31), int(abs(float(values.sum()))) % (1 << 31)])
            values = values[self._draw.random(len(values)) < p]
        self._values.append(values)

    def local_finalize(self) -> None:
        """Sample, sort, and rank once. Exact ranks need the node's values in order, estimated ones only the sample."""
        if not self._values:
            return
        data, self._values = np.sort(np.concatenate(self._values)), []
        size, self._seen, self._draw = self._seen, 0, None
        if (p := self._early) is not None:
            self.samples.append(Sample(data, np.arange(len(data)) / p, p, size))
            return
        total = self.total or self.n
        p = self.p or (theory.sample_rate_of_node if self.mode != "flat" else lambda s, n, k, e: theory.sample_rate(n, k, e))(len(data), total, self.nodes, self.eps)
        rng = np.random.default_rng([self.seed, len(data), int(abs(float(data[0])) * 100) % (1 << 31), int(abs(float(data.sum()))) % (1 << 31)])
        values = data[rng.random(len(data)) < p]
        ranks = np.searchsorted(data, values, side="right") - 1.0 if self.rank_mode == "exact" else np.arange(len(values)) / p
        self.samples.append(Sample(values, ranks, p, len(data)))

    def merge(self, other: RankSampleSet) -> None:
        self.local_finalize()
        other.local_finalize()
        self.samples += other.samples
        self.n += other.n
        self.total = max(self.total, other.total)
        if self.mode != "flat":
            self.compress()

    def compress(self) -> None:
        total, k, e = self.total or self.n, self.nodes, float(self.eps)
        rng = np.random.default_rng([self.seed, self.n, len(self.samples)])
        limit = total / np.sqrt(k)
        small = [s for s in self.samples if s.size < limit]
        large = [s for s in self.samples if s.size >= limit]
        if small and sum(s.size for s in small) >= limit:
            large.append(pooled(small, 1 / (e * sum(s.size for s in small)), rng))
            small = []
        classes: dict[int, list[Sample]] = {}
        for s in large:
            classes.setdefault(theory.sample_class(s.size, total, k), []).append(s)
        c = 0
        while c <= max(classes, default=-1):
            held = classes.get(c, [])
            while len(held) > 1:
                pair = [held.pop(), held.pop()]
                classes.setdefault(c + 1, []).append(pooled(pair, 1 / (e * sum(s.size for s in pair)), rng))
            c += 1
        self.samples = small + [s for held in classes.values() for s in held]

    def leave_component(self, components: int) -> None:
        """At the border of a component: its samples become one, thinned to the rate of a flat merge of so many nodes, or to
        the lowest rate among them. From here on samples add up."""
        self.local_finalize()
        if self.samples:
            p = min([theory.sample_rate(self.total or self.n, components, self.eps), *(s.p for s in self.samples)])
            self.samples = [pooled(self.samples, p, np.random.default_rng([self.seed, self.n, len(self.samples), components]))]
        self.mode = "flat"

    def query(self, phis) -> list:
        self.local_finalize()
        values = np.unique(np.concatenate([s.values for s in self.samples])) if self.samples else np.zeros(0)
        if not len(values):
            return [None] * len(phis)
        ranks = self.global_rank(values)
        return [values[int(abs(ranks - target(p, self.n)).argmin())].item() for p in phis]

    def global_rank(self, x: np.ndarray) -> np.ndarray:
        return sum((s.rank(x) for s in self.samples), np.zeros(len(x)))

    def rank(self, x) -> tuple[int, int]:
        r = float(self.global_rank(np.array([x]))[0])
        return int(r), int(r)

    def __len__(self) -> int:
        return sum(len(s.values) for s in self.samples)

    def pack(self) -> bytes:
        self.local_finalize()
        empty = [np.zeros(0)]
        self.values, self.ranks = (np.concatenate([getattr(s, k).astype(float) for s in self.samples] or empty) for k in ("values", "ranks"))
        self.lengths, self.sizes = (np.array([f(s) for s in self.samples], np.int64) for f in (lambda s: len(s.values), lambda s: s.size))
        self.rates = np.array([s.p for s in self.samples], float)
        return super().pack()

    def restore(self, head, arrays) -> None:
        super().restore(head, arrays)
        cuts = np.cumsum(self.lengths)[:-1]
        split = lambda a: np.split(a, cuts) if len(self.lengths) else []
        self.samples = [Sample(v, r, float(p), int(s)) for v, r, p, s in zip(split(self.values), split(self.ranks), self.rates, self.sizes, strict=True)]
