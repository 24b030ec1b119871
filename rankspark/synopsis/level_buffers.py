"""Levelled buffers: sorted buffers of s items on a hierarchy; an item on a level of value l stands for 2**l values.

Arriving items are thinned to the rate of the active level and staged; a full stage becomes a buffer. When no buffer is
free, the two buffers of the lowest level with two are merged: half of their items go one level up."""

from __future__ import annotations

import numpy as np

from rankspark import theory
from rankspark.params import target

from .base import Synopsis


class LevelBuffers(Synopsis):
    method = "levels"
    parts = ("items", "lengths", "values_of_levels", "stage")
    scalars = ("seed", "choice", "active", "normalise")

    def __init__(self, eps, seed: int = 0, choice: str = "alternate", normalise: bool = False):
        super().__init__(eps)
        self.seed, self.choice, self.normalise, self.active = seed, choice, normalise, 0
        self.height, self.most, self.size, self.constant = theory.level_parameters(self.eps)
        self.buffers: list[tuple[int, np.ndarray]] = []  # (value of the level, sorted items)
        self.stage = np.zeros(0)
        self.rng = np.random.default_rng(seed)

    def absorb_one(self, v) -> None:
        self.absorb(np.array([v]))

    def absorb(self, batch: np.ndarray) -> None:
        at = 0
        while at < len(batch):
            # what is still wanted, at the present rate; the rate may rise when the stage fills
            need = self.size - len(self.stage)
            piece = batch[at : at + (need << self.active)]
            drawn = np.ones(len(piece), bool) if not self.active else self.rng.random(len(piece)) < 0.5**self.active
            kept = piece[drawn]
            if len(kept) > need:
                piece = piece[: int(np.flatnonzero(drawn)[need - 1]) + 1]
                kept = kept[:need]
            at += len(piece)
            self.n += len(piece)
            self.stage = np.concatenate([self.stage, kept.astype(float)])
            if len(self.stage) >= self.size:
                self._flush()

    def _flush(self) -> None:
        self._place(self.active, np.sort(self.stage))
        self.stage = np.zeros(0)
        self._raise(theory.active_level(self.constant, self.n))

    def _raise(self, level: int) -> None:
        """A higher active level thins what is staged by a half for each step."""
        if level > self.active:
            self.stage = self.stage[self.rng.random(len(self.stage)) < 0.5 ** (level - self.active)]
            self.active = level

    def _place(self, level: int, items: np.ndarray) -> None:
        while len(self.buffers) >= self.most:
            self._free()
        if len(items):
            self.buffers.append((level, items))

    def _free(self) -> None:
        levels = sorted(lv for lv, _ in self.buffers)
        twice = [lv for lv in levels if levels.count(lv) > 1]
        if twice:
            a, b = [x for x in self.buffers if x[0] == twice[0]][:2]
            low = twice[0]
        else:  # no level holds two: the lower buffer is thinned to the weight of the next
            a, b = sorted(self.buffers, key=lambda x: x[0])[:2]
            low = b[0]
        self.buffers = [x for x in self.buffers if x is not a and x is not b]
        if a[0] < low:
            a = (low, a[1][self.rng.random(len(a[1])) < 0.5 ** (low - a[0])])
        self.buffers.append((low + 1, self._half(np.sort(np.concatenate([a[1], b[1]])))))

    def _half(self, both: np.ndarray) -> np.ndarray:
        if self.choice == "alternate":
            return both[int(self.rng.integers(2)) :: 2]
        return np.sort(self.rng.choice(both, len(both) // 2, replace=False)) if len(both) > 1 else both

    def merge(self, other: LevelBuffers) -> None:
        """The active level follows from both sizes. Stages and buffers below it are thinned into a pool, which fills new
        buffers at that level; the others keep their levels, and two of a level merge when room is needed."""
        self.n += other.n
        level = theory.active_level(self.constant, self.n)
        level = max(level, self.active, other.active)
        pool = [s.stage[self.rng.random(len(s.stage)) < 0.5 ** (level - s.active)] for s in (self, other)]
        held = self.buffers + other.buffers
        self.buffers = []
        self.active = level
        for lv, items in held:
            if lv < level:
                pool.append(items[self.rng.random(len(items)) < 0.5 ** (level - lv)])
        for lv, items in sorted((x for x in held if x[0] >= level), key=lambda x: x[0]):
            self._place(lv, items)
        rest = np.concatenate(pool)
        self.rng.shuffle(rest)
        while len(rest) >= self.size:
            self._place(level, np.sort(rest[: self.size]))
            rest = rest[self.size :]
        self.stage = rest

    def weighted(self) -> tuple[np.ndarray, np.ndarray]:
        held = [*self.buffers, (self.active, self.stage)]
        v, w = np.concatenate([i for _, i in held]), np.concatenate([np.full(len(i), 2.0**lv) for lv, i in held])
        order = np.argsort(v, kind="stable")
        return v[order], w[order]

    def query(self, phis, bound: str = "gt") -> list:
        """The first item before which the running weight reaches (ge) or passes with its own (gt) the target."""
        v, w = self.weighted()
        if not len(v):
            return [None] * len(phis)
        scale = self.n / w.sum() if self.normalise else 1.0
        total = np.cumsum(w) * scale
        goal = [target(p, self.n) if bound == "gt" else p[0] * self.n / p[1] for p in phis]
        at = np.searchsorted(total if bound == "gt" else total - w * scale, goal, side="right" if bound == "gt" else "left")
        return [v[min(int(i), len(v) - 1)].item() for i in at]

    def rank(self, x) -> tuple[int, int]:
        v, w = self.weighted()
        r = int(w[v <= x].sum())
        return r, r

    def __len__(self) -> int:
        return sum(len(i) for _, i in self.buffers) + len(self.stage)

    def pack(self) -> bytes:
        self.items = np.concatenate([i for _, i in self.buffers] or [np.zeros(0)])
        self.lengths = np.array([len(i) for _, i in self.buffers], np.int64)
        self.values_of_levels = np.array([lv for lv, _ in self.buffers], np.int64)
        return super().pack()

    def restore(self, head, arrays) -> None:
        super().restore(head, arrays)
        split = np.split(self.items, np.cumsum(self.lengths)[:-1]) if len(self.lengths) else []
        self.buffers = list(zip(self.values_of_levels.tolist(), split, strict=True))
        self.rng = np.random.default_rng([self.seed, self.n])
