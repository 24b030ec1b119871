"""Dyadic digests over integers 0 .. 2**bits - 1: counters on the nodes (level, index) of a binary tree of intervals.

The batch digest counts leaves first and folds poor triples (two children and their parent) upwards, level by level. The
online digest keeps a tree from the start: an item goes to its lowest node that exists, or to a new child below it."""

from __future__ import annotations

import numpy as np

from rankspark import theory
from rankspark.params import target

from .base import Synopsis


class DyadicDigest(Synopsis):
    method = "digest.batch"
    parts = ("level", "index", "count")
    scalars = ("bits", "sweeps", "smallest", "largest")
    #: Counts that wait to be added up, and nodes held before an early compression, both at least; from there sizes must double.
    MOST_PENDING, MOST_NODES = 1 << 20, 1 << 21

    def __init__(self, eps, bits: int = 20, sweeps: str = "one"):
        super().__init__(eps)
        self.bits, self.sweeps, self.smallest, self.largest = bits, sweeps, None, None
        self._waiting, self._room = 0, self.MOST_NODES
        self.level, self.index, self.count = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self._pending: list[tuple[np.ndarray, np.ndarray]] = []

    @property
    def threshold(self) -> int:
        return theory.digest_threshold(self.eps, self.n, self.bits)

    def _range(self, values: np.ndarray) -> None:
        low, high = int(values.min()), int(values.max())
        if low < 0 or high >= 1 << self.bits:
            raise ValueError("a value lies outside the universe")
        self.smallest = low if self.smallest is None else min(self.smallest, low)
        self.largest = high if self.largest is None else max(self.largest, high)

    def absorb(self, batch: np.ndarray) -> None:
        if len(batch):
            self.absorb_weighted(*np.unique(batch.astype(np.int64), return_counts=True))

    def absorb_one(self, v) -> None:
        self.absorb(np.array([v]))

    def absorb_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        if len(values):
            self._range(values)
            self._pending.append((values.astype(np.int64), weights.astype(np.int64)))
            self.n += int(weights.sum())
            self._waiting += len(values)
            if self._waiting > max(self.MOST_PENDING, len(self.index)):
                self._bound()

    def _bound(self) -> None:
        """Memory follows the distinct values, and past MOST_NODES the digest: a node folded early has at most the threshold
        of that time, which only grows, so the error stays below eps."""
        self._gather()
        if len(self.index) > self._room:
            self.compress()
            self._room = max(self.MOST_NODES, 2 * len(self.index))

    def _gather(self) -> None:
        if self._pending:
            v = np.concatenate([self.index, *[p[0] for p in self._pending]])
            lv = np.concatenate([self.level, np.zeros(len(v) - len(self.level), np.int64)])
            self._set(lv, v, np.concatenate([self.count, *[p[1] for p in self._pending]]))
            self._pending, self._waiting = [], 0

    def _set(self, level, index, count) -> None:
        """Equal nodes add up; empty ones go. Kept in order of (level, index)."""
        order = np.lexsort((index, level))
        level, index, count = level[order], index[order], count[order]
        new = np.concatenate([[True], (np.diff(level) != 0) | (np.diff(index) != 0)]) if len(level) else np.zeros(0, bool)
        at = np.flatnonzero(new)
        count = np.add.reduceat(count, at) if len(at) else count
        keep = count > 0
        self.level, self.index, self.count = level[at][keep], index[at][keep], count[keep]

    def end_chunk(self) -> None:
        self._gather()
        self.compress()

    local_finalize = end_chunk

    def compress(self) -> None:
        self._gather()
        if self.threshold < 1:
            return
        while self._sweep() and self.sweeps == "fixpoint":
            pass

    def _sweep(self) -> bool:
        by_level = {int(lv): (self.index[self.level == lv], self.count[self.level == lv]) for lv in np.unique(self.level)}
        none, changed = (np.zeros(0, np.int64), np.zeros(0, np.int64)), False
        for lv in range(self.bits):
            index, count = by_level.get(lv, none)
            if not len(index):
                continue
            p_index, p_count = by_level.get(lv + 1, none)
            parents, back = np.unique(index >> 1, return_inverse=True)
            own = np.zeros(len(parents), np.int64)
            if len(p_index):
                at = np.minimum(np.searchsorted(p_index, parents), len(p_index) - 1)
                own = np.where(p_index[at] == parents, p_count[at], 0)
            triple = np.bincount(back, count, len(parents)).astype(np.int64) + own
            poor = triple <= self.threshold
            if not poor.any():
                continue
            changed = True
            stay = ~poor[back]
            by_level[lv] = (index[stay], count[stay])
            others = ~np.isin(p_index, parents[poor])
            i = np.concatenate([p_index[others], parents[poor]])
            order = np.argsort(i)
            by_level[lv + 1] = (i[order], np.concatenate([p_count[others], triple[poor]])[order])
        self.level = np.concatenate([np.full(len(i), lv, np.int64) for lv, (i, _) in sorted(by_level.items())])
        self.index, self.count = (np.concatenate([by_level[lv][k] for lv in sorted(by_level)]) for k in (0, 1))
        return changed

    def merge(self, other: DyadicDigest) -> None:
        self._gather()
        other._gather()
        while self.bits < other.bits:
            self.grow()
        while other.bits < self.bits:
            other.grow()
        self.n += other.n
        self.eps = max(self.eps, other.eps)
        for name, f in (("smallest", min), ("largest", max)):
            known = [x for x in (getattr(self, name), getattr(other, name)) if x is not None]
            setattr(self, name, f(known) if known else None)
        self._set(*(np.concatenate([getattr(self, p), getattr(other, p)]) for p in self.parts))
        self.compress()

    def grow(self) -> None:
        """Twice the universe: a new root takes the old one as its left child."""
        self.bits += 1

    def pack(self) -> bytes:
        self._gather()
        return super().pack()

    def _post_order(self):
        self._gather()
        high = ((self.index + 1) << self.level) - 1
        order = np.lexsort((self.level, high))
        return high[order], self.count[order]

    def query(self, phis) -> list:
        if not self.n:
            return [None] * len(phis)
        high, count = self._post_order()
        at = np.searchsorted(np.cumsum(count), [target(p, self.n) for p in phis], side="right")
        return [int(min(high[min(i, len(high) - 1)], self.largest)) for i in at]

    def rank(self, x) -> tuple[int, int]:
        self._gather()
        low, high = self.index << self.level, ((self.index + 1) << self.level) - 1
        return int(self.count[high <= x].sum()), int(self.count[low <= x].sum())

    def nodes(self) -> dict[tuple[int, int], int]:
        self._gather()
        return dict(zip(zip(self.level.tolist(), self.index.tolist(), strict=True), self.count.tolist(), strict=True))


def properties(d: DyadicDigest) -> tuple[bool, bool]:
    """(no inner node above the threshold, no triple below it): counts of a node, its parent and its sibling."""
    nodes, t = d.nodes(), d.threshold
    first = all(c <= t for (lv, _), c in nodes.items() if lv > 0)
    second = all(c + nodes.get((lv, i ^ 1), 0) + nodes.get((lv + 1, i >> 1), 0) > t for (lv, i), c in nodes.items() if lv < d.bits)
    return first, second


class OnlineDigest(DyadicDigest):
    """Past ONE_BY_ONE items, values wait until they are a quarter of those before them (or MOST_WAITING) and go down the tree
    together, by the threshold of the time when they began to wait: nodes hold no more than item by item. In a universe of at
    most DENSE_BITS, many values at once turn the tree into one array of counters for each level."""

    method = "digest.online"
    ONE_BY_ONE, MOST_WAITING, DENSE_BITS = 1 << 13, 1 << 20, 20
    scalars = (*DyadicDigest.scalars, "doubled_at")

    def __init__(self, eps, bits: int = 1, sweeps: str = "one"):
        super().__init__(eps, bits, sweeps)
        self.doubled_at = 1
        self._waited = self._entries = 0
        self._tree: dict[tuple[int, int], int] | None = None
        self._dense: list[np.ndarray] | None = None

    def _open(self) -> dict[tuple[int, int], int]:
        if self._tree is None:
            self._tree = dict(zip(zip(self.level.tolist(), self.index.tolist(), strict=True), self.count.tolist(), strict=True))
        return self._tree

    def _gather(self) -> None:
        self._flatten()
        self._settle()
        if self._dense is not None:
            at = [np.flatnonzero(c) for c in self._dense]
            self.level, self.index = np.repeat(np.arange(self.bits + 1), [len(i) for i in at]), np.concatenate(at)
            self.count, self._dense = np.concatenate([c[i] for c, i in zip(self._dense, at, strict=True)]), None

    def _settle(self) -> None:
        """What waits goes down the tree."""
        if not self._pending:
            return
        v, raw = np.concatenate([p[0] for p in self._pending]), all(p[1] is None for p in self._pending)
        w = None if raw else np.concatenate([np.ones(len(x), np.int64) if y is None else y for x, y in self._pending])
        self._pending, self._waiting = [], 0
        if self._dense is None and len(v) > 1 << 16 and self.bits <= self.DENSE_BITS:
            self._dense = [np.zeros(1 << (self.bits - lv), np.int64) for lv in range(self.bits + 1)]
            for lv, c in enumerate(self._dense):
                own = slice(*np.searchsorted(self.level, [lv, lv + 1]))
                c[self.index[own]] = self.count[own]
        if len(v) > 1 << 16 and self.bits <= 22:
            sums = np.bincount(v, w)  # exact in doubles below 2**53
            values = np.flatnonzero(sums)
            weights = sums[values].astype(np.int64)
        else:
            values, back = np.unique(v, return_inverse=True)
            weights = np.bincount(back, w).astype(np.int64)
        (self._sink if self._dense is None else self._sink_dense)(values, weights)

    def _sink_dense(self, values: np.ndarray, weights: np.ndarray) -> None:
        """The same as `_sink`, on the arrays of counters."""
        t, low = self._waited, np.full(1, self.bits, np.int8)
        for lv in range(self.bits - 1, -1, -1):
            low = np.repeat(low, 2)
            low[self._dense[lv] > 0] = lv
        begin, left, on = low[values], weights.copy(), np.zeros(0, np.int64)
        order, starts = np.argsort(begin, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(begin, minlength=self.bits + 1))])
        for lv in range(self.bits, 0, -1) if t >= 1 else ():
            if starts[lv + 1] > starts[lv]:
                came = order[starts[lv] : starts[lv + 1]]
                on = np.sort(np.concatenate([on, came])) if len(on) else came
            if not len(on):
                continue
            node = values[on] >> lv
            room = t - self._dense[lv][node]
            open_ = np.flatnonzero(room > 0)
            if not len(open_):
                continue
            at, node, room = on[open_], node[open_], room[open_]
            first = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
            size = np.diff(np.append(first, len(node)))
            upto = np.cumsum(left[at])
            upto -= np.repeat(upto[first] - left[at[first]], size)
            left[at] = np.clip(upto - room, 0, left[at])
            self._dense[lv][node[first]] += np.minimum(upto[first + size - 1], room[first])
            on = on[left[on] > 0]
        self._dense[0][values] += left

    def _fold(self) -> None:
        """`compress`, on the arrays of counters if they are in use."""
        if self._dense is None:
            self.compress()
            return
        t, changed = self.threshold, True
        while t >= 1 and changed:
            changed = False
            for lv in range(self.bits):
                c, above = self._dense[lv].reshape(-1, 2), self._dense[lv + 1]
                pair = c[:, 0] + c[:, 1]
                poor = np.flatnonzero((pair > 0) & (pair + above <= t))
                if len(poor):
                    above[poor] += pair[poor]
                    c[poor] = 0
                    changed = self.sweeps == "fixpoint"

    def _sink(self, values: np.ndarray, weights: np.ndarray) -> None:
        """Sorted values down the tree: from its lowest node that exists each fills the nodes on its way up to the threshold."""
        t, begin = self._waited, np.full(len(values), self.bits)
        ends = np.searchsorted(self.level, np.arange(self.bits + 2))
        open_ = np.arange(len(values))
        for lv in range(self.bits + 1):
            index = self.index[ends[lv] : ends[lv + 1]]
            if len(index) and len(open_):
                want = values[open_] >> lv
                found = index[np.minimum(np.searchsorted(index, want), len(index) - 1)] == want
                begin[open_[found]] = lv
                open_ = open_[~found]
        added, left = [(self.level, self.index, self.count)], weights.copy()
        for lv in range(self.bits, 0, -1):
            on = np.flatnonzero((begin >= lv) & (left > 0))
            if not len(on) or t < 1:
                continue
            node = values[on] >> lv
            first = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
            nodes, size = node[first], np.diff(np.append(first, len(node)))
            index, have = self.index[ends[lv] : ends[lv + 1]], np.zeros(len(nodes), np.int64)
            if len(index):
                near = np.minimum(np.searchsorted(index, nodes), len(index) - 1)
                have = np.where(index[near] == nodes, self.count[ends[lv] : ends[lv + 1]][near], 0)
            upto = np.cumsum(left[on])
            upto -= np.repeat(upto[first] - left[on][first], size)
            room = np.repeat(np.maximum(0, t - have), size)
            left[on] = np.clip(upto - room, 0, left[on])
            took = np.minimum(upto[first + size - 1], room[first])
            added.append((np.full(len(nodes), lv, np.int64), nodes, took))
        on = np.flatnonzero(left)
        added.append((np.zeros(len(on), np.int64), values[on], left[on]))
        self._set(*(np.concatenate(x) for x in zip(*added, strict=True)))

    def _flatten(self) -> None:
        if self._tree is not None:
            keys = np.array(list(self._tree), dtype=np.int64).reshape(-1, 2)
            counts = np.array(list(self._tree.values()), dtype=np.int64)
            self._tree = None
            self._set(keys[:, 0], keys[:, 1], counts)

    def absorb(self, batch: np.ndarray) -> None:
        batch = batch.astype(np.int64, copy=False)
        if len(batch) and self.n < self.ONE_BY_ONE:
            first, batch = batch[: self.ONE_BY_ONE - self.n], batch[self.ONE_BY_ONE - self.n :]
            self.absorb_weighted(*np.unique(first, return_counts=True))
        if len(batch):
            self._reach(batch)
        at = 0
        while at < len(batch):  # as far as values may wait
            before = self.n - self._waiting
            piece = batch[at : at + max(1, min(before // 4 + 1 - self._waiting, self.MOST_WAITING + 1 - (self._entries if self._pending else 0)))]
            self._wait(piece, None, len(piece))
            at += len(piece)

    def absorb_one(self, v) -> None:
        self.absorb_weighted(np.array([v], dtype=np.int64), np.array([1], dtype=np.int64))

    def absorb_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        """As inserting each value as often as its weight says: every node on the way fills up to the threshold, the rest goes to the leaf."""
        if not len(values):
            return
        self._reach(values)
        if self.n >= self.ONE_BY_ONE:
            self._wait(values.astype(np.int64), weights.astype(np.int64), int(weights.sum()))
            return
        for e, w in zip(values.tolist(), weights.tolist(), strict=True):
            self.n += w
            tree = self._open()
            t = self.threshold
            lv = next((lv for lv in range(self.bits + 1) if (lv, e >> lv) in tree), None)
            if lv is None:
                lv = self.bits
                tree[lv, 0] = 0
            while w:
                node = (lv, e >> lv)
                have = tree.get(node, 0)
                take = w if lv == 0 else max(0, min(w, t - have))  # with a threshold of 0 all go to the leaf
                tree[node] = have + take
                w -= take
                lv -= 1
            if self.n >= 2 * self.doubled_at:
                self.doubled_at = self.n
                self.compress()

    def _reach(self, values: np.ndarray) -> None:
        """The universe grows until it holds the values."""
        if int(values.max()) >= 1 << self.bits:
            self._gather()
        while int(values.max()) >= 1 << self.bits:
            self.grow()
        self._range(values)

    def _wait(self, values: np.ndarray, weights: np.ndarray | None, weight: int) -> None:
        if not self._pending:
            self._flatten()
            self._waited, self._entries = self.threshold, 0
        self._entries += len(values)
        self._pending.append((values, weights))
        self.n += weight
        self._waiting += weight
        if 5 * self._waiting > self.n or self._entries > self.MOST_WAITING:
            self._settle()
            if self.n >= 2 * self.doubled_at:
                self.doubled_at = self.n
                self._fold()
