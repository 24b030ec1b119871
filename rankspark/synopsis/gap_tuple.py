"""Gap-tuple summary: tuples (v, g, delta) whose running sums of g bracket ranks.

The 1-based rank of v[i] lies between sum(g[..i]) and that plus delta[i], and g + delta never exceeds floor(2 eps n).

Ways to insert: "plain" (one tuple per item, compression each ceil(1 / (2 eps)) items), "mixed" (an item that could be
removed at once only adds weight to its successor; compression when the list has doubled), "adaptive" (after each item the
cheapest removable tuple goes), and "batch" (a sorted batch of exact tuples is merged; the way for large data)."""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from fractions import Fraction
from math import ceil, log2
from operator import add

import numpy as np

from rankspark import theory
from rankspark.params import target

from .base import Synopsis


def capacity(delta: np.ndarray, p: int, two_eps_n: float) -> np.ndarray:
    """The class of each delta for the bound p: largest for delta 0, 0 for delta p, and classes twice as wide from one to
    the next between them. The classes tile the range without holes."""
    out = np.zeros(len(delta), dtype=np.int64)
    for a in range(1, ceil(log2(p)) + 1 if p > 1 else 1):
        upper, lower = p - 2 ** (a - 1) - p % 2 ** (a - 1), p - 2**a - p % 2**a
        out[(delta > lower) & (delta <= upper)] = a
    out[delta == 0] = ceil(log2(two_eps_n)) + 1 if two_eps_n > 1 else 1
    out[(delta == p) & (delta > 0)] = 0
    return out


class GapSummary(Synopsis):
    method = "gap"
    parts = ("v", "g", "delta")
    scalars = ("mode", "slack", "compressed_at", "bands")

    def __init__(self, eps, mode: str = "batch", slack: str = "strict", bands: bool = False):
        super().__init__(eps)
        self.mode, self.slack, self.bands, self.compressed_at = mode, slack, bands, 0
        self.v, self.g, self.delta = np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self._lists: tuple[list, list, list] | None = None
        self._step = 64

    @property
    def most(self) -> int:
        return theory.slack(self.eps, self.n)

    def _open(self) -> tuple[list, list, list]:
        if self._lists is None:
            self._lists = (self.v.tolist(), self.g.tolist(), self.delta.tolist())
        return self._lists

    def _close(self) -> None:
        if self._lists is not None:
            v, g, d = self._lists
            self.v, self.g, self.delta, self._lists = np.array(v), np.array(g, np.int64), np.array(d, np.int64), None

    def tuples(self) -> list[tuple]:
        self._close()
        return list(zip(self.v.tolist(), self.g.tolist(), self.delta.tolist(), strict=True))

    def __len__(self) -> int:
        return len(self._lists[0]) if self._lists is not None else len(self.v)

    # ---- building

    def absorb(self, batch: np.ndarray) -> None:
        if self.mode == "mixed":
            self._absorb_mixed(batch)
        elif self.mode != "batch":
            super().absorb(batch)
        elif len(batch):
            values, weights = np.unique(batch, return_counts=True)
            self.absorb_weighted(values, weights)

    def absorb_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        """Sorted distinct values. A run of equal values is a tuple of weight 1 and tuples that carry the others, so ranks stay exact."""
        if not len(values):
            return
        self._close()
        n = self.n + int(weights.sum())
        most = max(1, theory.slack(self.eps, n))
        more = -(-(weights - 1) // most)
        each = np.repeat(values, 1 + more)
        g = np.full(len(each), most, dtype=np.int64)
        first = np.cumsum(1 + more) - (1 + more)
        g[first] = 1
        last = first + more
        g[last] = np.where(more > 0, weights - 1 - (more - 1) * most, 1)
        batch = GapSummary(self.eps)
        batch.v, batch.g, batch.delta, batch.n = each, g, np.zeros(len(each), np.int64), int(weights.sum())
        if not self.compressed_at:
            self.compressed_at = ceil(1 / (2 * self.eps))
        self._interleave(batch)
        if len(self.v) > 2 * self.compressed_at:
            self.compress()

    def absorb_one(self, v) -> None:
        values, g, d = self._open()
        period = ceil(1 / (2 * self.eps))
        if self.mode == "plain" and (self.n + 1) % period == 0 and values:
            self.n += 1  # the arriving item counts in the bound
            self.compress()
            self.n -= 1
            values, g, d = self._open()
        at = bisect_right(values, v)
        self.n += 1
        inner = 0 < at < len(values)
        if inner and self.mode == "mixed" and 1 + g[at] + d[at] <= self.most:
            g[at] += 1
            return
        inherited = g[at] + d[at] - 1 if inner else 0
        values.insert(at, v)
        g.insert(at, 1)
        d.insert(at, inherited)
        if self.mode == "mixed" and len(values) >= 2 * max(period, self.compressed_at):
            self.compress()
        if self.mode == "adaptive" and len(values) > 2:
            cost = np.array(g[1:-1]) + np.array(g[2:]) + np.array(d[2:])
            i = int(cost.argmin())
            if cost[i] <= self.most:
                g[i + 2] += g[i + 1]
                for a in (values, g, d):
                    del a[i + 1]

    def _absorb_mixed(self, batch: np.ndarray) -> None:
        """The same tuples as one item at a time. The items of a piece that all find room in their gap only add weight, and
        a run of items past the end is appended, both as arrays; what is left goes item by item."""
        at, period = 0, ceil(1 / (2 * self.eps))
        while at < len(batch) and self.n < 64:
            self.absorb_one(batch[at].item())
            at += 1
        num, den = 2 * self.eps.numerator, self.eps.denominator
        while at < len(batch):
            self._close()
            held, full = len(self.v), 2 * max(period, self.compressed_at)
            piece = batch[at : at + self._step]
            place = np.searchsorted(self.v, piece, side="right")
            if place[0] == held:
                inside, falls = np.flatnonzero(place < held), np.flatnonzero(piece[1:] < piece[:-1])
                run = min(inside[0] if len(inside) else len(piece), falls[0] + 1 if len(falls) else len(piece))
                if run > 3 and self.slack == "strict" and not self.delta.any():
                    self._append_run(piece[:run], period)
                    at, self._step = at + int(run), min(1 << 16, 2 * self._step)
                    continue
            counts, room = np.bincount(place, minlength=held + 1), np.full(held + 1, -1)
            room[1:held] = num * (self.n + 1) // den - self.g[1:] - self.delta[1:]
            crowded = (counts > room)[place]
            left = np.flatnonzero(crowded)
            if not len(left):
                self.g += counts[:held]
                self.n, at, self._step = self.n + len(piece), at + len(piece), min(1 << 16, 2 * self._step)
                continue
            gaps: dict[int, tuple[list, list, list]] = {}
            more: dict[int, int] = {}  # weight that the old tuple on the right of a gap takes
            new, cut = 0, len(piece)
            for i, gap, x in zip(left.tolist(), place[left].tolist(), piece[left].tolist(), strict=True):
                v, g, d = gaps.get(gap) or gaps.setdefault(gap, ([], [], []))
                j, last = bisect_right(v, x), False
                if j < len(v):
                    weight, slack, inner = g[j], d[j], gap > 0 or j > 0
                elif gap < held:
                    weight, slack, inner, last = int(self.g[gap]) + more.get(gap, 0), int(self.delta[gap]), gap > 0 or j > 0, True
                else:
                    weight, slack, inner = 0, 0, False
                if inner and 1 + weight + slack <= num * (self.n + i + 1) // den:
                    if last:
                        more[gap] = more.get(gap, 0) + 1
                    else:
                        g[j] += 1
                    continue
                v.insert(j, x)
                g.insert(j, 1)
                d.insert(j, weight + slack - 1 if inner else 0)
                new += 1
                if held + new >= full:
                    cut = i + 1
                    break
            self.g += np.bincount(place[:cut][~crowded[:cut]], minlength=held + 1)[:held]
            if more:
                self.g[list(more)] += np.array(list(more.values()))
            if new:
                where = np.repeat(list(gaps), [len(x[0]) for x in gaps.values()])
                self.v, self.g, self.delta = (np.insert(old, where, np.array([y for x in gaps.values() for y in x[k]], old.dtype)) for k, old in enumerate((self.v, self.g, self.delta)))
            self.n, at = self.n + cut, at + cut
            if new and len(self.v) >= full:
                self.compress()
            self._step = max(64, self._step // 2) if len(left) * 8 > len(piece) else min(1 << 16, 2 * self._step) if len(left) * 32 < len(piece) else self._step

    def _append_run(self, run: np.ndarray, period: int) -> None:
        """Increasing items past the end of tuples that are all exact (delta 0), with the compressions on their way. New items
        are only a number until a compression cuts them into runs; it leaves older tuples as they are unless the bound has
        reached the least weight of two neighbours."""
        g, at, most_at, num, den = self.g.tolist(), list(range(len(self.v))), len(self.v), 2 * self.eps.numerator, self.eps.denominator
        end, new, least = most_at + len(run), 0, 0
        while most_at < end:
            full = 2 * max(period, self.compressed_at)
            k = min(end - most_at, max(1, full - len(g) - new))
            new, most_at, self.n = new + k, most_at + k, self.n + k
            if len(g) + new < full:
                continue
            most = num * self.n // den
            if len(g) + new > 2 and most > 1:
                runs, weight = divmod(new, most)
                if not weight:
                    runs, weight = runs - 1, most
                place = most_at - 1 - runs * most  # of the leftmost run, which takes older tuples
                while len(g) > 1 and weight + g[-1] <= most:
                    weight += g.pop()
                    at.pop()
                if most >= least:
                    before = len(g)
                    for i in [i for i, both in enumerate(map(add, g[1:], g[2:]), 1) if both <= most][::-1]:
                        if i + 1 >= before:  # a run further right took this pair's right tuple
                            continue
                        before, held = i, g[i + 1] + g[i]
                        while before > 1 and held + g[before - 1] <= most:
                            before -= 1
                            held += g[before]
                        g[before : i + 2] = [held]
                        del at[before : i + 1]
                    least = min(map(add, g[1:], g[2:]), default=1 << 62)
                if len(g) > 1:
                    least = min(least, g[-1] + weight)
                if runs:
                    least = min(least, weight + most)
                g += [weight] + [most] * runs
                at += range(place, most_at, most)
            else:
                g += [1] * new
                at += range(most_at - new, most_at)
                least = 0
            new, self.compressed_at = 0, max(len(g), period)
        g += [1] * new
        at += range(most_at - new, most_at)
        self.v = np.concatenate([self.v, run])[at]
        self.g, self.delta = np.array(g, np.int64), np.zeros(len(g), np.int64)

    # ---- compression

    def compress(self) -> None:
        self._close()
        if self.bands or self.mode in ("plain", "mixed"):
            self._compress_bands()
        else:
            self._compress_greedy()
        self.compressed_at = max(len(self.v), ceil(1 / (2 * self.eps)))

    def _compress_bands(self) -> None:
        """From right to left: a tuple and its descendants (the run on its left of smaller capacity) fold into the right
        neighbour if its capacity is not larger and the bound holds. The first and the last tuple stay."""
        if len(self.v) < 3:
            return
        two_eps_n = 2 * self.eps * self.n
        caps = capacity(self.delta, self.most, float(two_eps_n))
        strict = self.slack == "strict"
        if strict and (caps == caps[0]).all():  # no descendants: the same as without bands
            self._compress_greedy()
            return
        g, d, cap, total, most = self.g.tolist(), self.delta.tolist(), caps.tolist(), [0, *np.cumsum(self.g).tolist()], self.most
        start, stack = [1] * len(cap), []  # where the descendants of a tuple begin
        for i in range(1, len(cap)):
            while stack and cap[stack[-1]] < cap[i]:
                stack.pop()
            start[i] = stack[-1] + 1 if stack else 1
            stack.append(i)
        kept, weights = [], []
        now, weight, i = len(cap) - 1, g[-1], len(cap) - 2
        while i >= 1:
            j = start[i]
            together = total[i + 1] - total[j] + weight + d[now]
            if cap[i] <= cap[now] and (together <= most if strict else (together - 1) * two_eps_n.denominator < two_eps_n.numerator):
                weight += total[i + 1] - total[j]
                i = j - 1
            else:
                kept.append(now)
                weights.append(weight)
                now, weight = i, g[i]
                i -= 1
        at = np.array([now, *kept[::-1]]) if kept else np.array([now])
        at, self.g = np.concatenate([[0], at]), np.array([g[0], weight, *weights[::-1]], np.int64)
        self.v, self.delta = self.v[at], self.delta[at]

    def _compress_greedy(self) -> None:
        """Without bands: each kept tuple takes as many left neighbours as the bound allows, found on running sums."""
        n = len(self.v)
        if n < 3 or self.most < 2:
            return
        total, kept, i = np.concatenate([[0], np.cumsum(self.g)]), [], n - 1
        room = (total[1:] + self.delta - self.most).tolist()  # sums of g before the run must be at least this
        totals = total.tolist()
        while i >= 1:
            j = min(i, max(1, bisect_left(totals, room[i], 0, i + 1)))
            kept.append((i, j))
            i = j - 1
        kept.append((0, 0))
        at, start = (np.array(x)[::-1] for x in zip(*kept, strict=True))
        self.g = total[at + 1] - total[start]
        self.v, self.delta = self.v[at], self.delta[at]

    # ---- merging

    def _interleave(self, other: GapSummary) -> None:
        self._close()
        other._close()
        if not other.n:
            return
        if not self.n:
            self.v, self.g, self.delta, self.n = other.v, other.g, other.delta, other.n
            return
        grown = []
        for own, against, side in ((self, other, "left"), (other, self, "right")):
            near = np.searchsorted(against.v, own.v, side=side)  # the other side's first tuple that is not smaller
            inside = near < len(against.v)
            at = np.minimum(near, len(against.v) - 1)
            grown.append(own.delta + np.where(inside, against.g[at] + against.delta[at] - 1, against.delta[-1]))
        v = np.concatenate([self.v, other.v])
        order = np.argsort(v, kind="stable")
        self.v, self.g, self.delta = v[order], np.concatenate([self.g, other.g])[order], np.concatenate(grown)[order]
        self.n += other.n

    def merge(self, other: GapSummary) -> None:
        self.eps = max(self.eps, other.eps)
        self._interleave(other)
        self.compress()

    def pack(self) -> bytes:
        self._close()
        return super().pack()

    # ---- asking

    def ranks(self) -> tuple[np.ndarray, np.ndarray]:
        self._close()
        low = np.cumsum(self.g)
        return low, low + self.delta

    def query(self, phis, pick: str = "minimax", policy: str = "floor_plus_one") -> list:
        low, high = self.ranks()
        if not self.n:
            return [None] * len(phis)
        out = []
        for p in phis:
            r = target(p, self.n) + 1 if policy == "floor_plus_one" else -(-p[0] * self.n // p[1]) if policy == "ceil" else p[0] * self.n // p[1]
            if pick == "minimax":
                i = int(np.maximum(abs(r - low), abs(high - r)).argmin())
            elif pick == "min_slack":
                i = int((abs(r - low) + abs(high - r)).argmin())
            else:
                covers = np.flatnonzero((low <= r) & (r <= high))
                i = int(covers[0]) if len(covers) else int(np.maximum(abs(r - low), abs(high - r)).argmin())
            out.append(self.v[i].item())
        return out

    def rank(self, x) -> tuple[int, int]:
        low, high = self.ranks()
        k = int(np.searchsorted(self.v, x, side="right"))
        return (int(low[k - 1]) if k else 0), (int(high[k]) - 1 if k < len(high) else self.n)


def check_invariants(s: GapSummary, truth: np.ndarray | None = None) -> bool:
    low, high = s.ranks()
    good = int(low[-1]) == s.n and bool((np.diff(s.v) >= 0).all()) and (s.most < 1 or int((s.g + s.delta).max()) <= max(1, s.most))
    if truth is not None:
        data = np.sort(truth)
        first, last = np.searchsorted(data, s.v, "left") + 1, np.searchsorted(data, s.v, "right")
        good &= bool(((low <= last) & (high >= first)).all())
    return good


def exact_slack(eps: Fraction, n: int) -> bool:
    """Whether a summary at this error holds every item."""
    return theory.slack(eps, n) <= 1
