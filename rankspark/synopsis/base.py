"""The contract that all summaries share: build, merge, estimate, and travel as bytes."""

from __future__ import annotations

import json
from fractions import Fraction

import numpy as np

from rankspark.params import fraction, target


class Synopsis:
    """A summary of a multiset of n values. Subclasses keep arrays named in `parts` and scalars named in `scalars`."""

    method = "none"
    parts: tuple[str, ...] = ()
    scalars: tuple[str, ...] = ()

    def __init__(self, eps: Fraction | float | str):
        self.eps, self.n = fraction(eps), 0

    # build
    def begin_chunk(self) -> None:
        """Called before the first batch of a partition."""

    def absorb(self, batch: np.ndarray) -> None:
        for v in batch.tolist():
            self.absorb_one(v)

    def absorb_one(self, v) -> None:
        raise NotImplementedError

    def absorb_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        self.absorb(np.repeat(values, weights))

    def end_chunk(self) -> None:
        """Called after the last batch of a partition."""

    # merge and estimate
    def merge(self, other: Synopsis) -> None:
        raise NotImplementedError

    def compress(self) -> None:
        pass

    def local_finalize(self) -> None:
        """Called once before a partial summary leaves its worker."""

    def query(self, phis: list[tuple[int, int]]) -> list:
        raise NotImplementedError

    def rank(self, x) -> tuple[int, int]:
        """Bounds of the number of values <= x."""
        raise NotImplementedError

    def __len__(self) -> int:
        return sum(len(getattr(self, p)) for p in self.parts[:1])

    # travel
    def pack(self) -> bytes:
        """A version byte, a JSON header, then the arrays as little-endian buffers."""
        arrays = [np.ascontiguousarray(getattr(self, p)) for p in self.parts]
        head = json.dumps({
            "m": self.method, "e": [self.eps.numerator, self.eps.denominator], "n": self.n,
            "a": [[a.dtype.newbyteorder("<").str, len(a)] for a in arrays], "s": {k: getattr(self, k) for k in self.scalars},
        }).encode()
        return b"\x01" + len(head).to_bytes(4, "little") + head + b"".join(a.astype(a.dtype.newbyteorder("<")).tobytes() for a in arrays)

    def restore(self, head: dict, arrays: list[np.ndarray]) -> None:
        self.n = head["n"]
        for name, a in zip(self.parts, arrays, strict=True):
            setattr(self, name, a)
        for name in self.scalars:
            setattr(self, name, head["s"][name])


def read_header(payload: bytes) -> tuple[dict, list[np.ndarray]]:
    if payload[:1] != b"\x01":
        raise ValueError("unknown version of a summary")
    size = int.from_bytes(payload[1:5], "little")
    head, at, arrays = json.loads(payload[5 : 5 + size]), 5 + size, []
    for kind, n in head["a"]:
        a = np.frombuffer(payload, dtype=kind, count=n, offset=at)
        arrays.append(a.copy())
        at += a.nbytes
    return head, arrays


def weighted_answers(values: np.ndarray, weights: np.ndarray, n: int, phis: list[tuple[int, int]]) -> list:
    """For each quantile the first value whose running weight exceeds its 0-based target."""
    if not len(values):
        return [None] * len(phis)
    total = np.cumsum(weights)
    at = [min(len(values) - 1, int(np.searchsorted(total, target(p, n), side="right"))) for p in phis]
    return [values[i].item() for i in at]
