"""Bounds and rules that the summaries are sized by and judged against."""

from __future__ import annotations

from fractions import Fraction
from math import ceil, floor, log2, sqrt


def slack(eps: Fraction, n: int) -> int:
    """Largest g + delta of a gap-tuple summary: floor(2 eps n)."""
    return floor(2 * eps * n)


def gap_bound(eps: Fraction, n: int) -> float:
    return max(1.0, float(1 / eps) * log2(max(2.0, float(eps * n))))


def digest_threshold(eps: Fraction, n: int, bits: int) -> int:
    return floor(eps * n / max(1, bits))


def digest_bound(eps: Fraction, bits: int) -> float:
    return float(3 * bits / eps)


def sample_rate(n: int, k: int, eps: Fraction) -> float:
    """sqrt(k) / (eps n), at most 1."""
    return min(1.0, sqrt(k) / (float(eps) * n)) if n else 1.0


def sample_rate_of_node(size: int, n: int, k: int, eps: Fraction) -> float:
    """A node with n / sqrt(k) values or more sends about 1 / eps of them."""
    return min(1.0, 1 / (float(eps) * size)) if size * sqrt(k) >= n and size else sample_rate(n, k, eps)


def sample_class(size: int, n: int, k: int) -> int:
    """-1: small; else floor(log2(size sqrt(k) / n)), found by integers: 4**c n**2 <= size**2 k."""
    c, left = -1, size * size * k
    while left >= n * n * 4 ** (c + 1) and n:
        c += 1
    return c


def tree_height(k: int, fan_in: int) -> int:
    """Levels of merges until k nodes are one; at least 1."""
    h = 0
    while k > 1:
        k, h = -(-k // fan_in), h + 1
    return max(1, h)


def rank_variance(k: int, p: float) -> float:
    return k / p**2


def tree_cost(k: int, h: int, eps: Fraction) -> dict[str, float]:
    """Values sent by the flat, the tree and the component form of the rank sample."""
    return {"flat": sqrt(k) / float(eps), "tree": h * sqrt(k) / float(eps), "components": sqrt(k * h) / float(eps)}


def level_parameters(eps: Fraction) -> tuple[int, int, int, float]:
    """Height, buffers, buffer size and the constant of the active level, from the error alone (base-2 logarithms)."""
    e = log2(1 / float(eps))
    return floor(e), floor(e) + 1, max(1, floor(float(1 / eps) * sqrt(e))), 1 - 2 * e - log2(e) / 2


def active_level(constant: float, n: int) -> int:
    return max(0, ceil(constant + log2(n + 1)))


def levels_hold(eps: Fraction, n: int) -> bool:
    """Whether levelled buffers of this error keep every one of n values."""
    _, most, size, constant = level_parameters(eps)
    return n <= most * size and active_level(constant, n) == 0
