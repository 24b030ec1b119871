"""Shared parameters: quantile grids, value codecs, the generated columns of the experiments."""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The grid of the experiments, .05 to .95, as (num, den).
GRID = [(k, 20) for k in range(1, 20)]


def fraction(eps: float | str | Fraction) -> Fraction:
    """0.1 means one tenth, not the nearest binary fraction."""
    return eps if isinstance(eps, Fraction) else Fraction(str(eps))


def target(phi: tuple[int, int], n: int) -> int:
    """0-based place of a quantile in sorted order: floor(phi n), by integers."""
    return min(n - 1, phi[0] * n // phi[1])


@dataclass(frozen=True)
class ExecutionSpec:
    """How many partial summaries are built (None: one per input partition) and how many meet in a merge."""

    partitions: int | None = None
    fan_in: int = 32
    order: str = "stored"  # or "sorted": each partition in increasing order; "random": dealt by a hash
    pieces: int | None = None  # the input is packed (`engine.pack`) for so many partials, or for any divisor of that number


@dataclass(frozen=True)
class MethodSpec:
    method: str
    eps: Fraction
    options: dict = field(default_factory=dict)

    @staticmethod
    def of(method: str, eps: float | str | Fraction, **options) -> MethodSpec:
        return MethodSpec(method, fraction(eps), options)


def cents(column: str) -> Column:
    """A money column as whole cents."""
    return F.round(F.col(column) * 100).cast("long")


def q20() -> Column:
    """A 20-bit hash of a lineitem row, the same integers in every engine. The factor 2654435761 meets 16 bits at a time, so no product overflows."""
    row = F.pmod((F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 1009 + F.col("l_partkey") * 31 + F.col("l_suppkey"), F.lit(1 << 32))
    high, low = F.expr("65536L"), F.pmod(row, F.lit(65536))
    product = F.pmod(F.floor(row / high) * F.lit(2654435761), high).cast("long") * high + low * F.lit(2654435761)
    return F.floor(F.pmod(product, F.lit(1 << 32)) / 4096).cast("long")


_ROW = f"(((l_orderkey * 8 + l_linenumber) * 1009 + l_partkey * 31 + l_suppkey) % {1 << 32})"
Q20_SQL = f"((((({_ROW} // 65536) * 2654435761) % 65536) * 65536 + ({_ROW} % 65536) * 2654435761) % {1 << 32} // 4096)"


def distribution(name: str) -> Column:
    """z0: uniform on 20 bits; z5: density as x**-0.5; z1: density as 1/x."""
    h = q20()
    if name == "z0":
        return h
    if name == "z5":
        return F.floor(h * h / (1 << 20)).cast("long")
    octave = F.pmod(F.col("l_partkey") * 31 + F.col("l_orderkey") * 17 + F.col("l_linenumber"), F.lit(20))
    base = F.call_function("shiftleft", F.lit(1).cast("long"), octave.cast("int"))
    return (base + F.pmod(h, base)).cast("long")


DISTRIBUTION_SQL = {
    "z0": Q20_SQL,
    "z5": f"({Q20_SQL} * {Q20_SQL} // {1 << 20})",
    "z1": f"((1::BIGINT << ((l_partkey * 31 + l_orderkey * 17 + l_linenumber) % 20)::INT) + {Q20_SQL} % (1::BIGINT << ((l_partkey * 31 + l_orderkey * 17 + l_linenumber) % 20)::INT))",
}
