"""Column expressions of information measures; all stay in generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x) if isinstance(x, (int, float)) else F.col(x)


def h2(p) -> Column:
    """Binary entropy in bits; 0 at both ends."""
    p = _col(p)
    term = lambda q: F.when(q > 0, -q * F.log2(q)).otherwise(F.lit(0.0))
    return term(p) + term(1 - p)


def share_bits(count, total) -> Column:
    """Bits that ``count`` symbols take at their share of ``total``."""
    count, total = _col(count), _col(total)
    return F.when(count > 0, count * F.log2(total / count)).otherwise(F.lit(0.0))


def bit_length(x) -> Column:
    """Binary digits of a positive whole number; exact, unlike a rounded logarithm."""
    return F.length(F.bin(_col(x).cast("long")))


def elias_gamma_bits(x) -> Column:
    return 2 * bit_length(x) - 1


def elias_delta_bits(x) -> Column:
    n = bit_length(x)
    return n - 1 + 2 * F.length(F.bin(n.cast("long"))) - 1


def symbol_width(k) -> Column:
    """Whole bits of a symbol of an alphabet of ``k``."""
    return F.when(_col(k) <= 1, F.lit(0)).otherwise(bit_length(_col(k) - 1))


def plain_bits(n, k) -> Column:
    return _col(n) * symbol_width(k)
