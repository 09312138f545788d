"""Column expressions of the scheme: grid, tolerance split, cones, sign maps and code lengths."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SAFE = 2.0**52


def quantize(x: Column, step: float) -> Column:
    """Nearest grid point; null outside the exact range of doubles."""
    y = x / F.lit(float(step))
    return F.when(F.abs(y) < SAFE, F.floor(y + 0.5).cast("long"))


def dequantize(q: Column, step: float) -> Column:
    return q * F.lit(float(step))


def split_budget(eps: float | Column, lam: float | Column = 0.5) -> tuple:
    """(grid part, line part) of a tolerance; columns of them where either is a column, which raise when read."""
    wrong = "eps must be positive and lam in (0, 1]"
    if isinstance(eps, Column) or isinstance(lam, Column):
        eps, lam = (v if isinstance(v, Column) else F.lit(float(v)) for v in (eps, lam))
        good = (eps > 0) & (lam > 0) & (lam <= 1)
        return tuple(F.when(good, v).otherwise(F.raise_error(F.lit(wrong))) for v in (lam * eps, (1 - lam) * eps))
    if not eps > 0 or not 0 < lam <= 1:
        raise ValueError(wrong)
    return lam * eps, (1 - lam) * eps


def cone(dx: Column, dt: Column, half: Column | float) -> Column:
    """Slopes that pass a sample at distance dt and height dx within ``half``."""
    half = half if isinstance(half, Column) else F.lit(float(half))
    return F.struct(((dx - half) / dt).alias("lo"), ((dx + half) / dt).alias("hi"))


def meet(a: Column, b: Column) -> Column:
    return F.struct(F.greatest(a["lo"], b["lo"]).alias("lo"), F.least(a["hi"], b["hi"]).alias("hi"))


def is_empty(c: Column) -> Column:
    return c["lo"] > c["hi"]


def zigzag(i: Column, kind: str = "dense") -> Column:
    """Signed to unsigned: ``dense`` uses every code, ``sparse`` leaves code 1 out."""
    i = i.cast("long")
    return F.when(i >= 0, 2 * i).otherwise(-2 * i + (1 if kind == "sparse" else -1))


def unzigzag(u: Column, kind: str = "dense") -> Column:
    odd = u % 2 == 1
    return F.when(~odd, F.floor(u / 2)).otherwise(-F.floor((u + (1 if kind == "dense" else -1)) / 2)).cast("long")


def bit_length(u: Column) -> Column:
    """Bits of an unsigned integer, none for zero."""
    return F.when(u == 0, F.lit(0)).otherwise(F.length(F.bin(u))).cast("long")


def varint_bits(u: Column) -> Column:
    return (F.greatest(F.lit(1), F.ceil(bit_length(u) / 7)) * 8).cast("long")


def unary_bits(u: Column) -> Column:
    return (u + 1).cast("long")


def rice_bits(u: Column, r: Column) -> Column:
    return (F.floor(u / F.pow(F.lit(2.0), r)) + 1 + r).cast("long")


def gamma_bits(u: Column) -> Column:
    return (2 * (bit_length(u + 1) - 1) + 1).cast("long")


def delta_bits(u: Column) -> Column:
    n = bit_length(u + 1)
    return (n - 1 + 2 * (bit_length(n) - 1) + 1).cast("long")
