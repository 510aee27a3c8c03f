"""Support and confidence thresholds as integers: no ratio of floats is ever compared."""

from __future__ import annotations

from fractions import Fraction
from math import floor

from pyspark.sql import Column
from pyspark.sql import functions as F

Number = str | int | float | Fraction


def fraction(x: Number) -> Fraction:
    """The decimal that x is written as (0.1 is one tenth)."""
    return x if isinstance(x, Fraction) else Fraction(str(x))


def min_count(minsup: Number, n: int, strict: bool = False) -> int:
    """The least count that has the support among n transactions (inclusive, or strictly above)."""
    least = fraction(minsup) * n
    return floor(least) + 1 if strict else -(-least.numerator // least.denominator)


def confident(cnt_xy: Column, cnt_x: Column, minconf: Number, strict: bool = False) -> Column:
    """cnt_xy / cnt_x reaches the confidence, by whole numbers."""
    c = fraction(minconf)
    left, right = cnt_xy.cast("decimal(19,0)") * c.denominator, cnt_x.cast("decimal(19,0)") * c.numerator
    return left > right if strict else left >= right


def is_confident(cnt_xy: int, cnt_x: int, minconf: Number, strict: bool = False) -> bool:
    c = fraction(minconf)
    left, right = cnt_xy * c.denominator, cnt_x * c.numerator
    return left > right if strict else left >= right
