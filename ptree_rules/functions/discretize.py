"""Bands of numeric and date attributes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def band(col: str | Column, cuts: Sequence[float], labels: Sequence[str], closed: str = "left") -> Column:
    """The label of the band of a value; null stays null. closed='left': a cut begins its band; 'right': it ends the one below."""
    assert len(labels) == len(cuts) + 1, "one label more than cuts"
    c = F.col(col) if isinstance(col, str) else col
    out = F.when(c.isNull(), F.lit(None).cast("string"))
    for cut, label in zip(cuts, labels, strict=False):
        out = out.when(c < cut if closed == "left" else c <= cut, F.lit(label))
    return out.otherwise(F.lit(labels[-1]))


def width_cuts(df: DataFrame, col: str, k: int) -> list[float]:
    """The k-1 inner cuts of k equally wide bands between the least and largest value; none for a constant."""
    lo, hi = df.agg(F.min(col).cast("double"), F.max(col).cast("double")).first()
    return [] if lo is None or lo == hi else [lo + (hi - lo) * i / k for i in range(1, k)]


def frequency_cuts(df: DataFrame, col: str, k: int, exact: bool = False) -> list[float]:
    """The k-1 inner cuts of k bands of about equally many values: by a sketch, or by exact percentiles. Equal cuts are one."""
    shares = [i / k for i in range(1, k)]
    agg = F.percentile(col, shares) if exact else F.percentile_approx(col, shares, 10_000)
    return sorted(set(df.agg(agg).first()[0] or []))


def band_width(df: DataFrame, col: str, k: int) -> Column:
    cuts = width_cuts(df, col, k)
    return band(col, cuts, [f"b{i}" for i in range(len(cuts) + 1)])


def band_freq(df: DataFrame, col: str, k: int, exact: bool = False) -> Column:
    cuts = frequency_cuts(df, col, k, exact)
    return band(col, cuts, [f"b{i}" for i in range(len(cuts) + 1)])


def date_part(col: str | Column, part: str) -> Column:
    """year, month, dayofweek (1 is Sunday) or hour of a date or time."""
    return {"year": F.year, "month": F.month, "dayofweek": F.dayofweek, "hour": F.hour}[part](col)
