"""Codes, sizes and the three-valued AND of bit trees."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def padded_size(n: int, minimum: int = 16, pad: str = "pow2", pad_exact: bool = False) -> int:
    """Slots of a tree over n tuples: the least power of two (or four) that holds them, `minimum` at least.

    pad_exact: a number that is such a power itself takes the next one.
    """
    step = {"pow2": 1, "pow4": 2}[pad]
    size = 1
    while size < max(n, minimum) or (pad_exact and size == n):
        size <<= step
    return size


def padded_slots(n: Column, minimum: int = 16, pad: str = "pow2", pad_exact: bool = False) -> Column:
    """padded_size of a column of numbers of tuples, from the binary digits of what a size must exceed; null stays null."""
    step = {"pow2": 1, "pow4": 2}[pad]
    below = F.greatest(n.cast("long") + int(pad_exact), F.lit(minimum).cast("long")) - 1
    digits = F.length(F.bin(below))
    slots = F.call_function("shiftleft", F.lit(1).cast("long"), digits + digits % step)
    return F.when(n.isNotNull(), F.when(below > 0, slots).otherwise(1))


def morton(x: Column, y: Column, bits: int) -> Column:
    """The Z-order code of a cell: the bits of y and x in turn, y's first."""
    terms = [F.shiftleft(F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1)), 2 * b + up) for b in range(bits) for c, up in ((x, 0), (y, 1))]
    return reduce(lambda a, b: a.bitwiseOR(b), terms)


def and_mask(x1: Column, x2: Column) -> Column:
    """The mask of the AND of two nodes: '0', '1', 'm', or 'recurse' where two mixed nodes' children decide."""
    return F.when((x1 == "0") | (x2 == "0"), "0").when(x1 == "1", x2).when(x2 == "1", x1).otherwise("recurse")


def register_sql(spark: SparkSession) -> None:
    """and_mask and padded_size as SQL functions of the session. padded_size counts binary digits: a logarithm in floats goes
    wrong at 2^29 already."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION and_mask(x1 STRING, x2 STRING) RETURNS STRING
        RETURN CASE WHEN x1 = '0' OR x2 = '0' THEN '0' WHEN x1 = '1' THEN x2 WHEN x2 = '1' THEN x1 ELSE 'recurse' END""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION padded_size(n BIGINT) RETURNS BIGINT
        RETURN shiftleft(1L, length(bin(greatest(n, 16L) - 1)))""")
