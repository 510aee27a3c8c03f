"""Connected components of an edge list, by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, written


def _stars(pairs: DataFrame, large: bool) -> DataFrame:
    """One step over links (a, b) with a > b. A node's least neighbour (or itself) becomes the neighbour of those of its
    neighbours that are larger than the node (large), or that are not (small)."""
    if large:
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("least")).select("a", F.least("a", "least").alias("least"))
        out = both.where(F.col("b") > F.col("a")).join(least, "a").select(F.col("b").alias("a"), F.col("least").alias("b"))
    else:
        least = pairs.groupBy("a").agg(F.min("b").alias("least"))
        moved = pairs.join(least, "a").where(F.col("b") != F.col("least")).select(F.col("b").alias("a"), F.col("least").alias("b"))
        out = moved.unionByName(least.select("a", F.col("least").alias("b")))
    return out.distinct()


def _is_stars(pairs: DataFrame) -> bool:
    """Whether every node that isn't the least of its component is linked to that one alone: one pass over nodes."""
    ends = pairs.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down"))
    ends = ends.unionByName(pairs.select(F.col("b").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    found = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return found.where("up + down > 1").isEmpty()


def components(links: DataFrame) -> DataFrame:
    """node and root, the least node of its component, for every node of links(a, b) but the roots themselves.

    Nodes are longs. Direction, loops and repeats don't matter. Each round writes its links, so plans stay short; the driver
    sees only whether all are stars by then. The number of rounds grows with the logarithm of the largest component.
    """
    a, b = F.col("a").cast("long"), F.col("b").cast("long")
    now = written(links.where(a != b).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct(), "links")
    while not _is_stars(now):
        step = written(_stars(now, True), "links")
        following = written(_stars(step, False), "links")
        discard(now, step)
        now = following
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
