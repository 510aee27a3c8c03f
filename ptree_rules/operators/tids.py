"""Tuple numbers: dense over the relation, or dense within segments. Root counts and mining need no order and use segments."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import written

#: Tuples of a segment: 4^9, a whole 4-way tree of nine levels.
SEGMENT = 4**9


def dense_tids(df: DataFrame, keys: list[str]) -> DataFrame:
    """tid from 0 without gaps, in the order of the keys (ties in any order).

    The keys should tell rows apart, such as the relation's own key with all attributes after it: rows that agree in all keys
    can't be split, and few different keys make few partitions. A range shuffle sorts; the sorted table is written once with each row's place in its partition, so a retry can't number
    anew; the partitions' sizes (a row each) give the offsets. No window spans the whole relation.
    """
    place = F.monotonically_increasing_id()
    rows = written(df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_place", place), "numbered")
    part = F.shiftright("_place", 33)
    sizes = rows.groupBy(part.alias("part")).agg(F.count("*").alias("n")).orderBy("part").collect()
    offset, table = 0, []
    for r in sizes:
        table.append((r.part, offset))
        offset += r.n
    offsets = df.sparkSession.createDataFrame(table, "_part long, _offset long")
    own = F.col("_place").bitwiseAND(F.lit(2**33 - 1))
    out = rows.withColumn("_part", part).join(F.broadcast(offsets), "_part")  # a row per partition
    return out.select((own + F.col("_offset")).alias("tid"), *df.columns)


def segment_tids(df: DataFrame) -> DataFrame:
    """segment and offset in one narrow pass: numbers are dense within a partition, and 2^33 slots of a partition are a whole
    number of segments, so none crosses partitions. A segment's end stays zero, as padding does."""
    rows = written(df.withColumn("_id", F.monotonically_increasing_id()), "numbered")
    return rows.select(F.floor(F.col("_id") / SEGMENT).alias("segment"), (F.col("_id") % SEGMENT).cast("int").alias("offset"), *df.columns)


def assign_tids(df: DataFrame, keys: list[str] | None = None, mode: str = "key") -> DataFrame:
    return dense_tids(df, keys or df.columns) if mode == "key" else segment_tids(df)
