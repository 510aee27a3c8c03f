"""Exact dedup by a tree of merges over sorted runs of digests that partitions exchange in rounds; DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, id_back, id_or_least, table, text_or_empty, written

#: Runs that one merge of a round takes in.
FAN_IN = 8
_KEY = ["sha", "n", "check"]


def _merged(rows: DataFrame, best, value: str, size: Column) -> DataFrame:
    """Each partition's runs, sorted by digest, as one sorted run without repeats: rows that agree in SHA-256, length and a second
    hash become one, with the identifier that stays and their number. The aggregation streams over the sort order (its value is
    a struct, which Spark doesn't hash-aggregate), so a run is never held as a whole."""
    runs = rows.repartition("part").sortWithinPartitions("part", *_KEY)
    found = runs.groupBy("part", *_KEY).agg(best(F.struct(value)).alias("best"), size.alias("size"))
    return found.select("part", *_KEY, F.col(f"best.{value}").alias("keep"), "size")


def exact_groups(docs: DataFrame, keep: str = "smallest", fan_in: int = FAN_IN) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of docs(doc_id, text).

    fan_in^r partitions hold a sorted run of digests each, dealt by id. In each of r rounds, fan_in partitions that differ in one
    digit of their number exchange their runs: a row goes to the one of them that its digest's digit names, where the runs that
    arrive are merged and what agrees becomes one, verified anew at every level. After r rounds a partition has the one run of
    its slice of all digests. The decisions then go back down the same tree. At no step do more rows of one digest meet than
    fan_in, or than one run holds; a group of copies with a third of all rows is spread over all partitions at first.

    keep: 'smallest' or 'largest' doc_id. Null text is an empty text. Null ids come before all others; rows that repeat an id
    and its text are one document and are kept or dropped together. No rows give no rows. Other columns are ignored.
    """
    best = {"smallest": F.min, "largest": F.max}[keep]
    spark = docs.sparkSession
    wanted, runs, rounds = max(64, int(spark.conf.get("spark.sql.shuffle.partitions"))), fan_in, 1
    while runs < wanted:
        runs, rounds = runs * fan_in, rounds + 1
    text = text_or_empty()
    rows = written(
        docs.select(
            id_or_least().alias("id"),
            F.unhex(F.sha2(text.cast("binary"), 256)).alias("sha"),
            F.octet_length(text).alias("n"),
            F.xxhash64(text).alias("check"),
        ).withColumn("part", F.pmod(F.xxhash64("id"), F.lit(runs))),
        "digests",
    )

    def after(level: int) -> Column:
        """A row's partition after so many rounds: that many digits of the digest's number, then those of its run's."""
        span = fan_in ** (rounds - level)
        return (F.floor(F.pmod("check", F.lit(runs)) / span) * span + F.col("part") % span).cast("long")

    levels = [_merged(rows, best, "id", F.count("*"))]
    for level in range(1, rounds + 1):
        levels.append(written(_merged(levels[-1].withColumn("part", after(level)), best, "keep", F.sum("size")), "runs"))
    decided = levels[rounds]
    for level in range(rounds - 1, -1, -1):
        # What the first merge made is not kept: rows go straight from their own partition to that after one round.
        below = (levels[level].select(*_KEY, "part", after(level + 1).alias("above")) if level else rows.select(*_KEY, "id", after(1).alias("above")))
        above = decided.select(*_KEY, F.col("part").alias("above"), "keep", "size")
        decided = below.join(above, [*_KEY, "above"]).drop("above")
    decided = written(decided, "decided")
    discard(rows, *levels[1:])
    return decided.select(
        id_back("id").alias("doc_id"),
        id_back("keep").alias("keep_id"),
        F.col("size").alias("group_size"),
        (F.col("id") == F.col("keep")).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(table(spark, sf_dir, "documents", "doc_id", "text"), keep="largest")


SQL = {
    "op4_exact_dedup": """
        SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
               doc_id = max(doc_id) OVER g AS kept, sha256(coalesce(text, '')) AS text_sha256
        FROM documents WINDOW g AS (PARTITION BY coalesce(text, ''))"""
}
