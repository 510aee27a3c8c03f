"""Readers, literal fixtures and sinks."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_own: dict[str, str] = {}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; columns and filters reach the Parquet scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_text_format(spark: SparkSession, path: str, fmt: str, schema: StructType) -> DataFrame:
    """CSV (with header), JSON, ORC, Parquet or lines of text with an explicit schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if fmt == "csv" else getattr(reader, fmt)(path)


def write_text_format(df: DataFrame, path: str, fmt: str) -> None:
    writer = df.write.mode("overwrite")
    writer.option("header", True).csv(path) if fmt == "csv" else getattr(writer, fmt)(path)


def stream_parquet(spark: SparkSession, path: str, schema: StructType, files_per_batch: int | None = None) -> DataFrame:
    """A table's files as a stream, be the table a folder or a single file (streams read folders only)."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(where).isDirectory()
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    if folder:
        return reader.parquet(path)
    return reader.option("pathGlobFilter", where.getName()).parquet(where.getParent().toString())


def read_jdbc(spark: SparkSession, url: str, query: str, **options: str) -> DataFrame:
    """A query of another database, where a driver for its URL is on the class path."""
    return spark.read.format("jdbc").options(url=url, query=query, **options).load()


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or the one given to setCheckpointDir. Where neither is set, a local
    master gets a folder of its own; on a cluster that would be a disk no one else sees, so there it is an error."""
    if found := spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir():
        return found
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="trees-")
        atexit.register(shutil.rmtree, _own[app], ignore_errors=True)
    return f"file://{_own[app]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder; lineage ends there."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def append_partitioned(df: DataFrame, path: str, by: list[str], sort: list[str] | None = None) -> None:
    """Adds df to a Parquet table in folders by some columns; rows of a folder are written by few tasks, sorted within them."""
    rows = df.repartition(*by)
    (rows.sortWithinPartitions(*by, *sort) if sort else rows).write.mode("append").partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, by: list[str]) -> None:
    """df as a table of the warehouse in buckets by some columns, sorted by them: joins of tables bucketed alike need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *by).sortBy(*by).format("parquet").saveAsTable(name)


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """df through files of a format and back."""
    path = f"{shared_dir(df.sparkSession)}/{fmt}-{uuid.uuid4().hex}"
    write_text_format(df, path, fmt)
    return read_text_format(df.sparkSession, path, fmt, df.schema)


#: The worked example's eight tuples, attributes A to G.
WORKED = (
    (1, 1, 1, 0, 0, 0, 0, 0),
    (2, 1, 1, 1, 1, 1, 1, 0),
    (3, 0, 1, 0, 1, 0, 0, 1),
    (4, 0, 1, 0, 0, 1, 0, 1),
    (5, 0, 0, 0, 1, 0, 1, 1),
    (6, 0, 0, 0, 1, 1, 0, 1),
    (7, 0, 1, 0, 0, 1, 0, 0),
    (8, 0, 1, 0, 1, 1, 1, 0),
)


def worked_example(spark: SparkSession) -> DataFrame:
    """tid (from 0) and A..G with 'yes' where the item is present, null where not."""
    df = spark.createDataFrame(WORKED, "tid int, A int, B int, C int, D int, E int, F int, G int")
    return df.select((F.col("tid") - 1).cast("long").alias("tid"), *(F.when(F.col(c) == 1, "yes").alias(c) for c in "ABCDEFG"))


def truth_table(spark: SparkSession, n: int) -> DataFrame:
    """All 2^n combinations of n bits."""
    return spark.range(2**n).select(*(F.shiftright("id", n - 1 - i).bitwiseAND(F.lit(1)).cast("int").alias(f"a{i + 1}") for i in range(n)))


def raster8(spark: SparkSession) -> DataFrame:
    """An 8 x 8 raster whose quadrants, in Z-order, hold 16, 8, 15 and 16 ones; the bits within them are our choice."""
    cells = spark.range(64).select((F.col("id") % 8).cast("int").alias("x"), F.floor(F.col("id") / 8).cast("int").alias("y"))
    quadrant = F.floor(F.col("y") / 4) * 2 + F.floor(F.col("x") / 4)
    bit = F.when(quadrant == 1, F.col("y") < 2).when(quadrant == 2, ~((F.col("x") == 3) & (F.col("y") == 7))).otherwise(F.lit(True))
    return cells.select("x", "y", bit.alias("bit"))
