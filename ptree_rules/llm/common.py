"""What the operators share: reading a table, and cutting lineage by a written table."""

from __future__ import annotations

import atexit
import ctypes
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The columns of the documents table; others that an input may have are ignored.
DOC_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Stands for a null doc_id inside the operators: such rows come first in every order.
NO_ID = -(2**63)
#: Makes a finished job give up its shuffle files at once, not when the driver next collects garbage.
_FREE_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Bytes of a batch that goes to a Python worker: ten thousand rows of long texts would be held several times over.
_BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
_WHILE_WRITING = {_FREE_SHUFFLES: "true", _BATCH_BYTES: str(8 << 20)}

_own: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named columns of a table; the scan reads no others."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or the one given to setCheckpointDir. Where neither is set, a
    local master (tests) gets a folder of its own; on a cluster that would be a disk no one else sees, so there it is an error."""
    if found := spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir():
        return found
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, _own[app], ignore_errors=True)
    return f"file://{_own[app]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder: lineage ends there, and a lost executor costs no recomputation. As nothing
    reads the job's shuffles after that, their files go with it, and batches are bounded by bytes; the session's own settings hold
    again afterwards."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    before = {k: spark.conf.get(k, None) for k in _WHILE_WRITING}
    for k, v in _WHILE_WRITING.items():
        spark.conf.set(k, v)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path  # for discard()
    return out


def discard(*dfs: DataFrame) -> None:
    """Removes tables of written() that nothing reads any more."""
    for df in dfs:
        spark, path = df.sparkSession, df._written_at
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def giving_back(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """run, after which a Python worker gives what it has freed back to the system: workers wait for further tasks, and the
    next stage's would add to what they still hold."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # of the GNU C library only
            trim(0)

    return whole


def text_or_empty(text: str = "text") -> Column:
    return F.coalesce(F.col(text), F.lit(""))


def id_or_least(doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.col(doc_id).cast("long"), F.lit(NO_ID))


def id_back(column: str) -> Column:
    return F.when(F.col(column) != NO_ID, F.col(column))


def small_or_joined(df: DataFrame, most_rows: int) -> DataFrame:
    """df, a written table of short rows, marked for broadcast if it has at most so many rows; else for a shuffled join."""
    return F.broadcast(df) if df.count() <= most_rows else df.hint("merge")
