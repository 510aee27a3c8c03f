"""Windows over events, in batch and as streams; transactions of a window; sequences; incremental trees."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.thresholds import Number, confident, fraction
from ..operators.anding import build_segments, segment_items
from ..operators.items import ItemDict
from ..sources import tables
from ..sources.tables import load, shared_dir

#: Bands of an event's value that serve as items.
VALUE_CUTS = (25.0, 75.0)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, ts (a time with zone; the session's zone is taken as UTC), user_id, event_type, value, band and item."""
    return with_items(load(spark, sf_dir, "events"))


def with_items(df: DataFrame) -> DataFrame:
    low, high = VALUE_CUTS
    band = F.when(F.col("value") < low, "lo").when(F.col("value") < high, "mid").otherwise("hi")
    return df.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", band.alias("band"))


def event_stream(spark: SparkSession, sf_dir: str, late: str | None = None, files_per_batch: int | None = None) -> DataFrame:
    """The events as a file stream with a watermark; repeated ids within it are dropped.

    late: how far behind the latest time an event may come. A table that is there as a whole may have its files in any order,
    so without a given lateness it is the table's own span of time, which drops nothing.
    """
    table = load(spark, sf_dir, "events")
    if late is None:
        first, last = table.agg(F.min("ts"), F.max("ts")).first()
        late = f"{int((last - first).total_seconds()) + 1 if first else 0} seconds"
    raw = tables.stream_parquet(spark, f"{sf_dir}/events.parquet", table.schema, files_per_batch)
    return with_items(raw).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def rate_stream(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """A stream of made events of even rate, with the columns of events."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    made = raw.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), (F.col("value") % 97).alias("user_id"), F.concat(F.lit("t"), F.col("value") % 5).alias("event_type"), (F.col("value") % 100).cast("double").alias("value"))
    return with_items(made)


def window_counts(df: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """Events by window and type."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return df.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), "event_type", "cnt")


def session_counts(df: DataFrame, gap: str) -> DataFrame:
    """Sessions of each user: start, end of the last event plus gap, and events."""
    return df.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("cnt")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "cnt")


def window_baskets(df: DataFrame, width: str) -> DataFrame:
    """A transaction for each user and window: the set of its items, types and value bands."""
    items = F.explode(F.array(F.concat(F.lit("type="), "event_type"), F.concat(F.lit("band="), "band")))
    return df.select("user_id", F.window("ts", width).start.alias("start"), items.alias("item")).distinct()


def mine_windowed(df: DataFrame, width: str, minsup: Number, minconf: Number) -> DataFrame:
    """Strong rules between two items within each window: start, antecedent, consequent, cnt_xy, cnt_x, n.

    Items of a transaction are few (types and bands), so a transaction's pairs are; counts are pre-aggregated by task.
    """
    basket = window_baskets(df, width)
    tx = basket.groupBy("start", "user_id").agg(F.array_sort(F.collect_set("item")).alias("items"))
    n = tx.groupBy("start").agg(F.count("*").alias("n"))
    single = tx.select("start", F.explode("items").alias("antecedent")).groupBy("start", "antecedent").agg(F.count("*").alias("cnt_x"))
    pairs = tx.select("start", F.explode("items").alias("antecedent"), "items").select("start", "antecedent", F.explode("items").alias("consequent")).where("antecedent != consequent")
    both = pairs.groupBy("start", "antecedent", "consequent").agg(F.count("*").alias("cnt_xy"))
    s = fraction(minsup)
    rules = both.join(single, ["start", "antecedent"]).join(n, "start")
    return rules.where((F.col("cnt_xy") * s.denominator >= F.col("n") * s.numerator) & confident(F.col("cnt_xy"), F.col("cnt_x"), minconf))


def sequence_pairs(df: DataFrame, gap_seconds: int) -> DataFrame:
    """first, second and cnt: a user's event followed by the user's next one of another type or the same within the gap."""
    from pyspark.sql import Window

    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    after = df.select("user_id", "event_type", "ts", F.lead("event_type").over(order).alias("second"), F.lead("ts").over(order).alias("then"))
    near = after.where((F.col("then").cast("double") - F.col("ts").cast("double")) <= gap_seconds)
    return near.groupBy(F.col("event_type").alias("first"), "second").agg(F.count("*").alias("cnt"))


def dropped_rows(query) -> int:
    """Rows that a finished query left out as later than its watermark, over the progress reports the session keeps."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def run_to_table(stream: DataFrame, most_late: int = 0) -> DataFrame:
    """Runs an aggregating stream over all files that are there and returns its result, as the last batch wrote it.

    Each batch writes the whole result into a folder of its own, which a retry overwrites. More than most_late rows left out by
    the watermark are an error: counts would be short of them without a word.
    """
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    done: list[int] = []

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        done.append(batch_id)

    query = stream.writeStream.foreachBatch(put).outputMode("complete").option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    if (late := dropped_rows(query)) > most_late:
        raise ValueError(f"{late} rows came later than the watermark allows; give a larger lateness, or allow so many to be left out")
    return spark.read.schema(stream.schema).parquet(f"{path}/batch={done[-1]}") if done else spark.createDataFrame([], stream.schema)


def streamed_root_counts(stream: DataFrame, most_late: int = 0) -> DataFrame:
    """Root counts of event items, kept up to date by the stream."""
    items = F.explode(F.array(F.concat(F.lit("type="), "event_type"), F.concat(F.lit("band="), "band")))
    return run_to_table(stream.select(items.alias("item")).groupBy("item").agg(F.count("*").alias("cnt")), most_late)


def stream_segments(stream: DataFrame, items: ItemDict, path: str) -> DataFrame:
    """Trees of a stream: every micro-batch packs its own segments into a folder named by its id, which a retry overwrites,
    so each batch counts once. Returns root counts over all segments, pure-0 items absent."""

    def pack(batch: DataFrame, batch_id: int) -> None:
        build_segments(batch, items).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    spark = stream.sparkSession
    query = stream.writeStream.foreachBatch(pack).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    return segment_items(spark.read.parquet(path)).groupBy("item_id").agg(F.sum("root_cnt").alias("cnt"))


def decayed_counts(df: DataFrame, half_life_seconds: float, at: str) -> DataFrame:
    """Counts of types that halve with each half-life of age at a time; later events don't count yet."""
    age = F.lit(at).cast("timestamp").cast("double") - F.col("ts").cast("double")
    return df.where(age >= 0).groupBy("event_type").agg(F.sum(F.pow(F.lit(0.5), age / half_life_seconds)).alias("weight"))
