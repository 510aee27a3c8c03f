import re

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from ptree_rules import catalogue
from ptree_rules.operators import items
from ptree_rules.operators.anding import build_segments, count_in_segments
from ptree_rules.sources import tables
from ptree_rules.sources import workloads as W
from ptree_rules.streaming import windows

SF = "/root/testdata/sf0.001"
SOME = ["item_dictionary", "level_counts_w1", "minsup_sweep_w1", "strong_rules_by_level_w1", "rules_applied", "range_count", "pure_pruned_tree", "mask_tree", "and_nodes_equals_words", "rules_fixed_w1", "itemsets_w2", "rules_nonredundant", "worked_example_table", "cube_counts", "join_asof", "windowed_rules", "session_counts", "streaming_root_counts", "word_popcounts", "band_freq_exact"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in tables.TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_sql(spark, duck, name):
    df = catalogue.QUERIES[name](spark, SF)
    names = sorted(df.columns)
    got = sorted(repr(tuple(r[c] for c in names)) for r in df.collect())
    rel = duck.sql(catalogue.ORACLE_SQL[name])
    assert sorted(rel.columns) == names
    at = [rel.columns.index(c) for c in names]
    assert got == sorted(repr(tuple(r[i] for i in at)) for r in rel.fetchall())


def test_entry_and_registration(spark):
    assert entry.entry(spark).count() == 21
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 100


def plan(df):
    return df._jdf.queryExecution().toString()


def test_scans_are_pruned_and_pushed(spark):
    text = plan(catalogue.QUERIES["join_inner"](spark, SF))
    assert re.search(r"PushedFilters: \[[^\]]*EqualTo\(l_returnflag,R\)", text)
    assert not re.search(r"ReadSchema: struct<[^>]*l_extendedprice", text)


def test_packing_a_relation_needs_no_shuffle(spark):
    info = W.w4(spark)
    assert "Exchange" not in plan(build_segments(info.df, items.build_items(info)))


def test_level_counts_shuffle_counts_only(spark):
    info = W.w4(spark)
    seg = tables.written(build_segments(info.df, items.build_items(info)), "segments")
    assert count_in_segments(seg, [(0, 1)])[0] == [2]


def test_streams_equal_batches(spark, tmp_path):
    events = windows.events(spark, SF)
    events.sparkSession.read.parquet(f"{SF}/events.parquet").repartition(3).write.parquet(str(tmp_path / "events.parquet"))
    stream = windows.event_stream(spark, str(tmp_path), late="60 days")
    got = {(r.start, r.event_type): r.cnt for r in windows.run_to_table(windows.window_counts(stream, "1 day")).collect()}
    assert got == {(r.start, r.event_type): r.cnt for r in windows.window_counts(events, "1 day").collect()}


def test_trees_of_a_stream(spark, tmp_path):
    events = windows.events(spark, SF)
    spark.read.parquet(f"{SF}/events.parquet").repartition(4).write.parquet(str(tmp_path / "events.parquet"))
    dic = items.build_items(W.info_table(events, ["event_type"], ["band"]))
    stream = windows.event_stream(spark, str(tmp_path), late="60 days")
    got = {dic.label(r.item_id): r.cnt for r in windows.stream_segments(stream.select("event_type", "band"), dic, str(tmp_path / "trees")).collect()}
    want = {f"{c}={r[c]}": r["count"] for c in ("event_type", "band") for r in events.groupBy(c).count().collect()}
    assert got == want


def test_decayed_counts(spark):
    got = windows.decayed_counts(spark.sql("SELECT timestamp'2024-01-01 00:00:00' AS ts, 'a' AS event_type UNION ALL SELECT timestamp'2024-01-01 01:00:00', 'a'"), 3600, "2024-01-01 01:00:00")
    assert got.first().weight == pytest.approx(1.5)


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats(spark, fmt):
    part = tables.load(spark, SF, "part").select("p_partkey", "p_name", "p_size")
    assert tables.round_trip(part, fmt).exceptAll(part).count() == 0


def split_events(spark, path, parts, seed=0):
    """The events over files whose times interleave."""
    df = tables.load(spark, SF, "events")
    df.repartition(parts, F.xxhash64("event_id", F.lit(seed))).write.parquet(f"{path}/events.parquet")
    return path


def test_streamed_counts_lose_nothing_over_interleaved_files(spark, tmp_path):
    folder = split_events(spark, str(tmp_path), 4)
    want = {r.item: r.cnt for r in windows.streamed_root_counts(windows.event_stream(spark, SF)).collect()}
    assert sum(want.values()) == 2 * tables.load(spark, SF, "events").count()
    for files in (None, 1):
        assert {r.item: r.cnt for r in windows.streamed_root_counts(windows.event_stream(spark, folder, files_per_batch=files)).collect()} == want


def test_rows_later_than_the_watermark_are_reported(spark, tmp_path):
    folder = split_events(spark, str(tmp_path), 4)
    with pytest.raises(ValueError, match="later than the watermark"):
        windows.streamed_root_counts(windows.event_stream(spark, folder, late="1 hour", files_per_batch=1))
    short = windows.streamed_root_counts(windows.event_stream(spark, folder, late="1 hour", files_per_batch=1), most_late=10**6)
    assert short.agg(F.sum("cnt")).first()[0] < 2 * tables.load(spark, SF, "events").count()
