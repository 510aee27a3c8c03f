"""Queries over small tables of known content, and against their SQL."""

from datetime import datetime, timedelta

import duckdb
import pytest
from pyspark.sql import functions as F

from ptree_rules import catalogue
from ptree_rules.functions.bits import padded_size, padded_slots, register_sql

SF = "/root/testdata/sf0.001"


def equals_sql(spark, name, folder, **files):
    """The query's rows, once they are known to be those of its SQL."""
    duck = duckdb.connect()
    for table, file in files.items():
        duck.sql(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet{file}'")
    df = catalogue.QUERIES[name](spark, str(folder))
    rel = duck.sql(catalogue.ORACLE_SQL[name])
    assert rel.columns == df.columns
    rows = [tuple(r) for r in df.collect()]
    assert sorted(map(repr, rows)) == sorted(map(repr, rel.fetchall()))
    return rows


def test_and_mask_table_ands_the_trees_of_orders(spark, tmp_path):
    pairs = [(x1, x2) for x1 in "01m" for x2 in "01m"]
    rows = []
    for node, (x1, x2) in enumerate(pairs):
        for slot in range(4):
            one, two = (x == "1" or x == "m" and slot == 0 for x in (x1, x2))
            rows.append((4 * node + slot, "F" if one else "P", "1-URGENT" if two else "5-LOW"))
    rows += [(4, "P", "5-LOW"), (43, None, None), (45, "O", "2-HIGH")]  # a key twice, an order without items, and gaps
    spark.createDataFrame(rows, "o_orderkey long, o_orderstatus string, o_orderpriority string").write.parquet(f"{tmp_path}/orders.parquet")
    got = equals_sql(spark, "and_mask_table", tmp_path, orders="/*.parquet")
    want = ["0", "0", "0", "0", "1", "m", "0", "m", "recurse"]
    assert sorted(r[1:] for r in got if r[2] == 4) == [(i, 4, *p, w) for i, (p, w) in enumerate(zip(pairs, want, strict=True))] + [(10, 4, "0", "0", "0"), (11, 4, "m", "m", "recurse")]
    assert {r[:3] for r in got if r[2] > 4} == {(0, 0, 64), (1, 0, 16), (1, 1, 16), (1, 2, 16)}
    assert len(equals_sql(spark, "and_mask_table", SF, orders="")) > 375


def test_padded_size_sql_pads_the_orders_of_customers(spark, tmp_path):
    sizes = {7: 1, 8: 15, 9: 16, 10: 17, 11: 32, 12: 33, None: 65}
    spark.createDataFrame([(c,) for c, n in sizes.items() for _ in range(n)], "o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    got = equals_sql(spark, "padded_size_sql", tmp_path, orders="/*.parquet")
    assert {c: (n, slots) for c, n, slots in got} == {c: (n, padded_size(n)) for c, n in sizes.items()}
    assert sum(n for _, n, _ in equals_sql(spark, "padded_size_sql", SF, orders="")) == 1500


def test_padded_size_in_sql_is_exact_at_powers_of_two(spark):
    register_sql(spark)
    sizes = sorted({n for i in range(62) for n in (2**i - 1, 2**i, 2**i + 1)})
    got = spark.createDataFrame([(n,) for n in sizes], "n long").selectExpr("n", "padded_size(n) AS slots").collect()
    assert [tuple(r) for r in got] == [(n, padded_size(n)) for n in sizes]


def test_padded_sizes_pads_the_lines_of_parts(spark, tmp_path):
    sizes = {1: 8, 2: 15, 3: 16, 4: 17, 5: 64, None: 65}
    spark.createDataFrame([(p,) for p, n in sizes.items() for _ in range(n)], "l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = equals_sql(spark, "padded_sizes", tmp_path, lineitem="/*.parquet")
    want = {8: (16, 16, 16), 15: (16, 16, 16), 16: (16, 16, 32), 17: (32, 64, 32), 64: (64, 64, 128), 65: (128, 256, 128)}
    assert {p: (n, *slots) for p, n, *slots in got} == {p: (n, *want[n]) for p, n in sizes.items()}
    assert sum(r[1] for r in equals_sql(spark, "padded_sizes", SF, lineitem="")) == 6000


@pytest.mark.parametrize("how", [{}, {"pad": "pow4"}, {"pad_exact": True}, {"pad": "pow4", "pad_exact": True}, {"minimum": 0}, {"minimum": 1, "pad_exact": True}, {"minimum": 100, "pad": "pow4"}])
def test_padding_a_column_is_padding_each_number(spark, how):
    sizes = [0, *sorted({n for i in range(61) for n in (2**i - 1, 2**i, 2**i + 1)})]
    got = spark.createDataFrame([(n,) for n in [*sizes, None]], "n long").select("n", padded_slots(F.col("n"), **how)).collect()
    assert {n: slots for n, slots in got} == {n: padded_size(n, **how) for n in sizes} | {None: None}


def test_raster_tree_counts_the_weeks_of_users(spark, tmp_path):
    sunday = datetime(2024, 1, 7)
    rows = [(1, sunday + timedelta(hours=h)) for h in range(168)] + [(1, sunday + timedelta(days=7)), (1, None), (3, None)]
    rows += [(2, sunday + timedelta(days=3, hours=11, minutes=59)), (2, sunday + timedelta(days=4, hours=12)), (2, sunday + timedelta(days=11, hours=14)), (None, sunday)]
    spark.createDataFrame(rows, "user_id long, ts timestamp_ntz").write.parquet(f"{tmp_path}/events.parquet")
    got = equals_sql(spark, "raster_tree", tmp_path, events="/*.parquet")
    want = {1: (56, 16, 16, 12, 12), 2: (2, 1, 0, 0, 1), None: (1, 1, 0, 0, 0)}
    assert set(got) == {(u, min(i, 1), max(i - 1, 0), n) for u, counts in want.items() for i, n in enumerate(counts) if n}
    assert len(equals_sql(spark, "raster_tree", SF, events="")) > 15


def test_truth_table_counts_order_lines(spark, tmp_path):
    lines = [("R", "O", 34.0), ("R", "O", 33.0), ("R", "O", 33.0), ("A", "F", 50.0), ("N", None, 1.0), (None, "O", None)]
    spark.createDataFrame(lines, "l_returnflag string, l_linestatus string, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = equals_sql(spark, "truth_table", tmp_path, lineitem="/*.parquet")
    counts = {7: 1, 6: 2, 1: 1, 0: 1, 2: 1}
    assert sorted(got) == [(i, i >> 2, i >> 1 & 1, i & 1, counts.get(i, 0)) for i in range(8)]
    assert sum(r[-1] for r in equals_sql(spark, "truth_table", SF, lineitem="")) == 6000
