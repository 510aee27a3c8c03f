import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from ptree_rules.functions.bits import and_mask, morton, padded_size
from ptree_rules.functions.discretize import band, band_freq, band_width
from ptree_rules.functions.thresholds import is_confident, min_count
from ptree_rules.operators import anding, items, ptree, segment_trees, tids
from ptree_rules.operators.anding import _count_in_segment
from ptree_rules.sources import tables
from ptree_rules.sources import workloads as W


@pytest.mark.parametrize("n,pow2,pow4,exact", [(0, 16, 16, 16), (8, 16, 16, 16), (15, 16, 16, 16), (16, 16, 16, 32), (17, 32, 64, 32), (64, 64, 64, 128)])
def test_padding(n, pow2, pow4, exact):
    assert (padded_size(n), padded_size(n, pad="pow4"), padded_size(n, pad_exact=True)) == (pow2, pow4, exact)


def test_shapes():
    assert ptree.TreeShape.of(16).fanouts == (4, 4)
    assert ptree.TreeShape.of(32).sizes == [32, 8, 2, 1]
    assert ptree.TreeShape.of(64).sizes == [64, 16, 4, 1]
    assert ptree.TreeShape((2, 4, 8)).capacity == 64


def test_thresholds_at_the_boundary():
    assert min_count("0.1", 8) == 1 and min_count("0.17", 6000) == 1020 and min_count("0.17", 6000, strict=True) == 1021
    assert min_count("0.5", 7) == 4 and min_count("0.5", 7, strict=True) == 4
    assert is_confident(3, 4, "0.75") and not is_confident(3, 4, "0.75", strict=True) and not is_confident(2, 3, "0.67")


def test_worked_table_and_its_items(spark):
    info = W.w4(spark)
    dic = items.build_items(info)
    assert [a for a, _ in dic.items] == list("ABCDEFG")
    counts = {r.attribute: r.cnt for r in items.item_counts(info).collect()}
    assert counts == dict(zip("ABCDEFG", (2, 6, 1, 5, 5, 3, 4)))


def worked_long(spark):
    dic = items.build_items(W.w4(spark))
    return items.bitmap_long(tables.worked_example(spark), dic), dic


def test_quadrants_words_and_masks(spark):
    long, dic = worked_long(spark)
    shape = ptree.TreeShape.for_tuples(8)
    got = {(dic.attribute[r.item_id], r.quadrant): r.cnt for r in ptree.quadrant_counts(long, shape).collect()}
    assert got == {("A", 0): 2, ("B", 0): 4, ("B", 1): 2, ("C", 0): 1, ("D", 0): 2, ("D", 1): 3, ("E", 0): 2, ("E", 1): 3, ("F", 0): 1, ("F", 1): 2, ("G", 0): 2, ("G", 1): 2}
    words = {dic.attribute[r.item_id]: r.bits for r in ptree.build_words(long).collect()}
    assert words["B"] == 207 and words["D"] == 182 and words["B"] & words["D"] == 134
    pruned = ptree.prune_pure(ptree.build_count_tree(long, shape), shape)
    masks = {(r.level, r.node_id): r.mask for r in ptree.to_mask_tree(ptree.with_absent_children(pruned, shape)).where(F.col("item_id") == 1).collect()}
    assert masks[0, 0] == "m" and [masks[1, i] for i in range(4)] == ["1", "m", "0", "0"] and (2, 0) not in masks
    b, d, a, g = (pruned.where(F.col("item_id") == dic.attribute.index(x)).drop("item_id") for x in "BDAG")
    both = {(r.level, r.node_id): r.cnt for r in anding.and_trees(b, d, shape).collect()}
    assert both[0, 0] == 3 and both[1, 0] == 2 and both[1, 1] == 1
    assert anding.and_trees(a, g, shape).count() == 0


def test_and_mask_is_exhaustive(spark):
    cells = [(x, y) for x in "01m" for y in "01m"]
    got = {(r.a, r.b): r.x for r in spark.createDataFrame(cells, "a string, b string").withColumn("x", and_mask(F.col("a"), F.col("b"))).collect()}
    assert all(v == ("0" if "0" in k else k[1] if k[0] == "1" else k[0] if k[1] == "1" else "recurse") for k, v in got.items())


def test_raster(spark):
    long = tables.raster8(spark).where("bit").select(F.lit(0).alias("item_id"), morton(F.col("x"), F.col("y"), 3).alias("tid"))
    shape = ptree.TreeShape.of(64)
    tree = ptree.build_count_tree(long, shape)
    top = {(r.level, r.node_id): r.cnt for r in tree.where("level < 2").collect()}
    assert top == {(0, 0): 55, (1, 0): 16, (1, 1): 8, (1, 2): 15, (1, 3): 16}
    assert ptree.prune_pure(tree, shape).where("level = 1 and cnt = size").count() == 2


@pytest.mark.parametrize("n,seed", [(1, 0), (16, 1), (40, 2), (300, 3)])
def test_trees_lose_nothing(spark, n, seed, tmp_path):
    rng = np.random.default_rng(seed)
    bits = {i: np.flatnonzero(rng.random(n) < p) for i, p in enumerate((0.0, 0.1, 0.5, 0.95, 1.0))}
    bits[2] = np.arange(n)[(np.arange(n) // 16) % 2 == 0]  # long pure runs
    rows = [(i, int(t)) for i, ts in bits.items() for t in ts]
    long = spark.createDataFrame(rows, "item_id int, tid long")
    shape = ptree.TreeShape.for_tuples(n)
    pruned = ptree.prune_pure(ptree.build_count_tree(long, shape), shape)
    ptree.store_trees(pruned, str(tmp_path / "t"), shape)
    back = ptree.expand_tree(ptree.load_trees(spark, str(tmp_path / "t")))
    assert sorted((r.item_id, r.tid) for r in back.collect()) == sorted(rows)
    lo, hi = n // 3, n // 2 + 1
    got = {r.item_id: r.cnt for r in ptree.range_count(pruned, lo, hi).collect()}
    assert got == {i: c for i, ts in bits.items() if (c := int(((ts >= lo) & (ts < hi)).sum()))}
    one, two = (pruned.where(F.col("item_id") == i).drop("item_id") for i in (2, 3))
    both = anding.and_trees(one, two, shape).select(F.lit(0).alias("item_id"), "*")
    assert sorted(r.tid for r in ptree.expand_tree(both).collect()) == sorted({*bits[2].tolist()} & {*bits[3].tolist()})


def test_dense_tids_and_round_trip(spark):
    df = spark.range(500).select((F.col("id") * 37 % 101).cast("string").alias("a"), F.when(F.col("id") % 3 > 0, "x").alias("b")).repartition(7)
    info = W.info_table(df, ["a"], ["b"])
    numbered = tids.dense_tids(info.df, ["a", "b"])
    assert sorted(r.tid for r in numbered.collect()) == list(range(500))
    order = [(r.a, r.b or "") for r in numbered.orderBy("tid").collect()]
    assert order == sorted(order)
    dic = items.build_items(info)
    back = items.decode(items.bitmap_long(numbered, dic), dic)
    assert back.exceptAll(numbered.select("tid", "a", "b")).count() == 0 and back.count() == 500
    segmented = tids.segment_tids(info.df)
    assert segmented.select("segment", "offset").distinct().count() == 500


def test_ids_made_before_the_explode_keep_pairs(spark):
    info = W.info_table(spark.createDataFrame([("x", "y")] * 10, "a string, b string"), ["a"], ["b"])
    dic = items.build_items(info)
    long = items.bitmap_long(info.df.withColumn("tid", F.monotonically_increasing_id()), dic)
    cands = spark.createDataFrame([(0, [0, 1])], "cand_id int, items array<int>")
    assert anding.and_words(ptree.build_words(long), cands).first().cnt == 10


def test_nulls_set_no_bit(spark):
    info = W.info_table(spark.createDataFrame([("x", None), (None, None), ("z", "y")], "a string, b string"), ["a"], ["b"])
    dic = items.build_items(info)
    assert [dic.label(i) for i in range(len(dic.items))] == ["a=x", "a=z", "b=y"]
    assert [r["items"] for r in items.transactions(info.df, dic).collect()] == [[0], [], [1, 2]]
    assert items.item_frame(info).where("domain = 'BAD'").first().attribute == "b"


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 200), st.integers(0, 2**32 - 1), st.sampled_from(["prefix", "none"]))
def test_kernel_counts(n, seed, reuse):
    rng = np.random.default_rng(seed)
    m = rng.random((6, n)) < rng.choice([0.0, 0.2, 0.8, 1.0], 6)[:, None]
    there = [i for i in range(6) if m[i].any()]
    row = {"n": n, "items": there, "kinds": ["1" if m[i].all() else "m" for i in there], "counts": [int(m[i].sum()) for i in there], "bits": [b"" if m[i].all() else np.packbits(m[i], bitorder="little").tobytes() for i in there]}
    cands = sorted({tuple(sorted(rng.choice(6, rng.integers(1, 5), replace=False).tolist())) for _ in range(15)})
    got, _ = _count_in_segment(row, cands, reuse)
    assert got.tolist() == [int(np.logical_and.reduce(m[list(c)]).sum()) for c in cands]


def test_segments_don_t_depend_on_partitions(spark):
    info = W.w4(spark)
    dic = items.build_items(info)
    for parts, size in ((1, 64), (3, 64), (2, 2)):
        seg = anding.build_segments(info.df.repartition(parts), dic, size)
        counts, _ = anding.count_in_segments(seg, [(1, 3), (0,), (1, 3, 4)])
        assert counts == [3, 2, 2]


def test_not_and_or(spark):
    long = spark.createDataFrame([(0, t) for t in (0, 5, 64, 69)] + [(1, 3)], "item_id int, tid long")
    words = ptree.build_words(long)
    no = {r.item_id: r.c for r in anding.not_words(words, 70).groupBy("item_id").agg(F.sum(F.bit_count("bits")).alias("c")).collect()}
    assert no == {0: 66, 1: 69}
    assert anding.or_words(words).agg(F.sum(F.bit_count("bits"))).first()[0] == 5


def test_bands(spark):
    df = spark.createDataFrame([(x,) for x in (0.0, 1.0, 2.0, 3.0, 10.0, None)], "v double")
    assert [r[0] for r in df.select(band("v", (1, 3), ("a", "b", "c"))).collect()] == ["a", "b", "b", "c", "c", None]
    assert [r[0] for r in df.select(band("v", (1, 3), ("a", "b", "c"), closed="right")).collect()] == ["a", "a", "b", "b", "c", None]
    assert [r[0] for r in df.select(band_width(df, "v", 2)).collect()] == ["b0"] * 4 + ["b1", None]
    assert {r[0] for r in df.select(band_freq(df, "v", 2, exact=True)).collect()} == {"b0", "b1", None}


@pytest.mark.parametrize("fanouts", [(4, 4, 4, 4, 2), (4, 4, 4, 4), (4, 4), (2, 4, 8, 16), (3, 5, 7), (16, 4, 4, 8), (4, 4, 4, 4, 4, 4)])
def test_pruned_trees_are_built_bottom_up(spark, fanouts):
    shape = ptree.TreeShape(fanouts)
    rng = np.random.default_rng(len(fanouts))
    tids = {0: rng.random(shape.capacity) < 0.5, 1: np.arange(shape.capacity) < shape.capacity * 0.7, 2: np.ones(shape.capacity, bool), 3: rng.random(shape.capacity) < 0.98}
    rows = [(i, int(t)) for i, bits in tids.items() for t in np.flatnonzero(bits)]
    long = spark.createDataFrame(rows, "item_id int, tid long")
    want, cut = set(), set()
    for i, bits in tids.items():
        for level, size in enumerate(shape.sizes):
            counts = bits.reshape(-1, size).sum(1)
            above = bits.reshape(-1, shape.sizes[level - 1]).sum(1) == shape.sizes[level - 1] if level else np.zeros(1, bool)
            for node in np.flatnonzero(counts):
                want.add((i, level, int(node), size, int(counts[node])))
                if not level or not above[node * size // shape.sizes[level - 1]]:
                    cut.add((i, level, int(node), size, int(counts[node])))
    assert {tuple(r) for r in ptree.build_count_tree(long, shape).collect()} == want
    got = [tuple(r) for r in ptree.build_count_tree(long, shape, pruned=True).select("item_id", "level", "node_id", "size", "cnt").collect()]
    assert set(got) == cut and len(got) == len(cut)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 4096), st.integers(0, 2**32 - 1), st.sampled_from([64, 256, 1024, 4096]))
def test_segment_trees_and_their_and(n, seed, segment):
    n, rng = min(n, segment), np.random.default_rng(seed)
    a, b = (np.repeat(rng.random(-(-n // run)) < p, run)[:n] for run, p in zip(rng.choice([1, 16, 64, 300], 2), rng.choice([0.0, 0.3, 0.9, 1.0], 2), strict=True))
    x, y = segment_trees.tree_of(a, segment), segment_trees.tree_of(b, segment)
    both, ands = segment_trees.and_trees(x, y, segment_trees.block_bits(segment))
    want = segment_trees.tree_of(a & b, segment)
    assert (both.pure, both.mixed, both.count) == (want.pure, want.mixed, want.count) == (both.pure, both.mixed, int((a & b).sum()))
    assert (both.words == want.words).all() and ands == (x.mixed & y.mixed).bit_count()
    assert sum(segment_trees.quadrant_counts(x, segment)) == int(a.sum())


def test_tree_segments_count_as_flat_ones(spark):
    info = W.w4(spark)
    dic = items.build_items(info)
    for parts, size in ((1, 64), (3, 256)):
        seg = segment_trees.build_segment_trees(info.df.repartition(parts), dic, size)
        counts, _, _ = segment_trees.count_in_trees(seg, [(1, 3), (0,), (1, 3, 4), (0, 6)], size)
        assert counts == [3, 2, 2, 0]
        assert all(b >= c for b, c in zip(segment_trees.bound_counts(seg, [(1, 3), (0,), (1, 3, 4), (0, 6)]), counts, strict=True))


def test_stored_trees_take_less_where_neighbours_are_alike(spark):
    df = spark.range(40_000).select((F.col("id") % 4).cast("string").alias("a"), F.lit("x").alias("b")).repartition(1)
    sizes = []
    for rows in (df, df.sortWithinPartitions("a")):
        info = W.info_table(rows, ["a"], ["b"])
        sizes.append(segment_trees.stored_bytes(segment_trees.build_segment_trees(info.df, items.build_items(info))).first().stored)
    assert sizes[1] * 2 < sizes[0] < 40_000 * 5 / 8 * 1.4
