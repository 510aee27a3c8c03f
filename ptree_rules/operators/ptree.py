"""Bit trees: packed words, count, mask, P1 and P0 trees, their storage, statistics and inverse."""

from __future__ import annotations

from dataclasses import dataclass
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import padded_size
from ..sources.tables import written


@dataclass(frozen=True)
class TreeShape:
    """Fan-outs from the root down to the leaves' bits; their product is the capacity."""

    fanouts: tuple[int, ...]

    @classmethod
    def of(cls, capacity: int, root: int = 4, inner: int = 4) -> TreeShape:
        """root, then inner as often as it divides; what is left over is the leaves' number of bits."""
        out, left = [root], capacity // root
        if root * left != capacity:
            raise ValueError(f"{root} does not divide {capacity}")
        while left > inner and left % inner == 0:
            out.append(inner)
            left //= inner
        return cls((*out, left) if left > 1 else tuple(out))

    @classmethod
    def for_tuples(cls, n: int, **how) -> TreeShape:
        return cls.of(padded_size(n, **how))

    @property
    def capacity(self) -> int:
        return prod(self.fanouts)

    @property
    def sizes(self) -> list[int]:
        """Slots of a node at each level, the root's first; the last level is single bits."""
        return [self.capacity // prod(self.fanouts[:i]) for i in range(len(self.fanouts) + 1)]


def build_words(long: DataFrame) -> DataFrame:
    """item_id, word_id and bits, 64 tuples a word; map-side OR shrinks the shuffle to a row per word and task. Words without
    a one are absent."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("tid") % 64).cast("int"))
    return long.groupBy("item_id", F.floor(F.col("tid") / 64).alias("word_id")).agg(F.bit_or(bit).alias("bits"))


def build_bitmaps(long: DataFrame) -> DataFrame:
    """item_id, bucket and bitmap of 32,768 bits. The built-in positions begin at one, hence the shift of the tid."""
    at = F.col("tid") + 1
    return long.groupBy("item_id", F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bitmap"))


def root_counts(words: DataFrame) -> DataFrame:
    return words.groupBy("item_id").agg(F.sum(F.bit_count("bits")).alias("cnt"))


def quadrant_counts(long: DataFrame, shape: TreeShape) -> DataFrame:
    """item_id, quadrant and cnt of the first level; quadrants without a one are absent."""
    return long.groupBy("item_id", F.floor(F.col("tid") / shape.sizes[1]).alias("quadrant")).agg(F.count("*").alias("cnt"))


def build_count_tree(long: DataFrame, shape: TreeShape, pruned: bool = False) -> DataFrame:
    """item_id, level, node_id, size and cnt of all nodes that hold a one, single bits included; pruned: of the tree proper, in
    which nodes below a pure-1 node are cut. Pure-0 nodes are absent.

    Bottom-up from words of 64 tuples: a word gives the nodes inside it without a shuffle (and none below a pure one), and the
    levels above are sums of its count, a row per word and no longer per bit. Shapes whose sizes aren't powers of two are
    counted from single bits.
    """
    sizes = shape.sizes
    if any(s & (s - 1) for s in sizes):
        nodes = _summed(long.select("item_id", F.lit(1).alias("cnt"), F.col("tid").alias("node_id")), sizes, 1)
        return prune_pure(nodes, shape) if pruned else nodes
    word = min(64, shape.capacity)
    top = max(i for i, s in enumerate(sizes) if s >= word)  # the lowest level whose nodes are words, or several
    held = sizes[top] // word
    words = written(build_words(long), "words").select("item_id", "word_id", "bits", F.bit_count("bits").cast("long").alias("cnt"))
    block = F.floor(F.col("word_id") / held)
    if held == 1:
        blocks = words.select("item_id", "word_id", "bits", F.col("cnt").alias("of_block"))
    else:
        blocks = words.groupBy("item_id", block.alias("node_id")).agg(F.sum("cnt").alias("of_block"), F.collect_list(F.struct("word_id", "bits")).alias("w"))
        blocks = blocks.select("item_id", "of_block", F.explode("w").alias("w")).select("item_id", "of_block", "w.*")
    upper = _summed(words.select("item_id", "cnt", block.alias("node_id")), sizes[: top + 1], sizes[top])
    if pruned:
        upper, blocks = prune_pure(upper, shape), blocks.where(F.col("of_block") < sizes[top])

    def part(first: Column, size: int) -> Column:
        """Ones among so many bits of a word from a place on."""
        return F.bit_count(F.call_function("shiftrightunsigned", F.col("bits"), first.cast("int")).bitwiseAND(F.lit((1 << size) - 1))).cast("long")

    def inside(level: int) -> Column:
        size, above = sizes[level], sizes[level - 1]

        def node(k: Column) -> Column:
            cut = (part(F.floor(k * size / above) * above, above) == above) if pruned and above < 64 and level - 1 > top else F.lit(False)
            return F.struct(F.lit(level).alias("level"), (F.col("word_id") * (64 // size) + k).alias("node_id"), F.lit(size).cast("long").alias("size"), F.when(~cut, part(k * size, size)).otherwise(F.lit(0)).cast("long").alias("cnt"))

        return F.filter(F.transform(F.sequence(F.lit(0), F.lit(word // size - 1)), node), lambda x: x["cnt"] > 0)

    below = [inside(i) for i in range(top + 1, len(sizes))]
    if not below:
        return upper
    return upper.unionByName(blocks.select("item_id", F.explode(F.flatten(F.array(*below))).alias("x")).select("item_id", "x.*"))


def _summed(rows: DataFrame, sizes: list[int], of: int) -> DataFrame:
    """Counts by level of rows(item_id, node_id, cnt) whose nodes have `of` slots; map-side sums go before the shuffle."""
    levels = F.explode(F.array(*(F.struct(F.lit(i).alias("level"), F.lit(s).cast("long").alias("size")) for i, s in enumerate(sizes))))
    each = rows.select("item_id", "cnt", F.col("node_id").alias("own"), levels.alias("x"))
    return each.select("item_id", "x.*", F.floor(F.col("own") / (F.col("x.size") / of)).alias("node_id"), "cnt").groupBy("item_id", "level", "node_id", "size").agg(F.sum("cnt").alias("cnt"))


def prune_pure(nodes: DataFrame, shape: TreeShape) -> DataFrame:
    """The tree proper: nodes below a pure-1 node are cut. A node goes if its parent is pure-1, which covers all below."""
    if len(shape.fanouts) == 0:
        return nodes
    fan = F.element_at(F.array(*map(F.lit, shape.fanouts)), F.col("level"))
    parent = F.when(F.col("level") > 0, F.floor(F.col("node_id") / fan))
    pure = nodes.where("cnt = size").select("item_id", (F.col("level") + 1).alias("level"), F.col("node_id").alias("parent"))
    return nodes.withColumn("parent", parent).join(pure, ["item_id", "level", "parent"], "left_anti").select("item_id", "level", "node_id", "size", "cnt")


def to_mask_tree(nodes: DataFrame) -> DataFrame:
    """The three-valued tree: 1, 0 or m for a node (absent nodes are 0)."""
    return nodes.withColumn("mask", F.when(F.col("cnt") == F.col("size"), "1").when(F.col("cnt") == 0, "0").otherwise("m")).drop("cnt")


def with_absent_children(nodes: DataFrame, shape: TreeShape) -> DataFrame:
    """nodes with the pure-0 children of mixed nodes, which the stored form leaves out."""
    fan, below = (F.element_at(F.array(*map(F.lit, x)), F.col("level") + 1) for x in (shape.fanouts, shape.sizes[1:]))
    mixed = nodes.where((F.col("cnt") < F.col("size")) & (F.col("level") < len(shape.fanouts)))
    child = mixed.select("item_id", "level", F.explode(F.sequence(F.col("node_id") * fan, F.col("node_id") * fan + fan - 1)).alias("node_id"), below.cast("long").alias("size"))
    child = child.withColumn("level", F.col("level") + 1)
    absent = child.join(nodes, ["item_id", "level", "node_id"], "left_anti").select("item_id", "level", "node_id", "size", F.lit(0).cast("long").alias("cnt"))
    return nodes.select("item_id", "level", "node_id", "size", "cnt").unionByName(absent)


def to_p1(nodes: DataFrame) -> DataFrame:
    """A bit per node: is it pure-1?"""
    return nodes.withColumn("bit", F.col("cnt") == F.col("size")).drop("cnt")


def to_p0(nodes: DataFrame) -> DataFrame:
    """A bit per node: is it pure-0?"""
    return nodes.withColumn("bit", F.col("cnt") == 0).drop("cnt")


def expand_tree(pruned: DataFrame) -> DataFrame:
    """item_id and tid of all ones, from the terminal nodes of a tree cut below pure ones."""
    pure = pruned.where("cnt = size")
    return pure.select("item_id", F.explode(F.sequence(F.col("node_id") * F.col("size"), (F.col("node_id") + 1) * F.col("size") - 1)).alias("tid"))


def store_trees(pruned: DataFrame, path: str, shape: TreeShape) -> None:
    """Root counts, first-level counts, and the rest of mixed quadrants only, as Parquet by part."""
    part = F.when(F.col("level") == 0, "root").when(F.col("level") == 1, "quadrant").otherwise("mixed")
    pruned.withColumn("part", part).repartition("part", "item_id").sortWithinPartitions("item_id", "level", "node_id").write.mode("overwrite").partitionBy("part").parquet(path)


def load_trees(spark, path: str, part: str | None = None) -> DataFrame:
    """Stored trees; one part prunes the others' files."""
    out = spark.read.parquet(path)
    return (out.where(F.col("part") == part) if part else out).drop("part")


def tree_stats(pruned: DataFrame) -> DataFrame:
    """Nodes, pure-1 nodes and ones by item and level."""
    return pruned.groupBy("item_id", "level").agg(F.count("*").alias("nodes"), F.count_if(F.col("cnt") == F.col("size")).alias("pure1"), F.sum("cnt").alias("ones"))


def range_count(pruned: DataFrame, lo: int, hi: int) -> DataFrame:
    """Ones of each item in the tids lo..hi-1, from the pure-1 nodes that meet the range."""
    begin, end = F.col("node_id") * F.col("size"), (F.col("node_id") + 1) * F.col("size")
    hit = pruned.where((F.col("cnt") == F.col("size")) & (begin < hi) & (end > lo))
    return hit.groupBy("item_id").agg(F.sum(F.least(end, F.lit(hi)) - F.greatest(begin, F.lit(lo))).alias("cnt"))


