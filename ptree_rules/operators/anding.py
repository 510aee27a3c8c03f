"""ANDing: on tree nodes, on words, on bitmaps, and on whole segments in Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .items import ItemDict
from .ptree import TreeShape
from .tids import SEGMENT

Itemset = tuple[int, ...]


def and_trees(a: DataFrame, b: DataFrame, shape: TreeShape) -> DataFrame:
    """The AND of two trees of nodes cut below pure ones: level, node_id, size, cnt of a tree cut likewise.

    Only pure-1 nodes matter, as what is pure-0 is absent and mixed nodes follow from their children: of two pure-1 nodes one
    of which lies in the other, the smaller one is in the result. A pair of levels is an equi-join on the ancestor at the
    coarser one; then counts are summed bottom-up over the levels and cut below pure nodes again.
    """
    sizes, out = shape.sizes, None
    ones = {s: t.where("cnt = size").select("level", "node_id", "size") for s, t in (("a", a), ("b", b))}
    depth = len(sizes)
    for big, small, same in (("a", "b", True), ("b", "a", False)):
        # Every small node offers its ancestor at each coarser level (and its own level once, for pairs of equal nodes).
        up = F.explode(F.array(*(F.struct(F.lit(i).alias("level"), F.lit(s).cast("long").alias("wide")) for i, s in enumerate(sizes))))
        offered = ones[small].select(F.col("level").alias("own"), "node_id", "size", up.alias("x")).where(F.col("x.level") <= F.col("own") if same else F.col("x.level") < F.col("own"))
        offered = offered.select("own", "node_id", "size", F.col("x.level").alias("level"), F.floor(F.col("node_id") * F.col("size") / F.col("x.wide")).alias("over"))
        held = ones[big].select("level", F.col("node_id").alias("over"))
        got = offered.join(held, ["level", "over"]).select(F.col("own").alias("level"), "node_id", "size")
        out = got if out is None else out.unionByName(got)
    up = F.explode(F.array(*(F.struct(F.lit(i).alias("level"), F.lit(s).cast("long").alias("size")) for i, s in enumerate(sizes))))
    first = out.select(F.col("node_id").alias("n"), F.col("size").alias("s"), F.col("level").alias("own"), up.alias("x")).where(F.col("x.level") <= F.col("own"))
    summed = first.groupBy("x.level", F.floor(F.col("n") * F.col("s") / F.col("x.size")).alias("node_id"), "x.size").agg(F.sum("s").alias("cnt"))
    if depth == 1:
        return summed
    fan = F.element_at(F.array(*map(F.lit, shape.fanouts)), F.col("level"))
    pure = summed.where("cnt = size").select((F.col("level") + 1).alias("level"), F.col("node_id").alias("parent"))
    parent = F.when(F.col("level") > 0, F.floor(F.col("node_id") / fan))
    return summed.withColumn("parent", parent).join(pure, ["level", "parent"], "left_anti").select("level", "node_id", "size", "cnt")


def and_words(words: DataFrame, candidates: DataFrame) -> DataFrame:
    """cand_id and cnt of candidates(cand_id, items) with a one; k words of a place are ANDed where all k are there.

    The candidates are small (their number is checked by the miner); a word meets only those that hold its item. Where words
    are dealt by word_id already, partial and final AND stay local and only (candidate, count) rows are shuffled.
    """
    wanted = candidates.select("cand_id", F.size("items").alias("k"), F.explode("items").alias("item_id"))
    met = words.join(F.broadcast(wanted), "item_id")
    anded = met.groupBy("word_id", "cand_id", "k").agg(F.bit_and("bits").alias("bits"), F.count("*").alias("n")).where("n = k")
    return anded.groupBy("cand_id").agg(F.sum(F.bit_count("bits")).alias("cnt")).where("cnt > 0")


def and_bitmaps(bitmaps: DataFrame, candidates: DataFrame) -> DataFrame:
    """and_words on bitmaps of 32,768 bits by the built-in aggregates."""
    wanted = candidates.select("cand_id", F.size("items").alias("k"), F.explode("items").alias("item_id"))
    met = bitmaps.join(F.broadcast(wanted), "item_id")
    anded = met.groupBy("bucket", "cand_id", "k").agg(F.bitmap_and_agg("bitmap").alias("bitmap"), F.count("*").alias("n")).where("n = k")
    return anded.groupBy("cand_id").agg(F.sum(F.bitmap_count("bitmap")).alias("cnt")).where("cnt > 0")


def or_words(words: DataFrame) -> DataFrame:
    """word_id and bits of the OR over all items of words."""
    return words.groupBy("word_id").agg(F.bit_or("bits").alias("bits"))


def not_words(words: DataFrame, n: int) -> DataFrame:
    """item_id, word_id, bits of the complement over n real tuples; padding stays zero."""
    count, last = -(-n // 64), n % 64
    places = words.sparkSession.range(count).select(F.col("id").alias("word_id"))
    every = words.select("item_id").distinct().crossJoin(places)
    full = F.when((F.col("word_id") == count - 1) & F.lit(bool(last)), F.lit((1 << last) - 1 if last else -1)).otherwise(F.lit(-1)).cast("long")
    out = every.join(words, ["item_id", "word_id"], "left").select("item_id", "word_id", F.bitwise_not(F.coalesce("bits", F.lit(0))).bitwiseAND(full).alias("bits"))
    return out.where("bits != 0")


# Segments: each row holds all items' vectors over up to SEGMENT tuples.

SEGMENT_ROWS = "segment_id long, n int, items array<int>, kinds array<string>, counts array<int>, bits array<binary>"


#: Candidates of one broadcast; more go in several passes over the same segments.
CHUNK = 100_000


def _packed_by(df: DataFrame, items: ItemDict, segment: int, packed: Callable[[np.ndarray, int], pa.RecordBatch], schema: str) -> DataFrame:
    """A narrow pass over df that calls packed(codes, number) for each segment: a row of item numbers (-1: none) per attribute."""
    names = list(dict.fromkeys(items.attribute))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = (TaskContext.get().partitionId() << 33) // segment
        kept, held = [], 0
        for batch in batches:
            codes = np.stack([c.fill_null(-1).to_numpy() for c in batch.columns]) if batch.num_rows else np.zeros((len(names), 0), np.int32)
            kept.append(codes)
            held += codes.shape[1]
            while held >= segment:
                whole = np.concatenate(kept, 1)
                yield packed(whole[:, :segment], number)
                number, kept, held = number + 1, [whole[:, segment:]], held - segment
        if held:
            yield packed(np.concatenate(kept, 1), number)

    return df.select(*(items.code(a).alias(f"c{i}") for i, a in enumerate(names))).mapInArrow(run, schema)


def _flat(codes: np.ndarray, number: int) -> pa.RecordBatch:
    n = codes.shape[1]
    items, kinds, counts, bits = [], [], [], []
    for column in codes:
        for item in np.unique(column[column >= 0]).tolist():
            one = column == item
            items.append(item)
            counts.append(int(one.sum()))
            kinds.append("1" if counts[-1] == n else "m")
            bits.append(np.packbits(one, bitorder="little").tobytes() if counts[-1] < n else b"")
    types = dict(segment_id=pa.int64(), n=pa.int32(), items=pa.list_(pa.int32()), kinds=pa.list_(pa.string()), counts=pa.list_(pa.int32()), bits=pa.list_(pa.binary()))
    row = dict(segment_id=number, n=n, items=items, kinds=kinds, counts=counts, bits=bits)
    return pa.RecordBatch.from_pydict({k: pa.array([v], types[k]) for k, v in row.items()})


def build_segments(df: DataFrame, items: ItemDict, segment: int = SEGMENT) -> DataFrame:
    """One row per segment (SEGMENT_ROWS): a narrow pass packs each partition's tuples, in their order, without a shuffle.

    A pure-1 vector is a kind without bits, a pure-0 one is absent. Segments of one input partition are full but for its last.
    """
    return _packed_by(df, items, segment, _flat, SEGMENT_ROWS)


def segment_items(segments: DataFrame) -> DataFrame:
    """segment_id, item_id, root_cnt: the headers of segments, flat ones or trees."""
    each = F.explode(F.arrays_zip("items", "counts"))
    return segments.select("segment_id", each.alias("x")).select("segment_id", F.col("x.items").alias("item_id"), F.col("x.counts").alias("root_cnt"))


def _count_in_segment(row: dict, candidates: Sequence[Itemset], reuse: str) -> tuple[np.ndarray, int]:
    """The candidates' counts in one segment, and the ANDs done. Candidates are in lexicographic order: with reuse='prefix'
    a candidate takes up the AND of the longest prefix it shares with the one before."""
    n, out, ands = row["n"], np.zeros(len(candidates), np.int64), 0
    bits, counts = {}, dict(zip(row["items"], row["counts"], strict=True))
    for item, kind, raw in zip(row["items"], row["kinds"], row["bits"], strict=True):
        if kind == "m":
            bits[item] = np.frombuffer(raw + bytes(-len(raw) % 8), np.uint64)
    stack: list[tuple[int, np.ndarray | None, int]] = []  # item, AND so far (None: all ones), its count
    for at, candidate in enumerate(candidates):
        keep = 0
        if reuse == "prefix":
            while keep < min(len(stack), len(candidate) - 1) and stack[keep][0] == candidate[keep]:
                keep += 1
        del stack[keep:]
        for item in candidate[keep:]:
            vector, count = (stack[-1][1], stack[-1][2]) if stack else (None, n)
            if count and item not in counts:
                vector, count = None, 0  # pure-0 wins
            elif count and item in bits:
                if vector is None:
                    vector, count = bits[item], counts[item]
                else:
                    vector = vector & bits[item]
                    count, ands = int(np.bitwise_count(vector).sum()), ands + 1
            stack.append((item, vector, count))
        out[at] = stack[-1][2] if stack else n
    return out, ands


def _counter(sent, kernel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        candidates = sent.value
        total, ands, spared = np.zeros(len(candidates), np.int64), 0, 0
        for batch in batches:
            for i in range(batch.num_rows):  # a segment takes megabytes: one at a time
                counts, done, left = kernel(batch.slice(i, 1).to_pylist()[0], candidates)
                total += counts
                ands, spared = ands + done, spared + left
        ids = np.concatenate([np.flatnonzero(total), [-1, -2]])
        yield pa.record_batch([pa.array(ids), pa.array(np.concatenate([total[ids[:-2]], [ands, spared]]))], ["cand_id", "cnt"])

    return run


def _counted_over(segments: DataFrame, candidates: Sequence[Itemset], kernel) -> tuple[list[int], int, int]:
    """The sums over all segments of kernel(row, candidates): counts, ANDs done and spared. Candidates are broadcast in
    lexicographic order, CHUNK at a time; tasks send a row per candidate they saw, and vectors never leave their executor."""
    order = sorted(range(len(candidates)), key=lambda i: candidates[i])
    out, ands, spared = [0] * len(candidates), 0, 0
    for lo in range(0, len(order), CHUNK):
        part = order[lo : lo + CHUNK]
        sent = segments.sparkSession.sparkContext.broadcast([candidates[i] for i in part])
        rows = segments.mapInArrow(_counter(sent, kernel), "cand_id long, cnt long").groupBy("cand_id").agg(F.sum("cnt").alias("cnt")).collect()
        got = {r.cand_id: r.cnt for r in rows}
        for at, i in enumerate(part):
            out[i] = got.get(at, 0)
        ands, spared = ands + got.get(-1, 0), spared + got.get(-2, 0)
        sent.unpersist()
    return out, ands, spared


def count_in_segments(segments: DataFrame, candidates: Sequence[Itemset], reuse: str = "prefix") -> tuple[list[int], int]:
    """The counts of sorted candidates over all flat segments, and the word-vector ANDs done."""

    def kernel(row: dict, candidates: Sequence[Itemset]) -> tuple[np.ndarray, int, int]:
        return *_count_in_segment(row, candidates, reuse), 0

    return _counted_over(segments, candidates, kernel)[:2]
