"""Mask trees by segment: what the miner ANDs. A segment's tree has a root over its tuples, four quadrants, two more levels of
four, and at its 64 blocks the bits of mixed blocks only; the header holds the root count and the quadrants' counts.

Pure-1 and mixed blocks are the bits of two numbers, so the AND of two trees is decided for all nodes at once from the root
down, and only blocks that are mixed in both trees have their bits ANDed.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anding import Itemset, _counted_over, _packed_by
from .items import ItemDict
from .tids import SEGMENT

TREE_ROWS = "segment_id long, n int, items array<int>, counts array<int>, quadrants array<array<int>>, pure array<long>, mixed array<long>, bits array<binary>"
#: Levels of four-way nodes above a block, and the least bits of a block.
DEPTH, LEAST_BLOCK = 3, 64


class Tree(NamedTuple):
    """pure and mixed: a bit per block; words: 64-bit words of the mixed blocks, in order; count: ones."""

    pure: int
    mixed: int
    words: np.ndarray
    count: int


def block_bits(segment: int) -> int:
    """Bits of a block of a segment of so many tuples."""
    size = segment
    for _ in range(DEPTH):
        if size // 4 >= LEAST_BLOCK and size % 4 == 0:
            size //= 4
    if size % LEAST_BLOCK:
        raise ValueError(f"a segment of {segment} tuples has no blocks of whole words")
    return size


def _number(flags: np.ndarray) -> int:
    return int(np.packbits(np.pad(flags, (0, 64 - len(flags))), bitorder="little").view("<u8")[0])


def _places(number: int) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(np.array([number], "<u8").view(np.uint8), bitorder="little"))


def _signed(number: int) -> int:
    return number - (1 << 64) if number >> 63 else number


def tree_of(bits: np.ndarray, segment: int = SEGMENT) -> Tree:
    """The tree of a vector of at most so many booleans; what is missing is padding, that is zero."""
    size = block_bits(segment)
    packed = np.packbits(bits, bitorder="little")
    words = np.pad(packed, (0, -len(packed) % (size // 8))).view("<u8").reshape(-1, size // 64)
    counts = np.bitwise_count(words).sum(1, dtype=np.int64)
    mixed = (counts > 0) & (counts < size)
    return Tree(_number(counts == size), _number(mixed), words[mixed], int(counts.sum()))


def quadrant_counts(tree: Tree, segment: int = SEGMENT) -> list[int]:
    """Ones in each of the four quadrants."""
    size = block_bits(segment)
    counts = np.zeros(max(4, segment // size), np.int64)
    counts[_places(tree.pure)] = size
    counts[_places(tree.mixed)] = np.bitwise_count(tree.words).sum(1, dtype=np.int64)
    return counts.reshape(4, -1).sum(1).tolist()


def and_trees(a: Tree, b: Tree, size: int) -> tuple[Tree, int]:
    """The AND of two trees with blocks of so many bits, and how many blocks had their bits ANDed.

    Pure-0 on either side is pure-0, pure-1 leaves the other side's subtree, and of two mixed blocks the bits decide; if no
    one is left, the block is pure-0.
    """
    pure, both = a.pure & b.pure, a.mixed & b.mixed
    todo = (a.pure | a.mixed) & (b.pure | b.mixed) & ~pure
    ones = pure.bit_count() * size
    if not todo:
        return Tree(pure, 0, a.words[:0], ones), 0
    if todo == a.mixed == b.mixed:
        words = a.words & b.words
    else:
        at = _places(todo)
        words = np.full((len(at), size // 64), np.iinfo(np.uint64).max, np.uint64)
        for t in (a, b):
            own = _places(t.mixed)
            used = np.isin(own, at)
            words[np.searchsorted(at, own[used])] &= t.words[used]
    counts = np.bitwise_count(words).sum(1, dtype=np.int64)
    if not counts.all():
        left = np.zeros(64, bool)
        left[_places(todo)[counts > 0]] = True
        todo, words = _number(left), words[counts > 0]
    return Tree(pure, todo, words, ones + int(counts.sum())), both.bit_count()


def _packer(segment: int):
    types = dict(segment_id=pa.int64(), n=pa.int32(), items=pa.list_(pa.int32()), counts=pa.list_(pa.int32()), quadrants=pa.list_(pa.list_(pa.int32())), pure=pa.list_(pa.int64()), mixed=pa.list_(pa.int64()), bits=pa.list_(pa.binary()))

    def packed(codes: np.ndarray, number: int) -> pa.RecordBatch:
        items, trees = [], []
        for column in codes:
            for item in np.unique(column[column >= 0]).tolist():
                items.append(item)
                trees.append(tree_of(column == item, segment))
        row = dict(segment_id=number, n=codes.shape[1], items=items, counts=[t.count for t in trees], quadrants=[quadrant_counts(t, segment) for t in trees], pure=[_signed(t.pure) for t in trees], mixed=[_signed(t.mixed) for t in trees], bits=[t.words.tobytes() for t in trees])
        return pa.RecordBatch.from_pydict({k: pa.array([v], types[k]) for k, v in row.items()})

    return packed


def build_segment_trees(df: DataFrame, items: ItemDict, segment: int = SEGMENT) -> DataFrame:
    """One row per segment (TREE_ROWS): a narrow pass packs each partition's tuples, in their order, without a shuffle. Items
    that a segment lacks are absent."""
    block_bits(segment)
    return _packed_by(df, items, segment, _packer(segment), TREE_ROWS)


def load_tree(row: dict, i: int, size: int) -> Tree:
    """The tree of the i-th item of a stored segment with blocks of so many bits."""
    return Tree(row["pure"][i] % (1 << 64), row["mixed"][i] % (1 << 64), np.frombuffer(row["bits"][i], "<u8").reshape(-1, size // 64), row["counts"][i])


def count_in_tree_segment(segment: int, reuse: str = "prefix"):
    """A counter of sorted candidates in one stored segment: their counts, the blocks ANDed, and the blocks that the trees
    spared of those that ANDs of flat vectors touch."""
    size = block_bits(segment)

    def run(row: dict, candidates: Sequence[Itemset]) -> tuple[np.ndarray, int, int]:
        out, ands, spared = np.zeros(len(candidates), np.int64), 0, 0
        number = {item: i for i, item in enumerate(row["items"])}
        loaded: dict[int, Tree] = {}
        occupied = -(-row["n"] // size)
        stack: list[tuple[int, Tree | None]] = []  # item, tree of the prefix up to it (None: pure-0)
        for at, candidate in enumerate(candidates):
            keep = 0
            if reuse == "prefix":
                while keep < min(len(stack), len(candidate) - 1) and stack[keep][0] == candidate[keep]:
                    keep += 1
            del stack[keep:]
            for item in candidate[keep:]:
                held = stack[-1][1] if stack else None
                if item not in number or (stack and held is None):
                    stack.append((item, None))
                    continue
                own = loaded.get(item)
                if own is None:
                    own = loaded[item] = load_tree(row, number[item], size)
                if held is not None:
                    own, done = and_trees(held, own, size)
                    ands, spared = ands + done, spared + occupied - done
                stack.append((item, own if own.count else None))
            if stack:
                out[at] = stack[-1][1].count if stack[-1][1] else 0
            else:
                out[at] = row["n"]
        return out, ands, spared

    return run


def count_in_trees(trees: DataFrame, candidates: Sequence[Itemset], segment: int = SEGMENT, reuse: str = "prefix") -> tuple[list[int], int, int]:
    """The counts of sorted candidates over all segments, the blocks ANDed, and the blocks spared."""
    return _counted_over(trees, candidates, count_in_tree_segment(segment, reuse))


def bound_counts(trees: DataFrame, candidates: Sequence[Itemset]) -> list[int]:
    """Upper bounds of the candidates' counts from headers alone: in each quadrant a set has no more ones than its rarest item."""

    def bounds(row: dict, candidates: Sequence[Itemset]) -> tuple[np.ndarray, int, int]:
        none = np.zeros(4, np.int64)
        of = {item: np.array(q, np.int64) for item, q in zip(row["items"], row["quadrants"], strict=True)}
        return np.array([np.minimum.reduce([of.get(i, none) for i in c]).sum() for c in candidates], np.int64), 0, 0

    return _counted_over(trees.select("items", "quadrants"), candidates, bounds)[0]


def stored_bytes(trees: DataFrame) -> DataFrame:
    """segments, n, mixed_blocks and stored: bytes of the trees (two masks, five counts and the bits of mixed blocks an item)."""
    sizes = F.aggregate("bits", F.lit(0).cast("long"), lambda acc, b: acc + F.length(b) + 36)
    blocks = F.aggregate("mixed", F.lit(0).cast("long"), lambda acc, m: acc + F.bit_count(m))
    return trees.agg(F.count("*").alias("segments"), F.sum("n").alias("n"), F.sum(blocks).alias("mixed_blocks"), F.sum(sizes).alias("stored"))


def rows_one_by_one(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """A batch's rows as Python values, one at a time: a segment takes megabytes."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]
