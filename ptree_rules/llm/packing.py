"""Best-fit packing of documents into sequences: dominance reduction on the histogram of lengths, best fit for the rest."""

from __future__ import annotations

import zlib
from bisect import bisect_left, bisect_right, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .byte_bpe import encode_column, slices
from .common import giving_back, table, text_or_empty, written

SEQUENCE, END_ID = 1024, 2
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"

Pattern = tuple[tuple[int, ...], int]  # lengths in one sequence, and how many sequences have them


class _Lengths:
    """A multiset of lengths, with the distinct ones in order."""

    def __init__(self, counts: dict[int, int]):
        self.count = {s: n for s, n in counts.items() if n}
        self.order = sorted(self.count)

    def take(self, size: int, n: int) -> None:
        self.count[size] -= n
        if not self.count[size]:
            del self.count[size]
            self.order.pop(bisect_left(self.order, size))

    def smallest(self, k: int, without: int) -> list[int]:
        """The k smallest items, one item of length `without` left out."""
        out: list[int] = []
        for s in self.order:
            out += [s] * min(k - len(out), self.count[s] - (s == without))
            if len(out) == k:
                break
        return out

    def has(self, wanted: tuple[int, ...]) -> int:
        """How often all of wanted can be taken together."""
        return min(self.count.get(s, 0) // wanted.count(s) for s in set(wanted))


def _dominant(items: _Lengths, size: int, room: int) -> tuple[int, ...] | None:
    """The other items of a sequence that holds `size` and dominates every other such sequence of a set of at most three
    further items, or None. A set dominates another if the other's items can be dealt to its items with no sum larger."""
    own = items.count[size] > 1
    i = bisect_right(items.order, room)
    if i and items.order[i - 1] == size and not own:
        i -= 1
    if not i:
        return ()
    best = items.order[i - 1]
    if best == room:
        return (best,)  # filled to the brim by one item, which dominates whatever fits
    two = items.smallest(2, size)
    if len(two) < 2 or sum(two) > room:
        return (best,)  # only one more item fits
    three = items.smallest(3, size)
    if len(three) == 3 and sum(three) <= room:
        return None
    # Exactly two more may fit: the largest feasible sum of two, against the best single item.
    pair, lo, hi = (0, 0), 0, i - 1
    while lo <= hi:
        a, b = items.order[lo], items.order[hi]
        if a + b > room:
            hi -= 1
            continue
        free = items.has((a, b)) and items.has(tuple(sorted((size, a, b))))
        if free and a + b > sum(pair):
            pair = (a, b)
        lo += 1
    if sum(pair) <= best:
        return (best,)
    a, b = pair
    if b == best and a + b == room:
        # Any other feasible pair has its larger item at most b; its smaller item must be at most a as well.
        j = bisect_right(items.order, room // 2)
        if not any(a < s and s + s <= room and items.has((s, s)) or a < s <= room - s for s in items.order[:j]):
            return (b, a)
    return None


def reduce_by_dominance(counts: dict[int, int], capacity: int) -> tuple[list[Pattern], dict[int, int]]:
    """The sequences that some best packing has, and the lengths left. Goes through the lengths from the largest down; a
    set that dominates all alternatives for its largest item is fixed as often as its items are there."""
    items, fixed = _Lengths(counts), []
    for size in sorted(counts, reverse=True):
        while size in items.count and (others := _dominant(items, size, capacity - size)) is not None:
            found = (size, *others)
            n = items.has(found)
            if others and others[0] + size < capacity or len(others) > 1:
                # What is feasible may change when an item runs out; below that, the same set dominates again.
                n = max(1, min(n, *((items.count[s] - 3) // found.count(s) for s in set(found)))) if n > 3 else 1
            for s in found:
                items.take(s, n)
            fixed.append((found, n))
    return fixed, items.count


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Best fit over the lengths from the largest down, all items of a length at a time; each goes to the open sequence with
    the least room that holds it."""
    bins: dict[int, list[list]] = {}  # room -> [lengths, how many]
    rooms: list[int] = []
    full: list[Pattern] = []

    def put(lengths: tuple[int, ...], room: int, n: int) -> None:
        if not room:
            full.append((lengths, n))
        elif n:
            if room not in bins:
                bins[room] = []
                insort(rooms, room)
            bins[room].append([lengths, n])

    for size in sorted(counts, reverse=True):
        left = counts[size]
        while left:
            i = bisect_left(rooms, size)
            if i == len(rooms):
                each = min(capacity // size, left)
                put((size,) * each, capacity - size * each, left // each)
                if left % each:
                    put((size,) * (left % each), capacity - size * (left % each), 1)
                break
            room = rooms[i]
            group = bins[room][-1]
            lengths, n = group
            each = min(room // size, left)
            used = min(n, left // each)
            group[1] -= used
            if not group[1]:
                bins[room].pop()
                if not bins[room]:
                    del bins[room]
                    rooms.pop(i)
            put(lengths + (size,) * each, room - size * each, used)
            left -= used * each
    return full + [(lengths, n) for groups in bins.values() for lengths, n in groups]


def pack_lengths(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """A packing of so many items of each length."""
    fixed, rest = reduce_by_dominance(counts, capacity)
    return fixed + best_fit_decreasing(rest, capacity)


def _tokenized(ranks: str, pattern: str, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            all_ids, all_texts = batch.column("doc_id"), batch.column("text")
            for lo, hi in slices(all_texts):
                ids, at = encode_column(all_texts.slice(lo, hi - lo), ranks, pattern)
                doc_ids = all_ids.slice(lo, hi - lo).to_pylist()
                out: dict[str, list] = {k: [] for k in ("doc_id", "piece", "start", "length", "ids_crc32")}
                raw = ids.astype("<u4").tobytes()
                end = np.array([END_ID], "<u4").tobytes()
                for doc_id, a, b in zip(doc_ids, at[:-1].tolist(), at[1:].tolist(), strict=True):
                    n = b - a + 1
                    cut = n % capacity or capacity
                    bounds = [0, *range(cut, n + 1, capacity)]
                    for piece, (x, y) in enumerate(zip(bounds, bounds[1:], strict=False)):
                        crc = zlib.crc32(raw[4 * (a + x) : 4 * (a + min(y, n - 1))])
                        out["doc_id"].append(doc_id)
                        out["piece"].append(piece)
                        out["start"].append(x)
                        out["length"].append(y - x)
                        out["ids_crc32"].append(zlib.crc32(end, crc) if y == n else crc)
                kinds = dict(doc_id=pa.int64(), piece=pa.int32(), start=pa.int64(), length=pa.int64(), ids_crc32=pa.int64())
                yield pa.RecordBatch.from_pydict({k: pa.array(v, kinds[k]) for k, v in out.items()})

    return run


def tokenized_pieces(docs: DataFrame, capacity: int = SEQUENCE, ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """The pieces of every row of docs(doc_id, text): its ids and the end id, cut from the end into pieces of the capacity,
    so that only the first may be shorter. Null text is empty: one piece of the end id alone.

    ranks_path is the vocabulary as ranks and pattern its pre-tokenizer, at the same place on every executor; the installed
    public byte-level vocabulary by default.
    """
    if ranks_path is None:
        import public_tokenizers as vocabularies

        ranks_path, pattern = vocabularies.path("byte_bpe_50k.tiktoken"), vocabularies.PATTERN
    run = giving_back(_tokenized(ranks_path, pattern, capacity))
    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(run, _PIECES)


def _slots(patterns: list[Pattern]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, last rank, sequence of the first rank, offset): the items of a length fill slots by their rank."""
    used: dict[int, int] = {}
    out, base = [], 0
    for lengths, n in patterns:
        offset = 0
        for s in lengths:
            lo = used.get(s, 0)
            out.append((s, lo, lo + n - 1, base, offset))
            used[s] = lo + n
            offset += s
        base += n
    return out


def _placed(slots: list[tuple[int, int, int, int, int]]):
    arr = np.array(sorted(slots), np.int64).reshape(-1, 5)
    first = {s: (np.searchsorted(arr[:, 0], s), np.searchsorted(arr[:, 0], s, "right")) for s in np.unique(arr[:, 0]).tolist()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            at = np.zeros(len(length), np.int64)
            for s in np.unique(length).tolist():
                lo, hi = first[s]
                own = length == s
                at[own] = lo + np.searchsorted(arr[lo:hi, 1], rank[own], "right") - 1
            cols = {n: batch.column(n) for n in batch.schema.names if n != "rank"}
            yield pa.RecordBatch.from_pydict(cols | {"sequence_id": pa.array(arr[at, 3] + rank - arr[at, 1]), "offset": pa.array(arr[at, 4])})

    return run


def packed(pieces: DataFrame, capacity: int = SEQUENCE) -> DataFrame:
    """pieces with sequence_id and offset.

    Only the histogram of lengths (at most `capacity` numbers) reaches the driver, and only the slots of the packing go
    back: both are bounded by the capacity, whatever the input. An item's rank among those of its length is made of its
    rank in a bucket and the counts of the buckets before, so that a length with a third of all rows is no single task.
    """
    spark = pieces.sparkSession
    buckets = 8 * max(8, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = written(pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)).cast("int")), "pieces")
    sums = written(rows.groupBy("length", "bucket").agg(F.count("*").alias("n")), "counts")
    counts = {r["length"]: r["n"] for r in sums.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    before = sums.select("length", "bucket", (F.sum("n").over(Window.partitionBy("length").orderBy("bucket")) - F.col("n")).alias("before"))
    within = Window.partitionBy("bucket", "length").orderBy("doc_id", "piece", "start")
    ranked = rows.withColumn("in_bucket", F.row_number().over(within) - 1).join(before, ["bucket", "length"])
    ranked = ranked.select(*[c.split()[0] for c in _PIECES.split(", ")], (F.col("in_bucket") + F.col("before")).cast("long").alias("rank"))
    slots = _slots(pack_lengths(counts, capacity))
    return ranked.mapInArrow(_placed(slots), f"{_PIECES}, sequence_id long, offset long")


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(tokenized_pieces(table(spark, sf_dir, "documents", "doc_id", "text")))
