"""SimHash near-dedup with fuzzy keys from the perfect binary Golay code."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_back, id_or_least, table, text_or_empty, written
from .components import components

#: Shingle length in words, largest number of differing bits of a link, seed of the shingle hash.
SHINGLE, DISTANCE, SEED = 3, 3, 42
#: A fingerprint's segments: first bit and width. Each is a word of the code of length 23, the rest zero.
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Generator polynomial of the [23,12,7] code: x^11+x^10+x^6+x^5+x^4+x^2+1.
GENERATOR = 0b110001110101


def fingerprint(text: bytes, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """64 bits; a bit is one if it is set in over half of the shingles' hashes. No words: zero."""
    words = text.lower().split()
    if not words:
        return 0
    flat = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    k = min(shingle, len(words))
    starts = np.append(0, ends[:-1] + 1)[: len(words) - k + 1].tolist()
    digest = xxhash.xxh64_intdigest
    ones, n = np.zeros(64, np.int64), len(starts)
    pairs = list(zip(starts, ends[k - 1 :].tolist(), strict=True))
    for lo in range(0, n, 65535 // 2):
        h = np.array([digest(flat[a:b], seed) for a, b in pairs[lo : lo + 65535 // 2]], np.uint64)
        ones += np.unpackbits(h.view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.uint16)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def _fingerprints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = [fingerprint(t.as_buffer().to_pybytes() if t.is_valid else b"", shingle) for t in batch.column("text")]
            out = {n: batch.column(n) for n in batch.schema.names if n != "text"}
            yield pa.RecordBatch.from_pydict(out | {"fp": pa.array(np.array(prints, np.uint64).view(np.int64))})

    return run


@lru_cache(1)
def _decoder() -> np.ndarray:
    """The error pattern (of weight at most 3) of each of the 2^11 syndromes."""
    single = np.array([_syndrome(np.array([1 << i], np.uint32))[0] for i in range(23)], np.uint32)
    out = np.zeros(1 << 11, np.uint32)
    for i in range(23):
        out[single[i]] = 1 << i
        for j in range(i):
            out[single[i] ^ single[j]] = 1 << i | 1 << j
            for k in range(j):
                out[single[i] ^ single[j] ^ single[k]] = 1 << i | 1 << j | 1 << k
    return out


def _syndrome(words: np.ndarray) -> np.ndarray:
    left = words.astype(np.uint32)
    for bit in range(22, 10, -1):
        left = left ^ np.where(left >> np.uint32(bit) & np.uint32(1), np.uint32(GENERATOR << (bit - 11)), np.uint32(0))
    return left


def nearest_codeword(words: np.ndarray) -> np.ndarray:
    """The index (12 bits) of the one codeword within three bits of each word of 23 bits."""
    return (words.astype(np.uint32) ^ _decoder()[_syndrome(words)]) >> np.uint32(11)


def nearby_codewords(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word number, index) of all codewords within four bits of each word: one, or six where the nearest is three off."""
    flips = np.concatenate([[0], 1 << np.arange(23)]).astype(np.uint32)
    found = nearest_codeword((words.astype(np.uint32)[:, None] ^ flips).ravel()).reshape(-1, 24)
    found.sort(1)
    new = np.ones(found.shape, bool)
    new[:, 1:] = found[:, 1:] != found[:, :-1]
    return np.nonzero(new)[0], found[new]


def fuzzy_keys(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(fingerprint number, key): any two fingerprints that differ in at most three bits share a key.

    Of three segments, the two with fewer errors have at most one each. For each pair of segments there are two kinds of keys
    of the same form: any nearby codeword of the first with the nearest of the second, and the nearest of the first with any
    nearby of the second. A word one bit off has the nearest codeword of the other among its nearby ones, so of two such
    fingerprints one's keys of the first kind meet the other's of the second.
    """
    parts = [(prints >> np.uint64(at) & np.uint64((1 << width) - 1)).astype(np.uint32) for at, width in SEGMENTS]
    near = [nearest_codeword(p) for p in parts]
    about = [nearby_codewords(p) for p in parts]
    who, keys = [], []
    for i, j in ((0, 1), (0, 2), (1, 2)):
        tag = np.int64((3 * i + j) << 24)
        for first in (True, False):
            row, code = about[i if first else j]
            one, two = (code, near[j][row]) if first else (near[i][row], code)
            who.append(row)
            keys.append(tag | one.astype(np.int64) << 12 | two.astype(np.int64))
    who, keys = np.concatenate(who), np.concatenate(keys)
    both = np.unique(keys << 31 | who)  # a fingerprint's two kinds share a key
    return both & ((1 << 31) - 1), both >> 31


def _keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        prints = batch.column("fp").to_numpy()
        for lo in range(0, len(prints), 5000):
            part = prints[lo : lo + 5000]
            who, keys = fuzzy_keys(part.view(np.uint64))
            yield pa.record_batch([pa.array(keys), pa.array(part[who])], ["key", "fp"])


def _linked(prints: np.ndarray, distance: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links that connect what is connected by pairs within the distance: a walk in which each fingerprint is
    compared with those not reached yet, all at once. No pair is written but those of the walk."""
    left, out = prints, []
    while len(left) > 1:
        todo, left = [left[0]], left[1:]
        while todo and len(left):
            at = todo.pop()
            close = np.bitwise_count(left ^ at) <= distance
            if close.any():
                out.append((np.full(int(close.sum()), at, np.uint64), left[close]))
                todo += left[close].tolist()
                left = left[~close]
    return out


def _links(distance: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_key, kept = None, np.zeros(0, np.uint64)

        def found(groups: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            links = [x for g in groups for x in _linked(g, distance)]
            if links:
                a, b = (np.concatenate([x[i] for x in links]).astype(np.uint64).view(np.int64) for i in (0, 1))
                yield pa.record_batch([pa.array(a), pa.array(b)], ["a", "b"])

        for batch in batches:
            key, fp = batch.column("key").to_numpy(), batch.column("fp").to_numpy().view(np.uint64)
            if not len(key):
                continue
            cuts = np.append(np.flatnonzero(np.append(True, key[1:] != key[:-1])), len(key))
            groups = []
            if kept_key != key[0]:
                groups.append(kept)
                kept = np.zeros(0, np.uint64)
            big = np.flatnonzero(np.diff(cuts) > 1)
            last = len(cuts) - 2
            if last:
                groups.append(np.concatenate([kept, fp[: cuts[1]]]))
                groups += [fp[cuts[g] : cuts[g + 1]] for g in big if 0 < g < last]
                kept = np.zeros(0, np.uint64)
            kept_key, kept = key[-1], np.concatenate([kept, fp[cuts[last] :]])
            yield from found(groups)
        yield from found([kept])

    return run


def near_groups(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """doc_id, fingerprint and component_id for every row of docs(doc_id, text).

    Rows with one fingerprint are one class, so a large group of copies is one row from there on. Classes meet by fuzzy keys
    (fuzzy_keys) and are verified by their distance; per key only the links of a walk are written, never all its pairs. A
    component's id is the least doc_id in it. Null or empty text, and text without words, has fingerprint zero and links
    like any other. Null ids come before all others and give a null component_id. A distance over three is an error, as
    fuzzy keys are proven for three bits.
    """
    if distance > DISTANCE:
        raise ValueError(f"fuzzy keys find up to {DISTANCE} differing bits, not {distance}")
    rows = docs.select(id_or_least().alias("id"), text_or_empty().alias("text")).mapInArrow(_fingerprints(shingle), "id long, fp long")
    rows = written(rows, "fingerprints")
    classes = written(rows.groupBy("fp").agg(F.min("id").alias("least")), "classes")
    keyed = classes.select("fp").mapInArrow(_keyed, "key long, fp long").repartition("key").sortWithinPartitions("key", "fp")
    roots = components(keyed.mapInArrow(_links(distance), "a long, b long"))
    known = written(classes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "least", F.coalesce("root", "fp").alias("root")), "rooted")
    least = known.groupBy("root").agg(F.min("least").alias("component"))
    named = written(known.join(least, "root").select("fp", "component"), "components")
    return rows.join(named, "fp").select(
        id_back("id").alias("doc_id"),
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        id_back("component").alias("component_id"),
    )


def one_of_each_group(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """docs(doc_id, ...) without the documents that are not the least doc_id of their component; rows of one id stay together."""
    groups = near_groups(docs.select("doc_id", "text"), shingle, distance)
    stays = F.col("doc_id").eqNullSafe(F.col("component_id"))
    goes = groups.groupBy(id_or_least().alias("goes")).agg(F.max(stays).alias("stays")).where(~F.col("stays"))
    # What goes is the smaller side: while it is small, documents' texts aren't shuffled.
    return docs.join(written(goes.select("goes"), "goes"), id_or_least() == F.col("goes"), "left_anti")


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(table(spark, sf_dir, "documents", "doc_id", "text"))
