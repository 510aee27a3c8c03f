"""Suffix-array dedup: bytes covered by strings of a given length that start elsewhere too, by difference-cover sorting.

Three steps. (1) Anchors: of the grams in each window of the length, the one of least hash is its anchor, so equal windows have
equal anchors at the same place; windows whose anchor occurs once can't repeat. (2) What windows of a repeated anchor see is
grouped by a longer gram around the anchor, and equal contexts become one. (3) Contexts that differ within a group are dealt
by group, and each lot is suffix-sorted by a difference cover: sampled triples are sorted and named, names are made triples
again until they cover the length, the other suffixes are merged in, and neighbours are compared. Steps 1 and 2 only leave out
what provably has no partner, or has one; nothing is sampled or capped. A group of very many contexts is no single lot: its
contexts are cut into narrower ones with longer grams first, and again if need be, so that they spread over many groups.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .chunk_dedup import cut_out, runs
from .common import discard, id_back, id_or_least, small_or_joined, table, text_or_empty, written

#: Bytes of a repeated string, and of an anchor.
LENGTH, ANCHOR = 200, 64
#: Up to so many repeated anchors (16 bytes each) are broadcast; beyond that they are joined by a shuffle.
FEW_ANCHORS = 1_000_000
#: Texts unpacked at a time, so that their contexts as Python objects take little memory.
_TEXTS = 250
#: Windows of a text handled at a time, and bytes of one lot of the suffix sort.
_SEGMENT, _LOT = 400_000, 2_000_000
#: A group of more contexts is cut, and how many windows its parts have at each cut. A part of one window is its own gram.
CROWD, _WIDTHS = 5_000, (9, 2, 1)
_BASE = 0x9E3779B97F4A7C15


@lru_cache(1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    inverse = pow(_BASE, -1, 2**64)
    return tuple(np.cumprod(np.append(np.ones(1, np.uint64), np.full(n, b, np.uint64))) for b in (_BASE, inverse))


def gram_hashes(raw: np.ndarray, size: int) -> np.ndarray:
    """A mixed polynomial hash of every gram of so many bytes; equal grams have equal hashes wherever they stand."""
    up, down = _powers(_SEGMENT + 2048)
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=sums[1:])
    h = (sums[size:] - sums[:-size]) * down[: len(raw) - size + 1]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


def _sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """The least of every `width` neighbours: running minima forward and backward in blocks of that width."""
    n = len(x) - width + 1
    full = np.full(-(-len(x) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    full[: len(x)] = x
    block = full.reshape(-1, width)
    ahead = np.minimum.accumulate(block, 1).ravel()
    back = np.minimum.accumulate(block[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[width - 1 : width - 1 + n])


def anchors(raw: np.ndarray, length: int, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, place of the anchor, first window) of each run of windows with one anchor; runs follow without gaps."""
    out: list[list[np.ndarray]] = [[], [], []]
    for lo in range(0, len(raw) - length + 1, _SEGMENT):
        h = gram_hashes(raw[lo : lo + _SEGMENT + length - 1], size)
        # The high bits of the hash, then the place: the leftmost of equal grams is the anchor.
        key = (h & ~np.uint64((1 << 20) - 1)) | np.arange(len(h), dtype=np.uint64)
        least = _sliding_least(key, length - size + 1)
        first = np.flatnonzero(np.append(True, least[1:] != least[:-1]))
        place = (least[first] & np.uint64((1 << 20) - 1)).astype(np.int64)
        for o, x in zip(out, (h[place], place + lo, first + lo), strict=True):
            o.append(x)
    return tuple(np.concatenate(o) if o else np.zeros(0, np.int64) for o in out)


_ANCHORS = "uid long, doc long, sha binary, n_bytes long, h array<long>, pos array<int>, lo array<int>"


def _anchored(length: int, size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        uid = TaskContext.get().partitionId() << 33
        for batch in batches:
            found, sizes = [], []
            for t in batch.column("text"):
                raw = np.frombuffer(t.as_buffer(), np.uint8) if t.as_buffer().size else np.zeros(0, np.uint8)
                sizes.append(len(raw))
                found.append(anchors(raw, length, size))
            n = batch.num_rows
            at = np.append(0, np.cumsum([len(f[0]) for f in found])).astype(np.int32)
            lists = [pa.ListArray.from_arrays(at, np.concatenate([f[i] for f in found]).astype(kind)) if n else pa.array([], pa.list_(pa.from_numpy_dtype(kind))) for i, kind in enumerate((np.int64, np.int32, np.int32))] if n else None
            if n:
                yield pa.record_batch([pa.array(np.arange(uid, uid + n)), batch.column("doc"), batch.column("sha"), pa.array(sizes, pa.int64()), *lists], ["uid", "doc", "sha", "n_bytes", "h", "pos", "lo"])
            uid += n

    return run


def _few(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo in range(0, batch.num_rows, _TEXTS):
            yield batch.slice(lo, _TEXTS)


_SEEN = "k1 long, k2 long, c1 long, c2 long, uid long, a int, n int, d int"
_PARTS = f"p1 long, p2 long, p3 long, p4 long, shift int, {_SEEN}"


def _contexts(length: int, size: int):
    """For each run of windows with a repeated anchor: those that hold more to the left of it, and the others. Both see a gram
    of half the rest of the window besides the anchor, which keys them; c1, c2 digest all they see and where the anchor is: d bytes after the first of the windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        half = (length - size) // 2
        digest = xxhash.xxh3_128_digest
        for batch in _few(batches):
            keys, seen, uids, first, count, before = [], [], [], [], [], []
            for uid, t, runs_ in zip(batch.column("uid").to_pylist(), batch.column("text"), batch.column("runs").to_pylist(), strict=True):
                raw = t.as_buffer().to_pybytes()
                for r in runs_:
                    pos, lo, hi = r["pos"], r["lo"], r["hi"]
                    for tag, a, b, gram in ((b"<", lo, min(hi, pos - half), pos - half), (b">", max(lo, pos - half + 1), hi, pos)):
                        if a <= b:
                            keys.append(digest(tag + raw[gram : gram + size + half]))
                            seen.append(digest(raw[a : b + length] + (pos - a).to_bytes(4, "little") + tag))
                            uids.append(uid)
                            first.append(a)
                            count.append(b - a + 1)
                            before.append(pos - a)
            if uids:
                yield _seen_batch([], keys, seen, uids, first, count, before)

    return run


def _seen_batch(parents: list[pa.Array], keys: list[bytes], seen: list[bytes], uids: list[int], *places: list[int]) -> pa.RecordBatch:
    k, c = (np.frombuffer(b"".join(x), "<i8").reshape(-1, 2).T.copy() for x in (keys, seen))
    names = [x.split()[0] for x in (_PARTS if parents else _SEEN).split(", ")]
    return pa.record_batch([*parents, *map(pa.array, (*k, *c)), pa.array(uids, pa.int64()), *(pa.array(x, pa.int32()) for x in places)], names)


def _parts(length: int, width: int):
    """Contexts cut where the anchor's distance from a window is a multiple of width; a part is keyed by the gram that all
    windows of such a part share, and equal windows still meet, as they are as far from their anchors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_128_digest
        for batch in _few(batches):
            parents, shift, keys, seen, uids, first, count, before = [], [], [], [], [], [], [], []
            for uid, t, wanted in zip(batch.column("uid").to_pylist(), batch.column("text"), batch.column("wanted").to_pylist(), strict=True):
                raw = t.as_buffer().to_pybytes()
                for w in wanted:
                    pos, least = w["a"] + w["d"], w["d"] - w["n"] + 1
                    for block in range(least // width, w["d"] // width + 1):
                        far, near = min(w["d"], block * width + width - 1), max(least, block * width)
                        gram = raw[pos - block * width : pos - (block * width + width - 1) + length]
                        tag = f"{width} {block} ".encode()
                        parents.append((w["k1"], w["k2"], w["c1"], w["c2"]))
                        shift.append(w["d"] - far)
                        keys.append(digest(tag + gram))
                        seen.append(digest(tag + raw[pos - far : pos - near + length] + far.to_bytes(4, "little")))
                        uids.append(uid)
                        first.append(pos - far)
                        count.append(far - near + 1)
                        before.append(far)
            if uids:
                own = [pa.array(x) for x in np.array(parents, np.int64).T.copy()]
                yield _seen_batch([*own, pa.array(shift, pa.int32())], keys, seen, uids, first, count, before)

    return run


def _fetched(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _few(batches):
            out: dict[str, list] = {k: [] for k in ("k1", "k2", "c1", "c2", "seen")}
            for t, wanted in zip(batch.column("text"), batch.column("wanted").to_pylist(), strict=True):
                raw = t.as_buffer().to_pybytes()
                for w in wanted:
                    for k in ("k1", "k2", "c1", "c2"):
                        out[k].append(w[k])
                    out["seen"].append(raw[w["a"] : w["a"] + w["n"] - 1 + length])
            yield pa.RecordBatch.from_pydict({k: pa.array(v, pa.binary() if k == "seen" else pa.int64()) for k, v in out.items()})

    return run


def _named(*symbols: np.ndarray) -> tuple[np.ndarray, int]:
    """The rank of each tuple of symbols among the distinct tuples, and their number."""
    order = np.lexsort(symbols[::-1])
    new = np.zeros(len(order), bool)
    for s in symbols:
        x = s[order]
        new[1:] |= x[1:] != x[:-1]
    names = np.empty(len(order), np.int64)
    names[order] = np.cumsum(new)
    return names, int(new.sum()) + 1 if len(order) else 0


def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """All places of a byte text in an order of their suffixes that is right as far as `depth` bytes at least.

    The difference cover modulo 3: places 1 and 2 (mod 3) are sampled. Their first names are those of triples of symbols of
    eight bytes each; a triple of names three times as far apart (a multiple of three, so sampled too) is named in turn, and
    so on until names tell all sampled suffixes apart or cover the depth. A place 0 (mod 3) sorts by its byte and the name of
    the sampled place after it, and is merged among places 1 by one byte and a name, among places 2 by two bytes and a name.
    """
    n = len(text)
    padded = np.concatenate([text, np.zeros(32, np.uint8)])
    word = np.zeros(n + 24, np.uint64)
    for k in range(8):
        word = word << np.uint64(8) | np.concatenate([padded[k:], np.zeros(k, np.uint8)])[: n + 24].astype(np.uint64)
    sampled = np.flatnonzero(np.arange(n) % 3)
    names, distinct = _named(word[sampled], word[sampled + 8], word[sampled + 16])
    span = 24
    rank = np.zeros(n + 2, np.int64)  # the name of a sampled place; beyond the text: 0, before all
    while True:
        rank[sampled] = names + 1
        if distinct == len(sampled) or span >= depth:
            break
        beyond = lambda far: np.where(sampled + far < n, rank[np.minimum(sampled + far, n)], 0)
        names, distinct = _named(names, beyond(span), beyond(2 * span))
        span *= 3
    order = sampled[np.argsort(names, kind="stable")]
    rest = np.arange(0, n, 3)
    one = padded[rest].astype(np.int64) << 40 | rank[rest + 1]
    by = np.argsort(one, kind="stable")
    rest, one = rest[by], one[by]
    two = padded[rest].astype(np.int64) << 48 | padded[rest + 1].astype(np.int64) << 40 | rank[np.minimum(rest + 2, n + 1)]
    ones, twos = order[order % 3 == 1], order[order % 3 == 2]
    before = np.searchsorted(padded[ones].astype(np.int64) << 40 | np.where(ones + 1 < n, rank[np.minimum(ones + 1, n + 1)], 0), one)
    before += np.searchsorted(padded[twos].astype(np.int64) << 48 | padded[twos + 1].astype(np.int64) << 40 | np.where(twos + 2 < n, rank[np.minimum(twos + 2, n + 1)], 0), two)
    return np.insert(order, before, rest)


def windows_that_repeat(seen: list[bytes], length: int) -> list[np.ndarray]:
    """For each context, which of its windows occur at another place of these contexts too."""
    sizes = np.array([len(s) for s in seen], np.int64)
    begin = np.cumsum(sizes) - sizes
    text = np.frombuffer(b"".join(seen), np.uint8)
    window = np.zeros(len(text), bool)
    for b, s in zip(begin.tolist(), sizes.tolist(), strict=True):
        window[b : b + s - length + 1] = True
    order = suffix_order(text, length)
    order = order[window[order]]
    tail = np.concatenate([text, np.zeros(8, np.uint8)])
    same = np.arange(len(order) - 1)  # neighbours that agree so far
    for k in range(0, length, 8):
        k = min(k, length - 8)
        for j in range(k, k + 8):
            same = same[tail[order[same] + j] == tail[order[same + 1] + j]]
            if not len(same):
                break
    hit = np.zeros(len(text), bool)
    hit[order[same]] = hit[order[same + 1]] = True
    return [hit[b : b + s - length + 1] for b, s in zip(begin.tolist(), sizes.tolist(), strict=True)]


def _spans(flags: np.ndarray) -> list[dict]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.view(np.int8), [0]])))
    return [{"start": int(a), "end": int(b)} for a, b in zip(edge[::2], edge[1::2], strict=True)]


def _sorted_lots(length: int):
    kinds = {"k1": pa.int64(), "k2": pa.int64(), "c1": pa.int64(), "c2": pa.int64()}
    spans = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def judged(lot: list[dict]) -> pa.RecordBatch:
        hits = windows_that_repeat([r["seen"] for r in lot], length)
        return pa.RecordBatch.from_pydict({k: pa.array([r[k] for r in lot], t) for k, t in kinds.items()} | {"hits": pa.array([_spans(h) for h in hits], spans)})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lot, size = [], 0
        for batch in batches:
            for r in batch.to_pylist():
                if size >= _LOT and (r["k1"], r["k2"]) != (lot[-1]["k1"], lot[-1]["k2"]):
                    yield judged(lot)
                    lot, size = [], 0
                lot.append(r)
                size += len(r["seen"])
        if lot:
            yield judged(lot)

    return run


def _outcomes(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            removed, counts, digests = [], [], []
            for t, b, e in zip(batch.column("text"), batch.column("start"), batch.column("end"), strict=True):
                raw = t.as_buffer().to_pybytes()
                spans = runs(b.values.to_numpy(), e.values.to_numpy() - 1 + length, 1)
                removed.append(int((spans[:, 1] - spans[:, 0]).sum()))
                counts.append(len(spans))
                digests.append(hashlib.sha256(cut_out(raw, spans)).hexdigest())
            yield pa.record_batch([batch.column("uid"), pa.array(removed, pa.int64()), pa.array(counts, pa.int64()), pa.array(digests, pa.string())], ["uid", "n_removed", "n_spans", "kept_sha256"])

    return run


def _texts(docs: DataFrame) -> DataFrame:
    text = text_or_empty()
    return docs.select(id_or_least().alias("doc"), F.unhex(F.sha2(text.cast("binary"), 256)).alias("sha"), text.cast("binary").alias("text"))


_CONTEXT, _KEY = ["k1", "k2", "c1", "c2"], ["k1", "k2"]
_SPANS = "array<struct<start:int,end:int>>"


def _hits(touched: DataFrame, contexts: DataFrame, length: int, crowd: int, widths: tuple[int, ...]) -> DataFrame:
    """k1, k2, c1, c2 and hits, the spans of windows that repeat, counted from the context's first; a context may have several rows."""
    # A place has each of its contexts once, so a context counted twice stands at two places.
    distinct = contexts.groupBy(*_CONTEXT).agg(F.min(F.struct("uid", "a")).alias("at"), F.first("n").alias("n"), F.first("d").alias("d"), (F.count("*") > 1).alias("copied"))
    distinct = written(distinct, "distinct")
    groups = written(distinct.groupBy(*_KEY).agg(F.count("*").alias("contexts")).where("contexts > 1"), "groups")
    crowded = F.col("contexts") > crowd if widths else F.lit(False)

    def asked(keys: DataFrame, *columns) -> DataFrame:
        """Texts with what is wanted of them: the contexts of these groups, each at one of its places."""
        wanted = distinct.join(keys.select(*_KEY), _KEY, "left_semi").select("at.uid", F.struct(*_CONTEXT, "at.a", "n", *columns).alias("w"))
        return touched.select("uid", "text").join(wanted.groupBy("uid").agg(F.collect_list("w").alias("wanted")), "uid")

    # One context in a group: its windows repeat if the context does. More: the suffix sort tells.
    seen = asked(groups.where(~crowded)).mapInArrow(_fetched(length), "k1 long, k2 long, c1 long, c2 long, seen binary")
    lots = seen.repartition(*_KEY).sortWithinPartitions(*_KEY)
    judged = written(lots.mapInArrow(_sorted_lots(length), f"k1 long, k2 long, c1 long, c2 long, hits {_SPANS}"), "judged")
    whole = F.array(F.struct(F.lit(0).alias("start"), F.col("n").alias("end"))).cast(_SPANS)
    hits = distinct.where("copied").select(*_CONTEXT, whole.alias("hits")).unionByName(judged.where(F.size("hits") > 0))
    spent = [judged]
    if not groups.where(crowded).isEmpty():
        parts = written(asked(groups.where(crowded), "d").mapInArrow(_parts(length, widths[0]), _PARTS), "parts")
        below = _hits(touched, parts, length, crowd, widths[1:])
        moved = F.transform("hits", lambda x: F.struct((x["start"] + F.col("shift")).alias("start"), (x["end"] + F.col("shift")).alias("end")))
        parents = [F.col(f"p{i}").alias(c) for i, c in enumerate(_CONTEXT, 1)]
        hits = hits.unionByName(parts.join(below, _CONTEXT).select(*parents, moved.cast(_SPANS).alias("hits")))
        spent += [parts, below]
    out = written(hits, "hits")
    discard(distinct, groups, *spent)
    return out


def repeated_bytes(docs: DataFrame, length: int = LENGTH, anchor: int = ANCHOR, crowd: int = CROWD) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of docs(doc_id, text).

    A byte goes if a string of `length` bytes that covers it starts anywhere else too, in the same document or another; all
    occurrences go. Strings are judged on the input and never cross documents. Null text is empty; shorter texts stay whole.
    Rows of one text are one text with copies: all of it goes if it is long enough. Null ids are returned as such.
    """
    texts = _texts(docs)
    rows = written(texts.mapInArrow(_anchored(length, anchor), _ANCHORS), "anchors")
    same = written(rows.groupBy("sha").agg(F.min("uid").alias("uid"), F.count("*").alias("copies"), F.first("n_bytes").alias("n_bytes")), "texts")
    # Each anchor with its windows lo..hi; copies of a text give the same v and don't count as repeats of each other.
    upto = F.concat(F.slice("lo", 2, F.size("lo")), F.array((F.col("n_bytes") - length + 1).cast("int")))
    each = rows.where(F.size("h") > 0).select("uid", F.xxhash64("sha").alias("t"), F.explode(F.arrays_zip("h", "pos", "lo", upto.alias("next"))).alias("x"))
    each = each.select("uid", "t", "x.h", "x.pos", "x.lo", (F.col("x.next") - 1).alias("hi"))
    v = F.xxhash64("t", "pos")
    again = written(each.groupBy("h").agg(F.min(v).alias("least"), F.max(v).alias("most")).where("least != most").select("h"), "again")
    marked = each.join(small_or_joined(again, FEW_ANCHORS), "h").groupBy("uid").agg(F.collect_list(F.struct("pos", "lo", "hi")).alias("runs"))
    own = rows.select("uid", "doc", "sha").join(same.select("uid"), "uid", "left_semi").join(marked, "uid")
    kept = texts.join(own, ["doc", "sha"]).dropDuplicates(["doc", "sha"]).select("uid", "text", "runs")
    touched = written(kept, "touched")

    contexts = written(touched.mapInArrow(_contexts(length, anchor), _SEEN), "contexts")
    widths = tuple(w for w in _WIDTHS if w < length - anchor)
    hits = _hits(touched, contexts, length, crowd, widths)
    found = contexts.join(hits, _CONTEXT).select("uid", "a", F.explode("hits").alias("x"))
    found = found.groupBy("uid").agg(F.collect_list(F.struct((F.col("a") + F.col("x.start")).alias("start"), (F.col("a") + F.col("x.end")).alias("end"))).alias("x"))
    cut = touched.select("uid", "text").join(found.select("uid", "x.start", "x.end"), "uid")
    cut = written(cut.mapInArrow(_outcomes(length), "uid long, n_removed long, n_spans long, kept_sha256 string"), "cut")

    gone = (F.col("copies") > 1) & (F.col("n_bytes") >= length)
    none = F.lit(hashlib.sha256(b"").hexdigest())
    outcome = same.join(cut, "uid", "left").select(
        "sha",
        F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).alias("n_removed"),
        F.when(gone, F.lit(1)).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(gone, none).otherwise(F.coalesce("kept_sha256", F.lower(F.hex("sha")))).alias("kept_sha256"),
    )
    outcome = written(outcome, "outcome")
    discard(touched, contexts, hits, again)
    return rows.select("doc", "sha", "n_bytes").join(outcome, "sha").select(id_back("doc").alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_bytes(table(spark, sf_dir, "documents", "doc_id", "text"))
