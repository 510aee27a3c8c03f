"""SimHash near-dedup for a Jaccard similarity: fuzzy Golay keys of a wide fingerprint propose, whole sets of shingles decide.

A fingerprint of 64 bits and three errors finds next to nothing at a similarity of 0.8, where about 15 % of the bits differ. So
the fingerprint here has eight words of the code, every pair of words gives fuzzy keys as in simhash.py, and a set of shingles
is counted against another one's before they are linked.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, discard, giving_back, id_or_least, small_or_joined, text_or_empty, written
from .components import components
from .simhash import nearby_codewords, nearest_codeword

#: Shingle length in words, the least similarity of a link as a fraction, seed of the shingle hash.
SHINGLE, ALIKE, SEED = 5, (4, 5), 43
#: Words of the code in a fingerprint and bits of a word. Bits beside them that go along with a key.
WORDS, WIDTH, EXCERPT = 8, 23, 29
#: Most differing bits between two excerpts, and between all words of two sets that may be alike: over three standard
#: deviations above what a similarity of 0.8 gives (4.4 and 27.9 on average).
EXCERPT_FAR, FAR = 10, 45
#: One in so many buckets is walked first; all others follow between the components so found.
FIRST = 8
#: Lists of up to so many classes go by their least class, so that what they share is joined once; longer ones go alone.
SHORT = 64
#: Up to so many rows, a table of ids is broadcast to the texts.
FEW_ROWS = 200_000
#: Bytes of sets that one batch holds, and names of lists that a task remembers.
_LOT, _KNOWN = 4_000_000, 1 << 17
_SALTS = np.random.default_rng(20240611).integers(1, 2**63, 4, dtype=np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15)


def shingles(text: bytes, shingle: int = SHINGLE) -> np.ndarray:
    """The hashes of a text's different shingles, ascending; a shorter text is one shingle, one without words has none."""
    words = text.lower().split()
    k = min(shingle, len(words))
    if not k:
        return np.zeros(0, np.uint64)
    flat = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.append(0, ends[:-1] + 1)[: len(words) - k + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(flat[a:b], SEED) for a, b in zip(starts, ends[k - 1 :].tolist(), strict=True)], np.uint64))


def class_of(found: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(found.tobytes(), SEED)).astype(np.int64))


def wide_print(found: np.ndarray) -> np.ndarray:
    """256 bits as four numbers; a bit is one if it is set in over half of the set's hashes."""
    ones = np.zeros((4, 64), np.int64)
    for lo in range(0, len(found), 1 << 15):
        for row, salt in zip(ones, _SALTS, strict=True):
            h = (found[lo : lo + (1 << 15)] ^ salt) * _ODD
            h ^= h >> np.uint64(32)
            h *= _ODD
            row += np.unpackbits(h.view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.uint16)
    return np.packbits(2 * ones > len(found), axis=1, bitorder="little").view("<u8").ravel()


def _word(prints: np.ndarray, i: int) -> np.ndarray:
    at, shift = divmod(i * WIDTH, 64)
    bits = prints[:, at] >> np.uint64(shift)
    if shift + WIDTH > 64:
        bits = bits | prints[:, at + 1] << np.uint64(64 - shift)
    return (bits & np.uint64((1 << WIDTH) - 1)).astype(np.uint32)


def wide_keys(prints: np.ndarray, n: np.ndarray, alike: tuple[int, int] = ALIKE) -> tuple[np.ndarray, np.ndarray]:
    """(print number, token). A token is a key and, in its last bits, an excerpt of the print that is no part of the key.

    A key names a pair of words, two codewords and a class of sizes. The codewords are any nearby one of the first word with
    the nearest of the second, or the nearest with any nearby, so a print one bit off in each has the other's key. Sizes go by
    powers of two; a set that can be alike with one of the next class has the keys of both.
    """
    words = [_word(prints, i) for i in range(WORDS)]
    near = [nearest_codeword(w) for w in words]
    about = [nearby_codewords(w) for w in words]
    found = []
    for tag, (i, j) in enumerate(combinations(range(WORDS), 2)):
        for row, one, two in ((about[i][0], about[i][1], near[j][about[i][0]]), (about[j][0], near[i][about[j][0]], about[j][1])):
            found.append(((np.int64(tag) << 24 | one.astype(np.int64) << 12 | two) << 20) | row)
    found = np.unique(np.concatenate(found))
    who, code = found & ((1 << 20) - 1), found >> 20
    size = np.frexp(np.maximum(n, 1).astype(np.float64))[1].astype(np.int64) - 1
    border = (n.astype(np.int64) * alike[1] >= alike[0] << (size + 1))[who]
    excerpt = (prints[:, 3] & np.uint64((1 << EXCERPT) - 1)).astype(np.int64)
    who, code, size = np.concatenate([who, who[border]]), np.concatenate([code, code[border]]), np.concatenate([size[who], size[who[border]] + 1])
    return who, (code >> 24 << 29 | size << 24 | code & ((1 << 24) - 1)) << EXCERPT | excerpt[who]


def _texts(batch: pa.RecordBatch) -> Iterator[bytes]:
    for t in batch.column("text"):
        yield t.as_buffer().to_pybytes() if t.is_valid else b""


_PRINT = [f"f{i}" for i in range(4)]


def _described(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cls, n, prints = [], [], np.zeros((batch.num_rows, 4), np.uint64)
            for i, text in enumerate(_texts(batch)):
                found = shingles(text, shingle)
                cls.append(class_of(found))
                n.append(len(found))
                prints[i] = wide_print(found)
            words = [pa.array(np.ascontiguousarray(prints[:, i]).view(np.int64)) for i in range(4)]
            yield pa.record_batch([batch.column("id"), pa.array(cls, pa.int64()), pa.array(n, pa.int32()), *words], ["id", "cls", "n", *_PRINT])

    return run


def _prints(columns, rows: slice = slice(None)) -> np.ndarray:
    return np.column_stack([columns[c][rows] for c in _PRINT]).view(np.uint64)


def _tokens(alike: tuple[int, int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = {c: batch.column(c).to_numpy() for c in batch.schema.names}
            for lo in range(0, batch.num_rows, 1000):
                rows = slice(lo, lo + 1000)
                who, tokens = wide_keys(_prints(columns, rows), columns["n"][rows], alike)
                yield pa.record_batch([pa.array(tokens), pa.array(columns["cls"][rows][who])], ["token", "cls"])

    return run


def _columns(batches: list[pa.RecordBatch]) -> dict:
    whole = pa.Table.from_batches(batches).combine_chunks()
    columns = {c: whole.column(c).chunk(0) for c in whole.column_names}
    return {c: x if pa.types.is_list(x.type) else x.to_numpy() for c, x in columns.items()}


def _ended(batches: Iterator[pa.RecordBatch], key) -> Iterator[dict]:
    """A sorted partition's columns in parts that no run of equal keys crosses; key makes it of the columns."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = key(_columns([batch]))
        last = int(np.searchsorted(keys, keys[-1])) if keys[0] != keys[-1] else 0
        if held and key(_columns([held[0].slice(0, 1)]))[0] != keys[0] or last:
            yield _columns([*held, *([batch.slice(0, last)] if last else [])])
            held = []
        held.append(batch.slice(last))
    if held:
        yield _columns(held)


def _bounds(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    starts = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    return starts, np.append(starts[1:], len(keys))


def _pair_names(pairs: np.ndarray) -> np.ndarray:
    a, b = (pairs[:, i].view(np.uint64) for i in (0, 1))
    h = (a ^ (b * _ODD)) * _ODD
    return (h ^ h >> np.uint64(29)).view(np.int64)


def _near_excerpts(excerpt: np.ndarray) -> Iterator[np.ndarray]:
    """The parts of a bucket that steps between near excerpts connect; parts of one are left out."""
    left = np.arange(len(excerpt))
    while len(left) > 1:
        reached, todo, left = [left[:1]], [left[0]], left[1:]
        while todo and len(left):
            close = np.bitwise_count(excerpt[left] ^ excerpt[todo.pop()]) <= EXCERPT_FAR
            if close.any():
                reached.append(left[close])
                todo += left[close].tolist()
                left = left[~close]
        if len(reached) > 1:
            yield np.concatenate(reached)


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Lists of classes that share a key and have near excerpts, under a name that equal lists share; most are repeats."""
    known: set[int] = set()
    for part in _ended(batches, lambda c: c["token"] >> EXCERPT):
        excerpt, cls = part["token"] & ((1 << EXCERPT) - 1), part["cls"]
        starts, ends = _bounds(part["token"] >> EXCERPT)
        first = starts[ends - starts == 2]
        first = first[np.bitwise_count(excerpt[first] ^ excerpt[first + 1]) <= EXCERPT_FAR]
        pairs = np.sort(np.column_stack([cls[first], cls[first + 1]]), axis=1)
        pairs = np.unique(pairs[pairs[:, 0] != pairs[:, 1]], axis=0)
        names, lists = [_pair_names(pairs)], [pairs.ravel()]
        sizes = [np.full(len(pairs), 2)]
        for a, b in zip(starts[ends - starts > 2].tolist(), ends[ends - starts > 2].tolist(), strict=True):
            for rows in _near_excerpts(excerpt[a:b]):
                own = np.unique(cls[a:b][rows])
                name = class_of(own) if len(own) != 2 else int(_pair_names(own[None])[0])
                if len(own) > 1 and name not in known:
                    if len(known) < _KNOWN:  # what repeats beyond that, or in other partitions, goes later
                        known.add(name)
                    names.append(np.array([name]))
                    lists.append(own)
                    sizes.append(np.array([len(own)]))
        at = np.append(0, np.cumsum(np.concatenate(sizes))).astype(np.int32)
        if len(at) > 1:
            yield pa.record_batch([pa.array(np.concatenate(names)), pa.ListArray.from_arrays(at, np.concatenate(lists))], ["bucket", "classes"])


def _listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each class of a list. A list's number is its own within the task; the last bit tells those that are walked first."""
    at = 0
    for batch in batches:
        size, bucket = batch.column("classes").value_lengths().to_numpy(), batch.column("bucket").to_numpy()
        number = np.arange(at, at + len(size)) << 1 | (bucket % FIRST == 0)
        at += len(size)
        hub = batch.column("hub").to_numpy()
        yield pa.record_batch([pa.array(hub.repeat(size)), batch.column("classes").flatten(), pa.array(number.repeat(size))], ["hub", "cls", "number"])


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each class of a hub, with the numbers of the lists that it is in."""
    for part in _ended(_listed(batches), lambda c: c["hub"]):
        order = np.lexsort((part["number"], part["cls"], part["hub"]))
        hub, cls, number = (part[c][order] for c in ("hub", "cls", "number"))
        starts = np.flatnonzero(np.append(True, (hub[1:] != hub[:-1]) | (cls[1:] != cls[:-1])))
        lists = pa.ListArray.from_arrays(np.append(starts, len(hub)).astype(np.int32), number)
        yield pa.record_batch([pa.array(hub[starts]), pa.array(cls[starts]), lists], ["hub", "cls", "lists"])


def _lists(part: dict, between: bool) -> Iterator[np.ndarray]:
    """The rows of each list of the hubs in a part."""
    number = part["lists"].flatten().to_numpy()
    rows = np.repeat(np.arange(len(part["hub"])), part["lists"].value_lengths().to_numpy())
    if not between:
        rows, number = rows[number & 1 == 1], number[number & 1 == 1]
    hub = part["hub"][rows]
    order = np.lexsort((rows, number, hub))
    rows, number, hub = rows[order], number[order], hub[order]
    return iter(np.split(rows, np.flatnonzero((hub[1:] != hub[:-1]) | (number[1:] != number[:-1])) + 1) if len(rows) else [])


def _distances(n: np.ndarray, prints: np.ndarray, i: int, rows: np.ndarray, alike: tuple[int, int]) -> np.ndarray:
    """Differing bits between print i and those of the rows; beyond all bounds where the sizes can't be alike."""
    low, high = np.minimum(n[rows], n[i]), np.maximum(n[rows], n[i])
    return np.where(alike[1] * low >= alike[0] * high, np.bitwise_count(prints[rows] ^ prints[i]).sum(1, dtype=np.int64), FAR + 1)


def _tree(g: dict[str, np.ndarray], alike: tuple[int, int]) -> Iterator[tuple[int, np.ndarray]]:
    """Pairs that connect what near prints connect: a walk, each class against those not reached yet. It begins at the class
    that is first by size and name, so that the many buckets of one group give much the same pairs."""
    n, prints = g["n"].astype(np.int64), g["prints"]
    left = np.lexsort((g["cls"], n))
    while len(left) > 1:
        todo, left = [left[0]], left[1:]
        while todo and len(left):
            at = todo.pop(0)
            close = _distances(n, prints, at, left, alike) <= FAR
            if close.any():
                yield at, left[close]
                todo += left[close].tolist()
                left = left[~close]


def _between(g: dict[str, np.ndarray], alike: tuple[int, int]) -> Iterator[tuple[int, np.ndarray]]:
    """Between the components in a bucket, the nearest pairs that connect them: a spanning tree of least distances."""
    n, prints, root = g["n"].astype(np.int64), g["prints"], g["root"]
    if (root == root[0]).all():
        return
    best, by = np.full(len(n), FAR + 1), np.zeros(len(n), np.int64)
    left = np.ones(len(n), bool)
    grow = 0
    while True:
        joins = np.flatnonzero(left & (root == root[grow]))
        left[joins] = False
        rows = np.flatnonzero(left)
        if not len(rows):
            return
        for i in joins:
            d = _distances(n, prints, i, rows, alike)
            less = d < best[rows]
            best[rows[less]], by[rows[less]] = d[less], i
        grow = rows[best[rows].argmin()]
        if best[grow] <= FAR:
            yield grow, by[grow : grow + 1]


def _pairs(alike: tuple[int, int], between: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _ended(batches, lambda c: c["hub"]):
            prints, found = _prints(part)[:, :3], []
            prints[:, 2] &= np.uint64((1 << (WORDS * WIDTH - 128)) - 1)
            for rows in _lists(part, between):
                g = {c: part[c][rows] for c in ("cls", "n", *(["root"] if between else []))} | {"prints": prints[rows]}
                found += [(np.full(len(y), g["cls"][x]), g["cls"][y]) for x, y in (_between if between else _tree)(g, alike)]
            if found:
                x, y = (np.concatenate([f[i] for f in found]) for i in (0, 1))
                both = np.unique(np.sort(np.column_stack([x, y]), axis=1), axis=0)
                yield pa.record_batch([pa.array(np.ascontiguousarray(both[:, i])) for i in (0, 1)], ["a", "b"])

    return run


def _sets(shingle: int):
    def batch_of(cls: list[int], found: list[np.ndarray]) -> pa.RecordBatch:
        at = np.append(0, np.cumsum([len(f) for f in found])).astype(np.int32)
        return pa.record_batch([pa.array(cls, pa.int64()), pa.ListArray.from_arrays(at, np.concatenate(found).view(np.int64))], ["cls", "found"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cls, found, size = [], [], 0
            for text in _texts(batch):
                found.append(shingles(text, shingle))
                cls.append(class_of(found[-1]))
                size += found[-1].nbytes
                if size > _LOT:
                    yield batch_of(cls, found)
                    cls, found, size = [], [], 0
            if cls:
                yield batch_of(cls, found)

    return run


def _alike(docs: DataFrame, classes: DataFrame, pairs: DataFrame, shingle: int, alike: tuple[int, int]) -> DataFrame:
    """The pairs(a, b) whose shared and different shingles, counted, are alike."""
    pairs = written(pairs.distinct(), "pairs")
    nodes = pairs.select(F.explode(F.array("a", "b")).alias("cls")).distinct()
    wanted = written(classes.select("cls", "least").join(nodes, "cls").select("least").distinct(), "wanted")
    texts = docs.join(small_or_joined(wanted, FEW_ROWS), F.col("id") == F.col("least")).select("text")
    # Rows that repeat an id may bring other classes along, and copies of the same.
    sets = written(texts.mapInArrow(giving_back(_sets(shingle)), "cls long, found array<long>").dropDuplicates(["cls"]), "sets")
    one, two = sets.select(F.col("cls").alias("a"), F.col("found").alias("of_a")), sets.select(F.col("cls").alias("b"), F.col("found").alias("of_b"))
    shared = F.size(F.array_intersect("of_a", "of_b"))
    out = pairs.join(one, "a").join(two, "b").where(shared * sum(alike) >= (F.size("of_a") + F.size("of_b")) * alike[0]).select("a", "b")
    out = written(out, "links")
    discard(pairs, wanted, sets)
    return out


def near_copies(docs: DataFrame, shingle: int = SHINGLE, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """id and component for every row of docs(doc_id, text); null ids are NO_ID.

    Rows whose sets of shingles (of 64-bit hashes) are equal are one class, so copies are one row from there on. Classes meet
    by fuzzy keys (wide_keys); of those that met, a walk over near prints gives pairs, whose sets are counted: a link is a
    Jaccard similarity of alike[0]/alike[1] or more, and a component's name is the least id in it. One bucket in FIRST is walked;
    between the components so found, the nearest pairs of every bucket are counted too, so that a large group isn't paired
    as a whole. Lists of at most SHORT classes that share a bucket are gathered by their least class, and a class is joined with its
    print once for all of them: 616 lists at most, so a hub is bounded whatever the group. No link is wrong. How many are found depends on the similarity (tests measure it: about 0.86 of lone pairs at 0.8, 0.98 at 0.9 and
    all from 0.95 on); copies in groups are mostly linked through others. Null or empty text is a set without members.
    """
    docs = docs.select(id_or_least().alias("id"), text_or_empty().alias("text"))
    words = ", ".join(f"{c} long" for c in _PRINT)
    described = written(docs.mapInArrow(giving_back(_described(shingle)), f"id long, cls long, n int, {words}"), "described")
    classes = described.groupBy("cls").agg(F.min("id").alias("least"), *(F.any_value(c).alias(c) for c in ("n", *_PRINT)))
    classes = written(classes, "classes")
    key = F.shiftright("token", EXCERPT)
    met = classes.select("cls", "n", *_PRINT).mapInArrow(giving_back(_tokens(alike)), "token long, cls long").repartition(key).sortWithinPartitions("token")
    buckets = written(met.mapInArrow(giving_back(_buckets), "bucket long, classes array<long>").dropDuplicates(["bucket"]), "buckets")
    hub = F.when(F.size("classes") <= SHORT, F.array_min("classes")).otherwise(F.col("bucket"))
    lists = buckets.select(hub.alias("hub"), "bucket", "classes").repartition("hub").sortWithinPartitions("hub")
    members = lists.mapInArrow(giving_back(_gathered), "hub long, cls long, lists array<long>").join(classes.select("cls", "n", *_PRINT), "cls")
    members = written(members, "members")
    # A large group is linked by few of its many buckets; the rest are asked only what is not linked by then.
    first = members.where(F.exists("lists", lambda x: x.bitwiseAND(1) == 1))
    walk = first.repartition("hub").sortWithinPartitions("hub", "cls").mapInArrow(giving_back(_pairs(alike, False)), "a long, b long")
    links = _alike(docs, classes, walk, shingle, alike)
    roots = components(links)
    placed = members.join(roots, F.col("cls") == F.col("node"), "left").select(*members.columns, F.coalesce("root", "cls").alias("root"))
    rest = placed.repartition("hub").sortWithinPartitions("hub", "cls").mapInArrow(giving_back(_pairs(alike, True)), "a long, b long")
    more = _alike(docs, classes, rest, shingle, alike)
    roots = components(links.unionByName(more))
    known = classes.join(roots, F.col("cls") == F.col("node"), "left").select("cls", "least", F.coalesce("root", "cls").alias("root"))
    known = written(known, "rooted")
    least = known.groupBy("root").agg(F.min("least").alias("component"))
    out = written(described.select("id", "cls").join(known.join(least, "root").select("cls", "component"), "cls").select("id", "component"), "placed")
    discard(described, classes, buckets, members, links, more, known)
    return out


def one_of_each_group(docs: DataFrame, shingle: int = SHINGLE, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """docs(doc_id, ...) without the documents that are not the least doc_id of their component; rows of one id stay together."""
    groups = near_copies(docs.select("doc_id", "text"), shingle, alike)
    goes = groups.groupBy("id").agg(F.max(F.col("id") == F.col("component")).alias("stays")).where(~F.col("stays"))
    goes = written(goes.select("id"), "goes")
    # What goes is the smaller side: while it is small, documents' texts aren't shuffled.
    return docs.join(goes, F.coalesce(docs["doc_id"].cast("long"), F.lit(NO_ID)) == goes["id"], "left_anti")
