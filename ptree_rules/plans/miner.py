"""The level-wise miner on bit trees."""

from __future__ import annotations

import time
from collections.abc import Iterable, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.measures import Level, MiningStats
from ..functions.thresholds import Number, min_count
from ..operators.anding import _count_in_segment, and_words, build_segments, count_in_segments, segment_items
from ..operators.candidates import closed, joined
from ..operators.items import ItemDict, bitmap_long, build_items
from ..operators.ptree import build_words, root_counts
from ..operators.segment_trees import bound_counts, build_segment_trees, count_in_trees, rows_one_by_one
from ..operators.tids import SEGMENT, assign_tids
from ..sources.tables import written
from ..sources.workloads import InfoTable
from .results import Itemset, MiningResult, derive, strong_result

#: More candidates than this of one level are an error, never cut.
MOST_CANDIDATES = 2_000_000


class Trees:
    """A relation's trees, written once: counts of any itemsets come from them without reading the relation again.

    counting='trees': mask trees by segment, ANDed from the root down. 'segments': the same vectors flat, ANDed as a whole.
    'words': rows of 64 tuples, ANDed by built-in aggregates only.
    """

    def __init__(self, info: InfoTable, counting: str = "trees", reuse: str = "prefix", segment: int = SEGMENT, items: ItemDict | None = None):
        self.info, self.counting, self.reuse, self.segment, self.scans = info, counting, reuse, segment, 1
        self.spark = info.df.sparkSession
        # Numbering the items needs the domains; the same pass writes the rows' own values, so the relation is read once.
        rows = info.df if items else written(info.df, "relation")
        self.items = items or build_items(InfoTable(rows, info.conditions, info.decisions))
        if counting == "words":
            numbered = assign_tids(rows, mode="segment").withColumn("tid", F.col("segment") * SEGMENT + F.col("offset"))
            self.n = numbered.count()
            self.store = written(build_words(bitmap_long(numbered, self.items)).repartition("word_id"), "words")
            self.roots = {r.item_id: r.cnt for r in root_counts(self.store).collect()}  # a number per item
        else:
            self.store = self.packed(rows)
            self.roots, self.n = headers(self.store)

    def packed(self, rows: DataFrame) -> DataFrame:
        build = {"trees": build_segment_trees, "segments": build_segments}[self.counting]
        return written(build(rows, self.items, self.segment), self.counting)

    def count(self, candidates: Sequence[Itemset]) -> tuple[list[int], int, int]:
        """Counts of sorted itemsets, the ANDs done (of blocks, or of whole vectors; 0 where they aren't counted), and the
        blocks spared."""
        if not candidates:
            return [], 0, 0
        if self.counting == "trees":
            return count_in_trees(self.store, candidates, self.segment, self.reuse)
        if self.counting == "segments":
            return *count_in_segments(self.store, candidates, self.reuse), 0
        frame = self.spark.createDataFrame([(i, list(c)) for i, c in enumerate(candidates)], "cand_id int, items array<int>")
        got = {r.cand_id: r.cnt for r in and_words(self.store, frame).collect()}
        return [got.get(i, 0) for i in range(len(candidates))], 0, 0

    def hopeful(self, candidates: list[Itemset], least: int, bound: bool) -> list[Itemset]:
        """Candidates without those that the headers' bounds rule out, if asked for."""
        if not bound or not candidates:
            return candidates
        if self.counting != "trees":
            raise ValueError("bounds come from the headers of trees")
        return [c for c, most in zip(candidates, bound_counts(self.store, candidates), strict=True) if most >= least]


def headers(segments: DataFrame) -> tuple[dict[int, int], int]:
    """Root counts by item, and the number of tuples: one job over the headers."""
    heads = segment_items(segments).select("item_id", "root_cnt").union(segments.select(F.lit(-1), "n"))
    roots = {r.item_id: r.cnt for r in heads.groupBy("item_id").agg(F.sum("root_cnt").alias("cnt")).collect()}  # a number per item
    return roots, roots.pop(-1, 0)


def frequent_items(roots: dict[int, int], least: int) -> dict[Itemset, int]:
    """The frequent single items, from the root counts alone."""
    return {(i,): c for i, c in sorted(roots.items()) if c >= least}


def _checked(candidates: list[Itemset], most: int) -> list[Itemset]:
    if len(candidates) > most:
        raise ValueError(f"{len(candidates)} candidates; raise the support, set max_len, or raise max_candidates (now {most})")
    return candidates


def _free(trees: Trees, least: int, stats: MiningStats, max_len: int | None, most: int, bound: bool) -> dict[Itemset, int]:
    start = time.perf_counter()
    level = frequent_items(trees.roots, least)
    counts = dict(level)
    stats.levels.append(Level(1, len(trees.roots), 0, len(level), time.perf_counter() - start))
    k = 2
    while level and (max_len is None or k <= max_len):
        start = time.perf_counter()
        made = joined(level, trees.items.attribute)
        candidates = _checked(closed(made, set(level)), most)
        if not candidates:
            break
        hopeful = trees.hopeful(candidates, least, bound)
        got, ands, spared = trees.count(hopeful)
        level = {c: n for c, n in zip(hopeful, got, strict=True) if n >= least}
        counts |= level
        stats.levels.append(Level(k, len(candidates), len(made) - len(candidates), len(level), time.perf_counter() - start, ands, spared, len(candidates) - len(hopeful)))
        k += 1
    return counts


def _fixed(trees: Trees, least: int, decisions: Sequence[str], conditions: Sequence[str], stats: MiningStats, max_len: int | None, most: int, bound: bool) -> tuple[dict[Itemset, int], dict[Itemset, int]]:
    """Counts of antecedents, and of antecedents with one decision item. An antecedent grows while some decision item with it
    is frequent; both counts of a candidate come from the same pass."""
    attribute = trees.items.attribute
    goals = [i for i, a in enumerate(attribute) if a in decisions]
    usable = {i for i, a in enumerate(attribute) if a in conditions}
    # Antecedents of size 0: each decision item by itself.
    pairs: dict[tuple[Itemset, int], int] = {((), d): trees.roots.get(d, 0) for d in goals if trees.roots.get(d, 0) >= least}
    xs: dict[Itemset, int] = {}
    xys: dict[Itemset, int] = {(d,): c for (_, d), c in pairs.items()}
    k, level = 1, pairs
    while level and (max_len is None or k < max_len):
        start = time.perf_counter()
        if k == 1:
            made = [((i,), d) for i in sorted(usable) for d in goals if attribute[i] != attribute[d] and trees.roots.get(i, 0) >= least]
            candidates = [c for c in made if ((), c[1]) in level]
        else:
            made, candidates = [], []
            for d in goals:
                own = {x for x, e in level if e == d}
                new = joined(own, attribute)
                made += new
                candidates += [(x, d) for x in closed(new, own)]
        asked = len(_checked(candidates, most))
        hopeful = set(trees.hopeful(sorted({tuple(sorted((*x, d))) for x, d in candidates}), least, bound))
        candidates = [(x, d) for x, d in candidates if tuple(sorted((*x, d))) in hopeful]
        wanted = sorted({x for x, _ in candidates} | {tuple(sorted((*x, d))) for x, d in candidates})
        if not wanted:
            break
        got, ands, spared = trees.count(wanted)
        count = dict(zip(wanted, got, strict=True))
        level = {(x, d): c for x, d in candidates if (c := count[tuple(sorted((*x, d)))]) >= least}
        xs |= {x: count[x] for x, _ in level}
        xys |= {tuple(sorted((*x, d))): c for (x, d), c in level.items()}
        stats.levels.append(Level(k + 1, asked, len(made) - asked, len(level), time.perf_counter() - start, ands, spared, asked - len(candidates)))
        k += 1
    return xs, xys


def mine_ptree(
    info: InfoTable,
    minsup: Number,
    minconf: Number,
    decision: str | Iterable[str] | None = None,
    conditions: Sequence[str] | None = None,
    consequent: str = "single",
    strict: bool = False,
    criterion: str = "none",
    counting: str = "trees",
    reuse: str = "prefix",
    bound: bool = False,
    emit: str = "itemsets",
    max_len: int | None = None,
    max_candidates: int = MOST_CANDIDATES,
    trees: Trees | None = None,
) -> MiningResult:
    """Frequent itemsets and strong rules from bit trees.

    decision: an attribute, or several at once, that consequents are of; itemsets are then those with one decision item, and
    antecedents grow only beside a frequent decision item. None: any attribute may stand on either side. conditions restrict
    the antecedents' attributes (all others but the decision itself by default). The relation is read once; every level is one
    job over the trees that sends a row per candidate and task. bound: a job over the headers alone rules candidates out first,
    which pays where like tuples lie together. emit='strong': both thresholds are applied to each level as it is counted, and
    strong rules of one consequent come straight out of it (redundant ones by no criterion). max_len bounds itemset sizes; too many candidates are an error.
    """
    trees = trees or Trees(info, counting, reuse)
    stats = MiningStats("ptree", trees.n, len(trees.items.items), trees.scans)
    least = max(1, min_count(minsup, trees.n, strict))
    if emit == "strong" and (consequent != "single" or criterion != "none"):
        raise ValueError("strong rules out of the levels have one consequent and no criterion")
    if decision is None:
        if conditions is not None:
            raise ValueError("conditions need a decision")
        counts = _free(trees, least, stats, max_len, max_candidates, bound)
        if emit == "strong":
            return strong_result(trees.spark, counts, counts, None, trees.items, trees.n, minconf, strict, stats)
        return derive(trees.spark, counts, trees.items, trees.n, minconf, consequent, None, strict, criterion, stats)
    decisions = [decision] if isinstance(decision, str) else list(decision)
    xs, xys = _fixed(trees, least, decisions, conditions or info.attributes, stats, max_len, max_candidates, bound)
    if emit == "strong":
        return strong_result(trees.spark, xs | xys, xys, decisions, trees.items, trees.n, minconf, strict, stats)
    return derive(trees.spark, xs | xys, trees.items, trees.n, minconf, consequent, decisions, strict, criterion, stats, shown=xys)


def append_segments(trees: Trees, more: DataFrame) -> Trees:
    """The trees of the relation and further tuples: only these are packed; root counts add up. New values get new items, with
    numbers after those there are, so stored trees stay as they are; the number of new items is checked."""
    if trees.counting == "words":
        raise ValueError("words are not appended to; use trees or segments")
    out = Trees.__new__(Trees)
    out.__dict__ |= trees.__dict__
    fresh = build_items(InfoTable(more, trees.info.conditions, trees.info.decisions)).items
    known = set(trees.items.items)
    out.items = ItemDict((*trees.items.items, *(x for x in fresh if x not in known)), trees.items.decisions)
    last = trees.store.agg(F.max("segment_id")).first()[0]
    new = out.packed(more)
    added, n = headers(new)
    out.store = trees.store.unionByName(new.withColumn("segment_id", F.col("segment_id") + F.lit((last or 0) + 1)))
    out.n = trees.n + n
    out.roots = {i: trees.roots.get(i, 0) + added.get(i, 0) for i in {*trees.roots, *added}}
    return out


def _local_miner(share: tuple[int, int], strict: bool, attribute: list[str], max_len: int | None, most: int):
    """Frequent itemsets of each part: the segments of one part add up. More than `most` of them, or of candidates, is an error."""
    from fractions import Fraction

    import pyarrow as pa

    def mined(part: list[dict]) -> pa.RecordBatch:
        n = sum(row["n"] for row in part)
        least = max(1, min_count(Fraction(*share), n, strict))
        roots: dict[int, int] = {}
        for row in part:
            for i, c in zip(row["items"], row["counts"], strict=True):
                roots[i] = roots.get(i, 0) + c
        level = frequent_items(roots, least)
        found, k = list(level), 2
        while level and (max_len is None or k <= max_len):
            candidates = sorted(_checked(closed(joined(level, attribute), set(level)), most))
            got = sum(_count_in_segment(row, candidates, "prefix")[0] for row in part)
            level = {c: n for c, n in zip(candidates, got.tolist(), strict=True) if n >= least}
            found = _checked(found + list(level), most)
            k += 1
        return pa.record_batch([pa.array(map(list, found), pa.list_(pa.int32()))], ["items"])

    def run(batches):
        part: list[dict] = []
        for row in rows_one_by_one(batches):
            if part and part[-1]["part"] != row["part"]:
                yield mined(part)
                part = []
            part.append(row)
        if part:
            yield mined(part)

    return run


def mine_segmented(info: InfoTable, minsup: Number, minconf: Number, strict: bool = False, max_len: int | None = None, max_candidates: int = MOST_CANDIDATES, segment: int = SEGMENT) -> MiningResult:
    """Two passes over the segments instead of one per level: what is frequent overall is frequent in some part, so the union of
    local answers holds all answers, and one exact count settles them.

    A full segment is a part and stays where it is. The last segments of the input's partitions are short, and with few tuples
    every itemset of a tuple is frequent; so they are dealt together to parts of about a segment's tuples.
    """
    from ..functions.thresholds import fraction

    trees = Trees(info, counting="segments", segment=segment)
    stats = MiningStats("segmented", trees.n, len(trees.items.items), trees.scans)
    share = fraction(minsup)
    run = _local_miner((share.numerator, share.denominator), strict, trees.items.attribute, max_len, max_candidates)
    whole = trees.store.where(F.col("n") == segment).withColumn("part", F.col("segment_id"))
    short = trees.store.where(F.col("n") < segment)
    parts = max(1, (short.agg(F.sum("n")).first()[0] or 0) // segment)
    short = short.withColumn("part", F.pmod(F.xxhash64("segment_id"), F.lit(parts))).repartition("part").sortWithinPartitions("part")
    local = whole.mapInArrow(run, "items array<int>").unionByName(short.mapInArrow(run, "items array<int>"))
    start = time.perf_counter()
    candidates = _checked([tuple(r.items) for r in local.distinct().limit(max_candidates + 1).collect()], max_candidates)
    got, ands, spared = trees.count(sorted(candidates))
    least = max(1, min_count(minsup, trees.n, strict))
    counts = {c: n for c, n in zip(sorted(candidates), got, strict=True) if n >= least}
    stats.levels.append(Level(0, len(candidates), 0, len(counts), time.perf_counter() - start, ands, spared))
    return derive(trees.spark, counts, trees.items, trees.n, minconf, "single", None, strict, "none", stats)
