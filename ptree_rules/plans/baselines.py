"""What the tree miner is compared with. All return the same rules for the same thresholds."""

from __future__ import annotations

import time
from collections.abc import Iterable, Sequence
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.measures import Level, MiningStats
from ..functions.thresholds import Number, min_count
from ..operators.candidates import closed, joined
from ..operators.items import ItemDict, build_items, compact, item_array
from ..sources.tables import written
from ..sources.workloads import InfoTable
from .miner import MOST_CANDIDATES, _checked
from .results import Itemset, MiningResult, derive

#: Candidates of one broadcast; more go in several passes over the same transactions.
CHUNK = 50_000
#: Combinations of attributes that an enumerating method may make of a row.
MOST_SUBSETS = 100_000


def _mask(items: Column, words: int) -> list[Column]:
    """A transaction's items as bits of so many longs."""
    def word(w: int) -> Column:
        own = F.filter(items, lambda i: F.floor(i / 63) == w)
        return F.aggregate(own, F.lit(0).cast("long"), lambda acc, i: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), (i % 63).cast("int"))))

    return [word(w) for w in range(words)]


def _masked_candidates(spark, candidates: Sequence[Itemset], words: int) -> DataFrame:
    rows = []
    for at, c in enumerate(candidates):
        bits = [0] * words
        for i in c:
            bits[i // 63] |= 1 << (i % 63)
        rows.append((at, *bits))
    return spark.createDataFrame(rows, "cand_id int, " + ", ".join(f"c{w} long" for w in range(words)))


class Transactions:
    """Item masks of all tuples; a count scans them all and tests every candidate against every transaction."""

    def __init__(self, info: InfoTable, items: ItemDict | None = None):
        self.info, self.items = info, items or build_items(info)
        self.spark = info.df.sparkSession
        self.words = -(-len(self.items.items) // 63) or 1
        self.n = info.df.count()
        self.scans = 1 if items else 2

    def scan(self) -> DataFrame:
        return self.info.df.select(*(m.alias(f"t{w}") for w, m in enumerate(_mask(item_array(self.items), self.words))))

    def count_level(self, candidates: Sequence[Itemset]) -> list[int]:
        out: list[int] = []
        for lo in range(0, len(candidates), CHUNK):
            part = candidates[lo : lo + CHUNK]
            test = F.lit(True)
            for w in range(self.words):
                test &= F.col(f"t{w}").bitwiseAND(F.col(f"c{w}")) == F.col(f"c{w}")
            small = F.broadcast(_masked_candidates(self.spark, part, self.words))  # at most CHUNK rows
            met = self.scan().join(small, test).groupBy("cand_id").agg(F.count("*").alias("cnt"))
            got = {r.cand_id: r.cnt for r in met.collect()}
            out += [got.get(i, 0) for i in range(len(part))]
            self.scans += 1
        return out


def _levels(tx: Transactions, least: int, stats: MiningStats, max_len: int | None, most: int, wanted=None) -> dict[Itemset, int]:
    """Apriori's loop. wanted(candidate) drops candidates before they are counted; what it drops needs no growth either."""
    attribute = tx.items.attribute
    candidates: list[Itemset] = [(i,) for i in range(len(attribute))]
    counts: dict[Itemset, int] = {}
    k, made = 1, len(candidates)
    while candidates and (max_len is None or k <= max_len):
        start = time.perf_counter()
        got = tx.count_level(_checked(candidates, most))
        level = {c: n for c, n in zip(candidates, got, strict=True) if n >= least}
        counts |= level
        stats.levels.append(Level(k, len(candidates), made - len(candidates), len(level), time.perf_counter() - start))
        new = joined(level, attribute)
        made, candidates, k = len(new), closed(new, set(level)), k + 1
        if wanted:
            candidates = [c for c in candidates if wanted(c)]
    stats.scans = tx.scans
    return counts


def mine_apriori(info: InfoTable, minsup: Number, minconf: Number, consequent: str = "single", strict: bool = False, criterion: str = "none", max_len: int | None = None, max_candidates: int = MOST_CANDIDATES) -> MiningResult:
    """Classic Apriori, free decision: every level scans the transactions."""
    tx = Transactions(info)
    stats = MiningStats("apriori", tx.n, len(tx.items.items))
    counts = _levels(tx, max(1, min_count(minsup, tx.n, strict)), stats, max_len, max_candidates)
    return derive(tx.spark, counts, tx.items, tx.n, minconf, consequent, None, strict, criterion, stats)


def mine_hybrid(info: InfoTable, minsup: Number, minconf: Number, decision: str | Iterable[str] | None = None, conditions: Sequence[str] | None = None, strict: bool = False, criterion: str = "none", max_len: int | None = None, max_candidates: int = MOST_CANDIDATES) -> MiningResult:
    """The fixed-decision hybrid: Apriori over transactions, sets without the decision left out of rule generation, rules
    derived and then cut down by the redundancy criterion. Antecedents are counted, as confidences need them. Without a
    decision it derives for every attribute, from the same itemsets."""
    tx = Transactions(info)
    stats = MiningStats("hybrid", tx.n, len(tx.items.items))
    goals = list(info.attributes) if decision is None else [decision] if isinstance(decision, str) else list(decision)
    attribute, usable = tx.items.attribute, {*goals, *(conditions or info.attributes)}
    wanted = lambda c: all(attribute[i] in usable for i in c)
    counts = _levels(tx, max(1, min_count(minsup, tx.n, strict)), stats, max_len, max_candidates, wanted)
    cond = set(conditions or info.attributes)
    shown = counts if decision is None else {c: n for c, n in counts.items() if any(attribute[i] in goals and all(attribute[j] in cond for j in c if j != i) for i in c)}
    out = derive(tx.spark, counts, tx.items, tx.n, minconf, "single", goals, strict, "none", stats, shown=shown)
    return _within(out, conditions, criterion)


def _within(out: MiningResult, conditions: Sequence[str] | None, criterion: str) -> MiningResult:
    from ..operators.rules import reduce_rules

    rules = out.rules
    if conditions is not None:
        usable = [i for i, a in enumerate(out.items.attribute) if a in conditions]
        rules = rules.where(F.forall("x", lambda x: x.isin(usable)))
    return MiningResult(out.itemsets, reduce_rules(rules, criterion), out.stats, out.items)


def combination_counts(rows: DataFrame, items: ItemDict, sizes: Iterable[int], attributes: Sequence[str]) -> DataFrame:
    """items and cnt of every combination of items of the given attributes in rows of coded(), weights added up: each row gives one row
    per subset of its attributes, and map-side sums go before the shuffle. More than MOST_SUBSETS subsets a row are an error."""
    subsets = [list(s) for k in sizes for s in combinations(range(len(attributes)), k)]
    if not subsets:
        return rows.sparkSession.createDataFrame([], "items array<int>, cnt long")
    if len(subsets) > MOST_SUBSETS:
        raise ValueError(f"{len(subsets)} combinations of attributes a row; set max_len, or use a method that doesn't enumerate")
    codes = rows.select(*(F.col(f"item_{a}").alias(f"c{i}") for i, a in enumerate(attributes)), "weight")
    # A list of positions for each subset, spread over rows by an explode of a literal.
    chosen = F.explode(F.array(*(F.array(*map(F.lit, s)) for s in subsets)))
    made = codes.select(F.array(*(f"c{i}" for i in range(len(attributes)))).alias("c"), "weight", chosen.alias("s")).select("weight", F.array_sort(F.transform("s", lambda i: F.get("c", i))).alias("items"))
    return made.where(~F.exists("items", lambda x: x.isNull())).groupBy("items").agg(F.sum("weight").alias("cnt"))


def coded(info: InfoTable, items: ItemDict, compacted: bool) -> DataFrame:
    """The relation as item numbers (item_<attribute>) and weight, written: looked up once, however many combinations follow."""
    rows = compact(info.df, info.attributes) if compacted else info.df.withColumn("weight", F.lit(1).cast("long"))
    return written(rows.select(*(items.code(a).alias(f"item_{a}") for a in info.attributes), "weight"), "coded")


def _enumerated(rows: DataFrame, items: ItemDict, attributes: Sequence[str], top: int, least: int) -> dict[Itemset, int]:
    """Counts of all frequent combinations of items. Sizes are enumerated one after the other; after one without a frequent
    combination no larger size has any, so it ends there."""
    out: dict[Itemset, int] = {}
    for k in range(1, top + 1):
        counted = combination_counts(rows, items, [k], attributes).where(F.col("cnt") >= least)
        got = {tuple(r["items"]): r.cnt for r in counted.collect()}
        if not got:
            break
        out |= got
    return out


def mine_brute_force(info: InfoTable, minsup: Number, minconf: Number, consequent: str = "single", strict: bool = False, max_len: int | None = None) -> MiningResult:
    """All combinations counted, then both thresholds: the measure for the others on few attributes."""
    items = build_items(info)
    n = info.df.count()
    stats = MiningStats("brute force", n, len(items.items), 3)
    top = min(len(info.attributes), max_len or len(info.attributes))
    counted = combination_counts(coded(info, items, True), items, range(1, top + 1), info.attributes)
    least = max(1, min_count(minsup, n, strict))
    counts = {tuple(r["items"]): r.cnt for r in counted.where(F.col("cnt") >= least).collect()}
    return derive(info.df.sparkSession, counts, items, n, minconf, consequent, None, strict, "none", stats)


def mine_rough_set(info: InfoTable, minsup: Number, minconf: Number, decision: str | Iterable[str] | None = None, conditions: Sequence[str] | None = None, strict: bool = False, criterion: str = "none", max_len: int | None = None, compacted: bool = True) -> MiningResult:
    """The rough-set generator: all rules of the information table, one decision attribute after the other, then both
    thresholds. Free: every attribute is the decision once, which is why this is the slowest. max_len bounds itemsets;
    compacted counts rows that agree in all attributes once, with a weight, which no other method is given."""
    items = build_items(info)
    rows = coded(info, items, compacted)
    n = rows.agg(F.sum("weight")).first()[0] or 0
    stats = MiningStats("rough set", n, len(items.items), 2)
    goals = list(info.attributes) if decision is None else [decision] if isinstance(decision, str) else list(decision)
    least = max(1, min_count(minsup, n, strict))
    xs: dict[Itemset, int] = {}
    xys: dict[Itemset, int] = {}
    for goal in goals:
        start = time.perf_counter()
        others = [a for a in (conditions or info.attributes) if a != goal]
        top = min(len(others) + 1, max_len or len(others) + 1)
        # X alone, and X with the decision: the count of a rule needs both.
        code = set(i for i, a in enumerate(items.attribute) if a == goal)
        got = _enumerated(rows, items, [*others, goal], top, least)
        with_goal = {c: m for c, m in got.items() if code & set(c)}
        xys |= with_goal
        xs |= {c: m for c, m in got.items() if not code & set(c)}
        stats.levels.append(Level(0, len(got), 0, len(with_goal), time.perf_counter() - start))
    out = derive(info.df.sparkSession, xs | xys, items, n, minconf, "single", goals, strict, "none", stats, shown=xs | xys if decision is None else xys)
    return _within(out, conditions, criterion)


def mine_fpgrowth(info: InfoTable, minsup: Number) -> DataFrame:
    """items (labels, sorted and joined) and cnt by Spark's own FP-growth, as a check. Its support threshold is rounded up to a
    count inside, so it is given the exact least count over n."""
    from pyspark.ml.fpm import FPGrowth

    items = build_items(info)
    named = F.array(*(F.when(F.col(a).isNotNull(), F.concat(F.lit(f"{a}="), F.col(a))) for a in dict.fromkeys(items.attribute)))
    tx = info.df.select(F.filter(named, lambda x: x.isNotNull()).alias("items")).persist()
    n = tx.count()
    model = FPGrowth(itemsCol="items", minSupport=(min_count(minsup, n) - 0.5) / n if n else 1.0, minConfidence=1.0).fit(tx)
    out = model.freqItemsets.select(F.array_join(F.array_sort("items"), "|").alias("label"), F.size("items").alias("k"), F.col("freq").alias("cnt"))
    return out
