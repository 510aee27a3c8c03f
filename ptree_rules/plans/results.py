"""What every miner returns."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..functions.measures import MiningStats
from ..functions.thresholds import Number, is_confident
from ..operators import rules as R
from ..operators.items import ItemDict

Itemset = tuple[int, ...]
ITEMSETS = "k int, items array<int>, label string, cnt long"


@dataclass(frozen=True)
class MiningResult:
    """itemsets (k, items, label, cnt), strong rules (rules.COLUMNS; x and y are their sides as items), what the run did, and
    the dictionary."""

    itemsets: DataFrame
    rules: DataFrame
    stats: MiningStats
    items: ItemDict


def itemset_frame(spark: SparkSession, counts: Mapping[Itemset, int], items: ItemDict) -> DataFrame:
    rows = [(len(s), list(s), items.labels(s), c) for s, c in sorted(counts.items())]
    return spark.createDataFrame(rows, ITEMSETS)


def derive(spark: SparkSession, counts: Mapping[Itemset, int], items: ItemDict, n: int, minconf: Number, consequent: str, decisions: Iterable[str] | None, strict: bool, criterion: str, stats: MiningStats, shown: Mapping[Itemset, int] | None = None) -> MiningResult:
    """Strong rules of counted itemsets. counts hold all antecedents; shown are the itemsets to return, if others."""
    frame = itemset_frame(spark, counts, items)
    dictionary = items.frame(spark)
    if decisions is not None:
        rules = R.rules_decision(frame, n, dictionary, list(decisions))
    else:
        rules = R.rules_any(frame, n) if consequent == "any" else R.rules_single(frame, n, dictionary)
    rules = R.reduce_rules(R.strong(rules, minconf, strict), criterion)
    return MiningResult(frame if shown is None else itemset_frame(spark, shown, items), rules, stats, items)


def strong_result(spark: SparkSession, counts: Mapping[Itemset, int], shown: Mapping[Itemset, int], decisions: list[str] | None, items: ItemDict, n: int, minconf: Number, strict: bool, stats: MiningStats) -> MiningResult:
    """Strong rules level by level: an itemset's count and those of its antecedents are known once its level is, so each rule is
    kept or left there and then, and no join derives it. The rules by size go to stats.strong."""
    rows, attribute = [], items.attribute
    for k in sorted({len(s) for s in shown if len(s) > 1}):
        level = []
        for s in sorted(s for s in shown if len(s) == k):
            for y in s:
                x = tuple(i for i in s if i != y)
                if (decisions is None or attribute[y] in decisions) and x in counts and is_confident(counts[s], counts[x], minconf, strict):
                    level.append((items.labels(x), items.label(y), k - 1, counts[s], counts[x], n, counts[s] / n, counts[s] / counts[x], attribute[y], list(x), [y]))
        stats.strong[k] = len(level)
        rows += level
    rules = spark.createDataFrame(rows, "antecedent string, consequent string, k int, cnt_xy long, cnt_x long, n long, support double, confidence double, decision string, x array<int>, y array<int>")
    return MiningResult(itemset_frame(spark, shown, items), rules, stats, items)
