"""The comparison of methods: times and equality of rules over data sets and decision modes."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..functions.measures import Timing, rule_diff, timed
from ..sources.tables import written
from ..sources.workloads import THRESHOLDS, WORKLOADS, InfoTable
from .baselines import mine_apriori, mine_hybrid, mine_rough_set
from .miner import mine_ptree


def cells(datasets=("w1", "w2", "w3"), methods=("ptree", "apriori", "hybrid", "rough_set")) -> list[tuple[str, str, str]]:
    """(dataset, mode, method): seven for each data set, as classic Apriori has no fixed decision."""
    return [(d, mode, m) for d in datasets for mode in ("fixed", "free") for m in methods if (m, mode) != ("apriori", "fixed")]


def prepared(spark: SparkSession, sf_dir: str, dataset: str) -> InfoTable:
    """A data set as one written relation, which all methods read: joins and bands that make it are no method's time."""
    info = WORKLOADS[dataset](spark, sf_dir)
    return InfoTable(written(info.df, dataset), info.conditions, info.decisions)


def run_cell(info: InfoTable, dataset: str, mode: str, method: str, **how):
    """The strong rules of one cell, collected, with the result. The enumerating generator counts rows that agree in all
    attributes once (compacted), which the others are not given: without that it would take many times as long."""
    s, c = THRESHOLDS[dataset]
    decision = info.decisions[0] if mode == "fixed" else None
    mine = {"ptree": mine_ptree, "apriori": mine_apriori, "hybrid": mine_hybrid, "rough_set": mine_rough_set}[method]
    if method != "apriori":
        how["decision"] = decision
    out = mine(info, s, c, **how)
    return out, out.rules.collect()


def time_cell(info: InfoTable, *cell: str, **how) -> tuple[int, Timing]:
    (_, rules), timing = timed(info.df.sparkSession, lambda: run_cell(info, *cell, **how))
    return len(rules), timing


def differences(spark: SparkSession, sf_dir: str, dataset: str, mode: str, methods=("ptree", "apriori", "hybrid", "rough_set")) -> dict[str, int]:
    """For each baseline, the number of rules that it and the tree miner don't share."""
    info = prepared(spark, sf_dir, dataset)
    base = run_cell(info, dataset, mode, "ptree")[0].rules
    return {m: rule_diff(base, run_cell(info, dataset, mode, m)[0].rules).count() for m in methods[1:] if (m, mode) != ("apriori", "fixed")}


def minsup_sweep(info: InfoTable, supports, minconf: str, **how) -> list[tuple[str, int, int, int, Timing]]:
    """(support, itemsets, rules, candidates, timing) of the tree miner for each support; the trees are built once for all."""
    from .miner import Trees

    trees, out = Trees(info), []
    for s in supports:
        (result, rules), timing = timed(info.df.sparkSession, lambda s=s: _collected(mine_ptree(info, s, minconf, trees=trees, **how)))
        out.append((s, result.itemsets.count(), len(rules), sum(x.candidates for x in result.stats.levels), timing))
    return out


def _collected(result):
    return result, result.rules.collect()
