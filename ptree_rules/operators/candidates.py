"""Candidate itemsets: as lists on the driver for the level loop, and as DataFrames."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Itemset = tuple[int, ...]


def joined(frequent: Iterable[Itemset], exclusive: Sequence | None = None) -> list[Itemset]:
    """Sorted k-sets from (k-1)-sets that share all but the last item; `exclusive[i]` is the attribute of item i, of which a
    set holds one value at most."""
    by_prefix: dict[Itemset, list[int]] = {}
    for s in sorted(frequent):
        by_prefix.setdefault(s[:-1], []).append(s[-1])
    out = [(*p, a, b) for p, last in by_prefix.items() for a, b in combinations(last, 2)]
    return [c for c in out if exclusive is None or exclusive[c[-1]] != exclusive[c[-2]]]


def closed(candidates: Iterable[Itemset], frequent: set[Itemset]) -> list[Itemset]:
    """Those whose subsets one item smaller are all frequent."""
    return [c for c in candidates if all(c[:i] + c[i + 1 :] in frequent for i in range(len(c)))]


def join_step(frequent: DataFrame, item_dict: DataFrame | None = None) -> DataFrame:
    """joined() on a DataFrame(items): an equi-join on the prefix. With a dictionary(item_id, attribute), two values of one
    attribute never meet. For pairs (an empty prefix) all frequent items meet, which their number squared bounds."""
    k = F.size("items")
    side = frequent.select(F.slice("items", F.lit(1), k - 1).alias("prefix"), F.element_at("items", -1).alias("last"))
    if item_dict is not None:
        of = F.broadcast(item_dict.select(F.col("item_id").alias("last"), "attribute"))
        side = side.join(of, "last")
    a, b = side.alias("a"), side.alias("b")
    on = (F.col("a.prefix") == F.col("b.prefix")) & (F.col("a.last") < F.col("b.last"))
    if item_dict is not None:
        on &= F.col("a.attribute") != F.col("b.attribute")
    return a.join(b, on).select(F.concat("a.prefix", F.array("a.last", "b.last")).alias("items"))


def prune_subsets(candidates: DataFrame, frequent: DataFrame) -> DataFrame:
    """closed() on DataFrames: candidates go if a subset is missing among the frequent ones."""
    each = candidates.select("items", F.explode(F.transform("items", lambda x: F.array_remove("items", x))).alias("subset"))
    missing = each.join(frequent.select(F.col("items").alias("subset")), "subset", "left_anti").select("items").distinct()
    return candidates.join(missing, "items", "left_anti")


def next_level(frequent: DataFrame, item_dict: DataFrame | None = None) -> DataFrame:
    return prune_subsets(join_step(frequent, item_dict), frequent)
