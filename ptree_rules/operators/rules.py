"""Rules from itemsets with counts: an itemset is (k, items, label, cnt), items ascending. Rules are derived on item numbers; texts
are put on at the end, so nothing depends on what values look like."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.thresholds import Number, confident

COLUMNS = ("antecedent", "consequent", "k", "cnt_xy", "cnt_x", "n", "support", "confidence", "decision")
#: The sides as item numbers, beside COLUMNS.
SIDES = ("x", "y")
#: More rules than this are not broadcast to rows.
MOST_RULES = 100_000


def _counted(split: DataFrame, itemsets: DataFrame, n: int) -> DataFrame:
    """split(x, y, cnt_xy) with both sides' texts and the antecedent's count: equi-joins on the item arrays."""
    left = itemsets.select(F.col("items").alias("x"), F.col("label").alias("antecedent"), F.col("cnt").alias("cnt_x"))
    right = itemsets.select(F.col("items").alias("y"), F.col("label").alias("consequent"))
    out = split.join(left, "x").join(right, "y").withColumn("n", F.lit(n).cast("long")).withColumn("k", F.size("x"))
    return out.withColumn("support", F.col("cnt_xy") / F.col("n")).withColumn("confidence", F.col("cnt_xy") / F.col("cnt_x"))


def rules_single(itemsets: DataFrame, n: int, dictionary: DataFrame) -> DataFrame:
    """All rules with one item as consequent, its attribute as decision; k is the antecedent's size. dictionary(item_id,
    attribute, ...) has a row per item."""
    each = itemsets.where("k > 1").select("items", "cnt", F.explode("items").alias("item_id"))
    split = each.select(F.array_remove("items", F.col("item_id")).alias("x"), F.array("item_id").alias("y"), F.col("cnt").alias("cnt_xy"), "item_id")
    of = dictionary.select("item_id", F.col("attribute").alias("decision"))
    return _counted(split.join(of, "item_id"), itemsets, n).select(*COLUMNS, *SIDES)


def rules_decision(itemsets: DataFrame, n: int, dictionary: DataFrame, decisions: list[str]) -> DataFrame:
    """Rules whose consequent is an item of a decision attribute; itemsets also hold the antecedents."""
    return rules_single(itemsets, n, dictionary.where(F.col("attribute").isin(decisions)))


def rules_any(itemsets: DataFrame, n: int) -> DataFrame:
    """All splits of an itemset into two sides."""
    top = F.call_function("shiftleft", F.lit(1), F.col("k")) - 2
    each = itemsets.where("k > 1").select("items", "cnt", F.explode(F.sequence(F.lit(1), top.cast("int"))).alias("mask"))
    left = F.filter("items", lambda x, i: F.col("mask").bitwiseAND(F.call_function("shiftleft", F.lit(1), i)) != 0)
    split = each.withColumn("x", left).select("x", F.array_except("items", "x").alias("y"), F.col("cnt").alias("cnt_xy"), F.lit(None).cast("string").alias("decision"))
    return _counted(split, itemsets, n).select(*COLUMNS, *SIDES)


def strong(rules: DataFrame, minconf: Number, strict: bool = False) -> DataFrame:
    return rules.where(confident(F.col("cnt_xy"), F.col("cnt_x"), minconf, strict))


def reduce_rules(rules: DataFrame, criterion: str = "none") -> DataFrame:
    """Rules without the redundant ones. 'shorter_as_good': one with a smaller antecedent, within this one's, has at least its
    confidence; 'same_cover': such a one has the same antecedent count. Rules are few against the data; the join is by
    consequent."""
    if criterion == "none":
        return rules
    short = rules.select(F.col("y").alias("of"), F.col("x").alias("few"), F.col("k").alias("k_s"), F.col("cnt_xy").alias("xy_s"), F.col("cnt_x").alias("x_s"))
    within = (F.col("y") == F.col("of")) & (F.col("k_s") < F.col("k")) & (F.size(F.array_except("few", "x")) == 0)
    as_good = F.col("xy_s").cast("decimal(19,0)") * F.col("cnt_x") >= F.col("cnt_xy").cast("decimal(19,0)") * F.col("x_s")
    better = {"shorter_as_good": as_good, "same_cover": F.col("x_s") == F.col("cnt_x")}[criterion]
    return rules.join(short, within & better, "left_anti")


def rules_table(rules: DataFrame) -> DataFrame:
    """Rules laid out by antecedent size (rows) and decision (columns), sorted texts in each cell."""
    text = F.concat("antecedent", F.lit(" -> "), "consequent")
    return rules.groupBy("k").pivot("decision").agg(F.array_join(F.array_sort(F.collect_list(text)), "; ")).orderBy("k")


def apply_rules(df: DataFrame, rules: DataFrame, row_items: Column) -> DataFrame:
    """df with the conclusion of the rule that fits best: of those whose antecedent a row's items hold, the one of the highest
    confidence, then support, then text; null where none fits.

    The rules, their number checked, are one broadcast row that every row of df looks through in place: nothing is shuffled.
    """
    if (found := rules.count()) > MOST_RULES:
        raise ValueError(f"{found} rules; raise the thresholds, or drop redundant rules, to apply at most {MOST_RULES}")
    book = rules.agg(F.reverse(F.array_sort(F.collect_list(F.struct("confidence", "support", "antecedent", "consequent", "x")))).alias("_rules"))
    fits = F.filter("_rules", lambda r: F.size(F.array_except(r["x"], F.col("_items"))) == 0)
    met = df.withColumn("_items", row_items).join(F.broadcast(book))
    return met.select(*df.columns, F.get(fits, F.lit(0))["consequent"].alias("conclusion"))
