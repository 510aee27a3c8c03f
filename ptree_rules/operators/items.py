"""From a relation to items, bitmaps and back."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import chain

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import written
from ..sources.workloads import InfoTable

#: A dictionary is data about domains, not about tuples; one with more items than this is refused rather than collected.
MOST_ITEMS = 100_000


@dataclass(frozen=True)
class ItemDict:
    """Items numbered from 0 by attribute and value. Attributes with one value that stands for presence are binary."""

    items: tuple[tuple[str, str], ...]
    decisions: tuple[str, ...] = ()

    def label(self, item: int) -> str:
        """attribute=value; signs of the notation inside names and values get a backslash, so a text stands for one itemset."""
        a, v = (x.replace("\\", "\\\\").replace("|", "\\|") for x in self.items[item])
        return "=".join((a.replace("=", "\\="), v))

    def labels(self, items) -> str:
        return "|".join(sorted(map(self.label, items)))

    @property
    def attribute(self) -> list[str]:
        return [a for a, _ in self.items]

    def code(self, attribute: str) -> Column:
        """The item of a row's value of an attribute; null for null and for values not in the dictionary."""
        pairs = [(v, i) for i, (a, v) in enumerate(self.items) if a == attribute]
        if not pairs:
            return F.lit(None).cast("int")
        lookup = F.create_map(*chain.from_iterable((F.lit(v), F.lit(i)) for v, i in pairs))
        return F.element_at(lookup, F.col(attribute))

    def frame(self, spark) -> DataFrame:
        size = {a: self.attribute.count(a) for a in self.attribute}
        rows = [(i, a, v, "BAD" if size[a] == 1 else "NBAD", a in self.decisions) for i, (a, v) in enumerate(self.items)]
        return spark.createDataFrame(rows, "item_id int, attribute string, value string, domain string, is_decision boolean")


def stacked(info: InfoTable) -> DataFrame:
    """attribute and value of every cell that isn't null."""
    cells = F.explode(F.array(*(F.struct(F.lit(a).alias("attribute"), F.col(a).alias("value")) for a in info.attributes)))
    return info.df.select(cells.alias("cell")).select("cell.*").where(F.col("value").isNotNull())


def item_counts(info: InfoTable) -> DataFrame:
    """attribute, value and count: one aggregation in which every task sends at most one row per item."""
    return stacked(info).groupBy("attribute", "value").agg(F.count("*").alias("cnt"))


def _checked(found: DataFrame) -> DataFrame:
    few = written(found.limit(MOST_ITEMS + 1), "items")
    if few.count() > MOST_ITEMS:
        raise ValueError(f"more than {MOST_ITEMS} items; band or drop attributes of large domains first")
    return few


def item_frame(info: InfoTable) -> DataFrame:
    """The dictionary as a table: item_id, attribute, value, domain, is_decision. Numbering sorts the items, whose number is
    checked, in one task."""
    found = _checked(item_counts(info).select("attribute", "value"))
    size = F.count("*").over(Window.partitionBy("attribute"))
    return found.select(
        (F.row_number().over(Window.orderBy("attribute", "value")) - 1).alias("item_id"),
        "attribute", "value", F.when(size == 1, "BAD").otherwise("NBAD").alias("domain"),
        F.col("attribute").isin(list(info.decisions)).alias("is_decision"),
    )


def build_items(info: InfoTable) -> ItemDict:
    found = _checked(item_counts(info).select("attribute", "value")).collect()
    return ItemDict(tuple(sorted((r.attribute, r.value) for r in found)), info.decisions)


def encode_binary(c: Column, both_values: bool = False) -> list[Column]:
    """A two-valued condition as one bit, or as one per value; null sets none."""
    yes = F.when(c, 1).otherwise(0)
    return [yes, F.when(~c, 1).otherwise(0)] if both_values else [yes]


def encode_nominal(c: Column, values: list[str], null_item: bool = False) -> list[Column]:
    """A bit for each value; null sets none, or its own with null_item."""
    bits = [F.when(c == v, 1).otherwise(0) for v in values]
    return [*bits, c.isNull().cast("int")] if null_item else bits


def bitmap_wide(df: DataFrame, items: ItemDict, keep: list[str]) -> DataFrame:
    """keep and a 0/1 column named by label for each item."""
    return df.select(*keep, *(F.when(F.col(a) == v, 1).otherwise(0).alias(f"{a}={v}") for a, v in items.items))


def item_array(items: ItemDict) -> Column:
    """The sorted items of a row."""
    return F.array_sort(F.filter(F.array(*(items.code(a) for a in dict.fromkeys(items.attribute))), lambda x: x.isNotNull()))


def bitmap_long(df: DataFrame, items: ItemDict) -> DataFrame:
    """tid and item_id of the ones. tid must be a column already: an id made in this select would differ by item."""
    return df.select("tid", F.explode(item_array(items)).alias("item_id"))


def decode(long: DataFrame, items: ItemDict) -> DataFrame:
    """The relation of a long bitmap: a string column per attribute, null where no bit is set."""
    names = list(dict.fromkeys(items.attribute))
    value = {i: v for i, (_, v) in enumerate(items.items)}
    of = {a: [i for i, x in enumerate(items.attribute) if x == a] for a in names}
    text = F.element_at(F.create_map(*chain.from_iterable((F.lit(i), F.lit(v)) for i, v in value.items())), F.col("item_id"))
    return long.groupBy("tid").agg(*(F.max(F.when(F.col("item_id").isin(of[a]), text)).alias(a) for a in names))


def transactions(df: DataFrame, items: ItemDict) -> DataFrame:
    """items: each row's sorted item array."""
    return df.select(item_array(items).alias("items"))


def compact(df: DataFrame, attributes: tuple[str, ...]) -> DataFrame:
    """Distinct rows with their number as weight. Worth it where attributes are few: rows become domain combinations."""
    return df.groupBy(*attributes).agg(F.count("*").alias("weight"))
