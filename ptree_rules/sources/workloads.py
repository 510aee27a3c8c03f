"""The experiment workloads on the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.discretize import band
from .tables import load, worked_example

#: More different labels than this are no table of columns.
MOST_LABELS = 2_000
QUANTITY = ((16, 33), ("lo", "mid", "hi"))


@dataclass(frozen=True)
class InfoTable:
    """A relation of string attributes with roles. An attribute that both is a condition and a decision is a decision when it
    is asked for, and a condition of the others."""

    df: DataFrame
    conditions: tuple[str, ...]
    decisions: tuple[str, ...]

    @property
    def attributes(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys([*self.conditions, *self.decisions]))


def info_table(df: DataFrame, conditions: list[str], decisions: list[str]) -> InfoTable:
    missing = {*conditions, *decisions} - set(df.columns)
    if missing:
        raise ValueError(f"no such attributes: {sorted(missing)}")
    keep = dict.fromkeys([*conditions, *decisions])
    return InfoTable(df.select(*(F.col(c).cast("string").alias(c) for c in keep)), tuple(conditions), tuple(decisions))


def _yes_no(c: Column) -> Column:
    return F.when(c, "yes").when(~c, "no")


#: W1's key. It names a line but for repeats in the given tables, so orders by it go on with the attributes.
W1_KEY = ("l_orderkey", "l_linenumber")


def w1_keyed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W1's attributes with its key before them."""
    lines = load(spark, sf_dir, "lineitem").select(*W1_KEY, "l_returnflag", "l_linestatus", "l_quantity", "l_discount")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderdate")
    df = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        *W1_KEY,
        F.col("l_returnflag").alias("rf"),
        F.col("l_linestatus").alias("ls"),
        F.col("o_orderstatus").alias("os"),
        F.year("o_orderdate").cast("string").alias("oy"),
        band("l_quantity", *QUANTITY, closed="right").alias("qty"),
        band("l_discount", (0.035, 0.065), ("lo", "mid", "hi")).alias("disc"),
    )
    kind = F.when((F.col("rf") == "R") | (F.col("os") == "P"), "c1").when((F.col("qty") == "hi") & (F.col("ls") == "O"), "c4").when(F.col("qty") == "mid", "c3").otherwise("c2")
    return df.withColumn("class", kind)


def w1(spark: SparkSession, sf_dir: str) -> InfoTable:
    """Seven nominal attributes of order lines, 25 items; the decision is a four-valued class."""
    return info_table(w1_keyed(spark, sf_dir), ["rf", "ls", "os", "oy", "qty", "disc"], ["class"])


def w2(spark: SparkSession, sf_dir: str) -> InfoTable:
    """Labelled documents: language, length band, labels and text flags, 20 items with much co-occurrence."""
    labels = load(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    df = load(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars", "text").join(labels, "doc_id").select(
        "lang",
        band("n_chars", (500, 2000), ("s", "m", "l")).alias("len_band"),
        F.col("quality").cast("string").alias("quality"),
        F.col("toxic").cast("string").alias("toxic"),
        _yes_no(F.col("text").rlike("[0-9]")).alias("has_digit"),
        _yes_no(F.col("text").contains("@")).alias("has_at"),
        _yes_no(F.col("text").contains("http")).alias("has_http"),
        _yes_no(F.col("text").contains("\n")).alias("has_newline"),
        _yes_no(F.lower("text").contains("license")).alias("has_license"),
    )
    return info_table(df, [c for c in df.columns if c != "has_digit"], ["has_digit"])


def w3(spark: SparkSession, sf_dir: str) -> InfoTable:
    """Twelve attributes of the order star, 37 items, five of them bands of numbers; the decision is two-valued."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus")
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal")
    # 25 nations and 5 regions: fixed sizes.
    nations = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    df = (
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(customers, F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    )
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    df = df.select(
        "r_name", "c_mktsegment", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus",
        band("l_quantity", *QUANTITY, closed="right").alias("qty"),
        band("l_extendedprice", (35_000, 70_000), ("lo", "mid", "hi")).alias("price"),
        band("l_discount", (0.05,), ("lo", "hi")).alias("disc2"),
        band("l_tax", (0.04,), ("lo", "hi")).alias("tax"),
        band("c_acctbal", (0,), ("neg", "pos")).alias("bal"),
        F.when(net >= 50_000, "gt50").when(net < 50_000, "le50").alias("net_class"),
    )
    return info_table(df, [c for c in df.columns if c != "net_class"], ["net_class"])


def w4(spark: SparkSession) -> InfoTable:
    """The worked example: one item for each attribute, present or not."""
    return info_table(worked_example(spark), list("ABCDEF"), ["G"])


def basket_table(baskets: DataFrame, labels: str = "labels") -> InfoTable:
    """Sets of labels as a relation of binary attributes, a column per label that holds 'yes' or null; the labels' number is
    checked, and only they come to the driver."""
    found = [r[0] for r in baskets.select(F.explode(labels).alias("x")).distinct().orderBy("x").limit(MOST_LABELS + 1).collect()]
    if len(found) > MOST_LABELS:
        raise ValueError(f"more than {MOST_LABELS} labels; drop rare ones first")
    df = baskets.select(*(F.when(F.array_contains(labels, x), "yes").alias(x) for x in found))
    return InfoTable(df, tuple(found), ())


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as sets of part types and brands: order key and the sorted distinct labels."""
    part = load(spark, sf_dir, "part").select("p_partkey", "p_type", "p_brand")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    labels = F.explode(F.array(F.concat(F.lit("type="), "p_type"), F.concat(F.lit("brand="), "p_brand")))
    each = lines.join(part, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", labels.alias("label"))
    return each.groupBy("l_orderkey").agg(F.array_sort(F.collect_set("label")).alias("labels"))


#: Thresholds (support, confidence) of the experiments.
THRESHOLDS = {"w1": ("0.10", "0.75"), "w2": ("0.35", "0.90"), "w3": ("0.17", "0.94"), "w4": ("0.10", "0.30"), "w9": ("0.05", "0.30")}
WORKLOADS = {"w1": w1, "w2": w2, "w3": w3}
