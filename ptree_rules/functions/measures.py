"""Measures of rules, rule sets and runs."""

from __future__ import annotations

import os
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def support(rules: DataFrame) -> DataFrame:
    return rules.withColumn("support", F.col("cnt_xy") / F.col("n"))


def confidence(rules: DataFrame) -> DataFrame:
    return rules.withColumn("confidence", F.col("cnt_xy") / F.col("cnt_x"))


def interest(rules: DataFrame, item_counts: DataFrame) -> DataFrame:
    """rules with lift, leverage, conviction (null where the rule never fails) and Jaccard; item_counts(consequent, cnt_y)."""
    x, y, xy, n = (F.col(c).cast("double") for c in ("cnt_x", "cnt_y", "cnt_xy", "n"))
    return rules.join(item_counts, "consequent").withColumns(
        {
            "lift": xy * n / (x * y),
            "leverage": xy / n - (x / n) * (y / n),
            "conviction": F.when(x != xy, (x * (n - y)) / (n * (x - xy))),
            "jaccard": xy / (x + y - xy),
        }
    )


def rule_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """The rules that only one of the methods has, with its side; equal sets have none. Rules compare by text and counts."""
    key = ["antecedent", "consequent", "cnt_xy", "cnt_x", "n"]
    x, y = a.select(*key), b.select(*key)
    return x.exceptAll(y).withColumn("side", F.lit("first")).unionByName(y.exceptAll(x).withColumn("side", F.lit("second")))


def rule_profile(rules: DataFrame) -> DataFrame:
    """Number of rules by antecedent size and decision."""
    return rules.groupBy("k", "decision").agg(F.count("*").alias("rules"))


def compression_ratio(stored_bytes: Column, n: Column, items: Column) -> Column:
    """Stored bytes over the raw bits of the table, one per tuple and item."""
    return stored_bytes * 8 / (n * items)


@dataclass
class Level:
    """What one level of a run did: candidates asked for, those the prune step left out before, and of the candidates those that
    bounds ruled out; ANDs done, and those that trees spared."""

    k: int
    candidates: int
    pruned: int
    frequent: int
    seconds: float
    ands: int = 0
    spared: int = 0
    bounded: int = 0


@dataclass
class MiningStats:
    method: str
    n: int = 0
    items: int = 0
    scans: int = 0
    levels: list[Level] = field(default_factory=list)
    strong: dict[int, int] = field(default_factory=dict)

    @property
    def ands(self) -> int:
        return sum(x.ands for x in self.levels)

    def frame(self, spark) -> DataFrame:
        """A row per level: k, candidates, pruned, bounded, frequent, ands, spared, scans (of the whole run)."""
        rows = [(x.k, x.candidates, x.pruned, x.bounded, x.frequent, x.ands, x.spared, self.scans) for x in self.levels]
        return spark.createDataFrame(rows, "k int, candidates long, pruned long, bounded long, frequent long, ands long, spared long, scans int")


@dataclass(frozen=True)
class Timing:
    """Wall time of a run and CPU time of all that worked for it, in minutes."""

    wall: float
    cpu: float


def _process_seconds() -> float:
    """CPU seconds so far of this process and all below it, ended ones that were waited for included: on a local master that is
    the driver, the JVM and Python's workers."""
    tick = os.sysconf("SC_CLK_TCK")
    parent, spent = {}, {}
    for name in filter(str.isdigit, os.listdir("/proc")):
        try:
            with open(f"/proc/{name}/stat") as f:
                stat = f.read().rpartition(")")[2].split()
        except OSError:  # it has ended meanwhile
            continue
        parent[int(name)], spent[int(name)] = int(stat[1]), sum(map(int, stat[11:15])) / tick
    total = 0.0
    for pid, seconds in spent.items():
        up = pid
        while up in parent and up != os.getpid():
            up = parent[up]
        total += seconds if up == os.getpid() else 0.0
    return total


def _task_seconds(spark) -> float:
    """CPU seconds of the JVM's task threads over the stages that the status store still has; Python's workers aren't in it."""
    store = spark.sparkContext._jsc.sc().statusStore()
    stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), spark._jvm.java.util.ArrayList())
    return sum(stages.apply(i).executorCpuTime() for i in range(stages.size())) / 1e9


def timed(spark, run: Callable[[], object]) -> tuple[object, Timing]:
    """run()'s result and its timing. CPU time is that of all processes on a local master; elsewhere that of JVM tasks."""
    local = spark.sparkContext.master.startswith("local[") and os.path.isdir("/proc/self")
    seconds = _process_seconds if local else lambda: _task_seconds(spark)
    before, start = seconds(), time.perf_counter()
    out = run()
    wall = time.perf_counter() - start
    return out, Timing(wall / 60, (seconds() - before) / 60)


def speedup(timings: DataFrame, of: str = "ptree") -> DataFrame:
    """Each method's minutes over those of one method, by dataset and mode; timings(dataset, mode, method, minutes)."""
    base = timings.where(F.col("method") == of).select("dataset", "mode", F.col("minutes").alias("base"))
    return timings.join(base, ["dataset", "mode"]).select("dataset", "mode", "method", "minutes", (F.col("minutes") / F.col("base")).alias("times"))
