"""Times the comparison of methods, the growth of the tree miner, and a few other queries at $BENCH_SF_DIR on local[$BENCH_CPUS];
prints one JSON line.

The value is the tree miner's total over all data sets and modes. Every method reads the same written relation; seconds are by
the clock, cpu_seconds those of all processes. BENCH_FULL=1 adds the enumerating generator on the largest data set, whose rows
hardly ever agree: it takes longer than all the rest.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
OTHERS = ("root_counts", "pure_pruned_tree", "and_three_items", "segmented_itemsets_w1", "cube_counts", "join_asof", "windowed_rules")
SUPPORTS = ("0.05", "0.10", "0.15", "0.20", "0.25", "0.30", "0.35")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from ptree_rules.catalogue import QUERIES
    from ptree_rules.plans import grid

    sizes = os.path.dirname(SF_DIR.rstrip("/"))
    warm = {d: grid.prepared(spark, os.path.join(sizes, "sf0.001"), d) for d in ("w1", "w2", "w3")}
    for cell in grid.cells():  # compiles code and starts workers
        if cell[2] != "rough_set":
            grid.run_cell(warm[cell[0]], *cell)
    seconds, cpu, rules = {}, {}, {}
    for d in ("w1", "w2", "w3"):
        info = grid.prepared(spark, SF_DIR, d)
        for cell in grid.cells((d,)):
            if cell[0] == "w3" and cell[2] == "rough_set" and not os.environ.get("BENCH_FULL"):
                continue
            name = "_".join(cell)
            rules[name], timing = grid.time_cell(info, *cell)
            seconds[name], cpu[name] = round(timing.wall * 60, 3), round(timing.cpu * 60, 3)
            print(name, seconds[name], cpu[name], file=sys.stderr, flush=True)
        if d == "w1":
            sweep = [dict(support=s, itemsets=f, rules=r, candidates=c, seconds=round(t.wall * 60, 3)) for s, f, r, c, t in grid.minsup_sweep(info, SUPPORTS, "0.75")]
    for d in ("w1", "w2", "w3"):
        for mode in ("fixed", "free"):
            of = {n: r for n, r in rules.items() if n.startswith(f"{d}_{mode}")}
            assert len(set(of.values())) == 1, of  # all methods find the same number of rules
    growth = []
    for size in ("sf0.001", "sf0.01", "sf0.1"):
        path = os.path.join(sizes, size)
        if os.path.isdir(path):
            info = grid.prepared(spark, path, "w1")
            n, (_, timing) = info.df.count(), grid.time_cell(info, "w1", "free", "ptree")
            growth.append(dict(sf=size[2:], tuples=n, seconds=round(timing.wall * 60, 3), cpu_seconds=round(timing.cpu * 60, 3)))
    for name in OTHERS:
        start = time.perf_counter()
        QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - start, 3)
    of_tree = lambda n: "_".join([*n.split("_")[:2], "ptree"])
    compared = [n for n in seconds if n[:2] in ("w1", "w2", "w3") and not n.endswith("ptree")]
    out = {
        "metric": "tree miner, all data sets and decision modes",
        "value": round(sum(s for n, s in seconds.items() if n.endswith("_ptree")), 3),
        "unit": "sec",
        "queries": seconds,
        "cpu_seconds": cpu,
        "times_the_tree_miner": {n: round(seconds[n] / seconds[of_tree(n)], 2) for n in compared},
        "cpu_times_the_tree_miner": {n: round(cpu[n] / cpu[of_tree(n)], 2) for n in compared if n in cpu},
        "rules": rules,
        "minsup_sweep_w1": sweep,
        "growth_w1_free": growth,
        "sf": SF_DIR.rpartition("sf")[2],
    }
    print(json.dumps(out), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
