from collections import Counter
from itertools import combinations

import numpy as np
import pytest

from ptree_rules.functions.measures import rule_diff, rule_profile, speedup
from ptree_rules.operators import candidates
from ptree_rules.operators.items import item_array
from ptree_rules.operators.rules import apply_rules, reduce_rules, rules_table
from ptree_rules.plans import baselines as B
from ptree_rules.plans.miner import Trees, append_segments, mine_ptree, mine_segmented
from ptree_rules.sources import workloads as W
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def sets(out):
    return {(r.label, r.cnt) for r in out.itemsets.collect()}


def texts(rules):
    return {f"{r.antecedent.replace('=yes', '').replace('|', '')}>{r.consequent[0]}" for r in rules.collect()}


def test_worked_example(spark):
    info = W.w4(spark)
    free = mine_ptree(info, "0.10", "0.30")
    assert Counter(r.k for r in free.itemsets.collect()) == {1: 7, 2: 19, 3: 24, 4: 15, 5: 6, 6: 1}
    assert free.rules.count() == 197
    assert mine_ptree(info, "0.10", "0.30", consequent="any").rules.count() == 538
    g = mine_ptree(info, "0.10", "0.30", decision="G", conditions=list("ABCDEF")).rules
    assert {(r.antecedent.replace("=yes", ""), r.cnt_xy, r.cnt_x) for r in g.collect()} == {("B", 2, 6), ("D", 3, 5), ("E", 2, 5), ("F", 1, 3), ("B|D", 1, 3), ("D|E", 1, 3), ("D|F", 1, 3)}
    f = mine_ptree(info, "0.10", "0.30", decision="F", conditions=list("ABCDE")).rules
    assert texts(f) == {f"{''.join(s)}>F" for k in range(1, 6) for s in combinations("ABCDE", k)}
    assert texts(mine_ptree(info, "0.10", "0.30", decision="F").rules) - texts(f) == {"DG>F"}
    # The rules that the published table lists.
    listed = {f"{x}>G" for x in "B D E F BD".split()} | {f"{x}>F" for x in "A B D E AB AC AD AE BC BD CD ABC ABD ABE ACD BCD BCE BDE CDE ABCD ABCE ACDE BCDE ABCDE".split()}
    assert listed <= texts(g) | texts(f)


def test_golden_counts(spark):
    out = mine_ptree(W.w1(spark, SF), *W.THRESHOLDS["w1"])
    assert Counter(r.k for r in out.itemsets.collect()) == {1: 23, 2: 97, 3: 20} and out.rules.count() == 26
    assert out.stats.scans == 1 and len(out.stats.levels) == 3 and out.stats.items == 25
    fixed = mine_ptree(W.w1(spark, SF), *W.THRESHOLDS["w1"], decision="class")
    assert fixed.rules.count() == 21
    assert rule_diff(fixed.rules, out.rules.where("decision = 'class'")).count() == 0


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(8)
    a = rng.integers(0, 3, 400)
    rows = [(f"a{x}", f"b{(x + rng.integers(0, 2)) % 3}", None if rng.random() < 0.1 else f"c{rng.integers(0, 2)}", "d" if rng.random() < 0.3 else None, f"e{int(x == 1)}") for x in a]
    return W.info_table(spark.createDataFrame(rows, "a string, b string, c string, d string, e string").repartition(3), ["a", "b", "c", "d"], ["e"])


@pytest.mark.parametrize("strict", [False, True])
def test_all_methods_agree(small, strict):
    s, c = "0.0525", "0.5"
    brute = B.mine_brute_force(small, s, c, strict=strict)
    trees = {how: mine_ptree(small, s, c, strict=strict, **how_args) for how, how_args in {"segments": {}, "none": {"reuse": "none"}, "words": {"counting": "words"}}.items()}
    others = [*trees.values(), mine_segmented(small, s, c, strict=strict, segment=64), B.mine_apriori(small, s, c, strict=strict), B.mine_hybrid(small, s, c, strict=strict), B.mine_rough_set(small, s, c, strict=strict)]
    want = sets(brute)
    assert len(want) > 40
    for out in others:
        assert sets(out) == want
        assert rule_diff(out.rules, brute.rules).count() == 0
    fixed = brute.rules.where("decision = 'e'")
    for out in (mine_ptree(small, s, c, "e", strict=strict), B.mine_hybrid(small, s, c, "e", strict=strict), B.mine_rough_set(small, s, c, "e", strict=strict)):
        assert rule_diff(out.rules, fixed).count() == 0


def test_library_agrees(small):
    got = {(r.label, r.cnt) for r in B.mine_fpgrowth(small, "0.0525").collect()}
    assert got == sets(mine_ptree(small, "0.0525", "0.5"))


def test_frequent_sets_are_closed_downward(small):
    found = {tuple(r["items"]): r.cnt for r in mine_ptree(small, "0.05", "0.5").itemsets.collect()}
    for s, c in found.items():
        assert all(found[s[:i] + s[i + 1 :]] >= c for i in range(len(s)) if len(s) > 1)


def test_several_decisions_and_conditions(small):
    free = mine_ptree(small, "0.05", "0.4").rules
    both = mine_ptree(small, "0.05", "0.4", decision=["e", "b"]).rules
    assert rule_diff(both, free.where("decision in ('e', 'b')")).count() == 0
    few = mine_ptree(small, "0.05", "0.4", decision="e", conditions=["a", "b"]).rules
    hybrid = B.mine_hybrid(small, "0.05", "0.4", decision="e", conditions=["a", "b"]).rules
    rough = B.mine_rough_set(small, "0.05", "0.4", decision="e", conditions=["a", "b"]).rules
    assert few.count() and rule_diff(few, hybrid).count() == 0 and rule_diff(few, rough).count() == 0


def test_appended_segments(small):
    known = Trees(small).items
    first = W.InfoTable(small.df.where("a = 'a0'"), small.conditions, small.decisions)
    trees = append_segments(Trees(first, items=known), small.df.where("a != 'a0'"))
    assert sets(mine_ptree(small, "0.05", "0.5", trees=trees)) == sets(mine_ptree(small, "0.05", "0.5"))


@pytest.mark.parametrize("rows", [[], [("x", "y")], [("x", None)] * 3, [(None, None)]])
def test_edges(spark, rows):
    info = W.info_table(spark.createDataFrame(rows, "a string, b string"), ["a"], ["b"])
    want = sets(B.mine_brute_force(info, "0.5", "0.5"))
    for out in (mine_ptree(info, "0.5", "0.5"), B.mine_apriori(info, "0.5", "0.5"), B.mine_rough_set(info, "0.5", "0.5")):
        assert sets(out) == want
    assert mine_ptree(info, "0.5", "0.5", decision="b").rules.count() == (1 if rows == [("x", "y")] else 0)


def test_too_many_candidates_are_an_error(small):
    with pytest.raises(ValueError, match="candidates"):
        mine_ptree(small, "0.05", "0.5", max_candidates=3)
    assert max(r.k for r in mine_ptree(small, "0.05", "0.5", max_len=2).itemsets.collect()) == 2


def test_candidates_as_frames(spark):
    two = [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)]
    df = spark.createDataFrame([(list(s),) for s in two], "items array<int>")
    got = {tuple(r["items"]) for r in candidates.next_level(df).collect()}
    assert got == set(candidates.closed(candidates.joined(two), set(two))) == {(0, 1, 2), (1, 2, 3)}
    one = spark.createDataFrame([([i],) for i in range(4)], "items array<int>")
    attribute = spark.createDataFrame([(0, "a"), (1, "a"), (2, "b"), (3, "b")], "item_id int, attribute string")
    assert {tuple(r["items"]) for r in candidates.next_level(one, attribute).collect()} == {(0, 2), (0, 3), (1, 2), (1, 3)}


def test_redundancy_layout_and_use_of_rules(spark, small):
    out = mine_ptree(small, "0.05", "0.4", decision="e")
    rules = out.rules.cache()
    kept = {(r.antecedent, r.consequent) for r in reduce_rules(rules, "shorter_as_good").collect()}
    all_ = rules.collect()
    for r in all_:
        worse = any(q.consequent == r.consequent and set(q.antecedent.split("|")) < set(r.antecedent.split("|")) and q.cnt_xy * r.cnt_x >= r.cnt_xy * q.cnt_x for q in all_)
        assert ((r.antecedent, r.consequent) in kept) == (not worse)
    assert rules_table(rules).columns == ["k", "e"]
    assert rule_profile(rules).agg(F.sum("rules")).first()[0] == len(all_)
    df = small.df.limit(50)
    got = apply_rules(df, spark.createDataFrame(all_, rules.schema), item_array(out.items))
    assert "hashpartitioning" not in got._jdf.queryExecution().executedPlan().toString()
    assert got.count() == 50 and got.where("conclusion is not null").count() > 0


def test_speedup(spark):
    rows = [("x", "free", "ptree", 2.0), ("x", "free", "apriori", 5.0)]
    got = {r.method: r.times for r in speedup(spark.createDataFrame(rows, "dataset string, mode string, method string, minutes double")).collect()}
    assert got == {"ptree": 1.0, "apriori": 2.5}


@pytest.mark.parametrize("v", ["xy", "x|y", "x=y", "x\\|y", "|", "="])
def test_rules_don_t_depend_on_what_values_look_like(spark, v):
    rows = [(v, "p"), (v, "p"), ("z", "q"), ("z", "p")]
    out = mine_ptree(W.info_table(spark.createDataFrame(rows, "a string, `b|=` string"), ["a"], ["b|="]), "0.2", "0.5")
    assert out.rules.count() == 5 and out.rules.select("antecedent", "consequent").distinct().count() == 5
    assert {tuple(sorted((*r.x, *r.y))) for r in out.rules.collect()} == {tuple(r["items"]) for r in out.itemsets.where("k = 2").collect()}
    any_ = mine_ptree(W.info_table(spark.createDataFrame(rows, "a string, `b|=` string"), ["a"], ["b|="]), "0.2", "0.5", consequent="any")
    assert any_.rules.count() == 5


def test_counting_ways_agree(spark, small):
    want = {tuple(r["items"]): r.cnt for r in mine_ptree(small, "0.05", "0.4", counting="segments").itemsets.collect()}
    for how in ({}, {"bound": True}, {"reuse": "none"}, {"counting": "words"}):
        assert {tuple(r["items"]): r.cnt for r in mine_ptree(small, "0.05", "0.4", **how).itemsets.collect()} == want
    sorted_ = W.InfoTable(small.df.coalesce(1).sortWithinPartitions(*small.attributes), small.conditions, small.decisions)
    out = mine_ptree(sorted_, "0.05", "0.4", trees=Trees(sorted_, segment=4**4), bound=True)
    assert {tuple(r["items"]): r.cnt for r in out.itemsets.collect()} == want
    assert sum(x.spared for x in out.stats.levels) > 0


def test_strong_rules_level_by_level(spark, small):
    for how in ({}, {"decision": "e"}, {"decision": ["e", "b"]}, {"decision": "e", "conditions": ["a", "b"]}):
        out = mine_ptree(small, "0.05", "0.4", emit="strong", **how)
        assert rule_diff(out.rules, mine_ptree(small, "0.05", "0.4", **how).rules).count() == 0
        assert sum(out.stats.strong.values()) == out.rules.count() > 0
    with pytest.raises(ValueError, match="one consequent"):
        mine_ptree(small, "0.05", "0.4", emit="strong", consequent="any")


def test_appended_tuples_bring_new_values(spark):
    schema = "a string, b string"
    first = W.info_table(spark.createDataFrame([("x", "p")] * 3, schema), ["a"], ["b"])
    more = spark.createDataFrame([("new", "p"), ("x", "other")], schema)
    trees = append_segments(Trees(first), more)
    got = {r.label: r.cnt for r in mine_ptree(first, "0.1", "0.1", trees=trees).itemsets.collect()}
    assert got == {"a=x": 4, "b=p": 4, "a=new": 1, "b=other": 1, "a=x|b=p": 3, "a=new|b=p": 1, "a=x|b=other": 1}


def test_short_segments_are_dealt_together(spark):
    rng = np.random.default_rng(0)
    wide = [tuple(f"v{x}" for x in rng.integers(0, 9, 14)) for _ in range(640)]
    names = [f"c{i}" for i in range(14)]
    info = W.info_table(spark.createDataFrame(wide, ", ".join(f"{c} string" for c in names)).repartition(64), names[:-1], names[-1:])
    # One tuple of 14 attributes alone would have 16,383 frequent itemsets.
    out = mine_segmented(info, "0.05", "0.5", segment=128, max_candidates=20_000)
    want = mine_ptree(info, "0.05", "0.5")
    assert {(r.label, r.cnt) for r in out.itemsets.collect()} == {(r.label, r.cnt) for r in want.itemsets.collect()}
