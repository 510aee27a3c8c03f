from collections import defaultdict

import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from ptree_rules.llm.mixing import _order, leaf_budgets, mixed, mixed_documents, planned

W = ({"d0": 4, "d1": 3}, {"en": 4, "de": 2}, {})


def share_out(given, children):
    """children: name -> (weight, cap); what stays above a cap goes round again."""
    got, open_ = dict.fromkeys(children, 0.0), {c for c, (w, cap) in children.items() if w > 0 and cap > 0}
    while open_ and given > 1e-9:
        unit = given / sum(children[c][0] for c in open_)
        full = {c for c in open_ if children[c][1] - got[c] <= unit * children[c][0] + 1e-12}
        for c in full or open_:
            more = children[c][1] - got[c] if full else unit * children[c][0]
            got[c] += more
            given -= more
        if not full:
            break
        open_ -= full
    return got


def slow_budgets(leaves, budget, epochs, weights):
    def go(path, given, out):
        if len(path) == 3:
            out[path] = given
            return out
        below = defaultdict(float)
        for leaf, n in leaves.items():
            if leaf[: len(path)] == path:
                below[leaf[len(path)]] += n * epochs
        w = weights[len(path)]
        for child, got in share_out(given, {c: (w.get(c, 1.0), cap) for c, cap in below.items()}).items():
            go((*path, child), got, out)
        return out

    return go((), budget, {})


@pytest.mark.parametrize("budget,epochs", [(1000, 1), (1800, 1), (1999, 2), (9000, 4), (50, 4), (0, 4)])
def test_budgets(spark, budget, epochs):
    leaves = {("d0", "en", "a"): 700, ("d0", "en", "b"): 30, ("d0", "de", "a"): 90, ("d0", None, "c"): 10, ("d1", "en", "a"): 400, ("d1", "de", None): 500, (None, "fr", "z"): 5, ("d2", "en", "q"): 0}
    df = spark.createDataFrame([(str(k), *k, n) for k, n in leaves.items()], "leaf string, domain string, lang string, source string, tokens long")
    got = {(r.domain, r.lang, r.source): r.budget for r in leaf_budgets(df, budget, epochs, W).collect()}
    want = slow_budgets(leaves, budget, epochs, W)
    assert got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) <= 1 for k in want), (got, want)
    assert sum(want.values()) == pytest.approx(min(budget, sum(leaves.values()) * epochs))


def check(docs, out, seed=17):
    by = defaultdict(list)
    for r in out.withColumn("id", F.coalesce("doc_id", F.lit(-(2**63)))).collect():
        by[(r.domain, r.lang, r.source)].append(r)
    for rows in by.values():
        budget, supply = rows[0].leaf_budget, sum(r.tokens for r in rows)
        assert len({r.leaf_budget for r in rows}) == 1
        whole = budget // supply if supply else 1
        rest = budget - whole * supply
        spark = docs.sparkSession
        ids = spark.createDataFrame([(r.id, r.tokens) for r in rows], "id long, t long")
        order = sorted((r.at, r.id, r.t) for r in ids.select("id", "t", _order(seed, F.lit(int(whole))).alias("at")).collect())
        taken, upto = set(), 0
        sums = defaultdict(int)
        for at, _, t in order:
            sums[at] += t
        for at in sorted(sums):
            upto += sums[at]
            if upto > rest or rest <= 0:
                break
            taken |= {i for a, i, _ in order if a == at}
        assert {(r.id, r.copies) for r in rows} == {(r.id, whole + (r.id in taken)) for r in rows}


def test_mixed(spark):
    rows = [(i, "w " * (i % 17), ["en", "de", None][i % 3], f"src{i % 5}") for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    out = mixed(docs, budget_share=0.6, max_epochs=3)
    assert out.count() == 400
    check(docs, out)
    copies = {r.doc_id: r.copies for r in out.collect()}
    again = defaultdict(int)
    for r in mixed_documents(docs, budget_share=0.6, max_epochs=3).collect():
        again[r.doc_id] += 1
    assert dict(again) == {i: c for i, c in copies.items() if c}


def test_hard_input(hard, none):
    out = mixed(hard, domain=F.lit("one"))
    assert out.count() == hard.count() and out.columns[: len(hard.columns)] == hard.columns
    check(hard, out)
    assert mixed(none).count() == 0


def test_own_columns_survive_clashing_names(hard):
    """Callers' columns of the operator's inner names, and of the names it adds."""
    inner = ("id", "leaf", "budget", "whole", "until", "r", "counted", "at", "bucket")
    docs = hard.select("*", *(F.concat(F.lit(f"{c}-"), F.coalesce(F.col("doc_id").cast("string"), F.lit("?"))).alias(c) for c in (*inner, "copies", "tokens", "domain")))
    out = mixed(docs)
    assert len(out.columns) == len(set(out.columns)) and set(out.columns) == {*docs.columns, "leaf_budget"}
    rows = out.collect()
    assert len(rows) == hard.count()
    assert all(r[c] == f"{c}-{'?' if r.doc_id is None else r.doc_id}" for r in rows for c in inner)
    assert mixed_documents(docs).columns == docs.columns


def test_tokens_are_the_vocabulary_s(spark):
    named = Tokenizer.from_file(str(public_tokenizers.path("byte_bpe_50k.json")))
    texts = ["", None, "two words", "  spaces \n\n and lines\t", "véry lông " * 500, "<|endoftext|> inside", "word"]
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string")
    got = {r.doc_id: r.tokens for r in planned(docs).collect()}
    assert got == {i: len(named.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(texts)}
    given = {r.doc_id: r.tokens for r in mixed(docs, tokens=F.col("doc_id") * 2).collect()}
    assert given == {i: 2 * i for i in range(len(texts))}
