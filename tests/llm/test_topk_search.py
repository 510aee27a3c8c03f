import math

import numpy as np
from pyspark.sql import functions as F

from ptree_rules.llm import topk_search
from ptree_rules.llm.topk_search import block_search, top_k


def brute(rows, k, every):
    v = {}
    for i, e in rows:
        if i is not None and e is not None and all(x is not None and math.isfinite(x) for x in e):
            v[i] = [math.floor(64 * x) for x in e]
    out = []
    for q in v:
        if q % every == 0:
            best = sorted((-sum(a * b for a, b in zip(v[q], v[i])), i) for i in v if i != q)[:k]
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(best)]
    return sorted(out)


def test_top_k(spark, monkeypatch):
    rng = np.random.default_rng(1)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(size=6)]) for i in range(400)]
    rows += [(i, [0.5] * 6) for i in range(400, 700)]  # a very common vector: ties
    rows += [(700, None), (701, [1.0, None]), (702, [float("nan")] * 6), (703, [float("inf")]), (None, [1.0]), (704, []), (720, [2.0])]
    df = spark.createDataFrame([(*r, "x") for r in [*rows, rows[3], rows[20]]], "vec_id long, embedding array<float>, score string")
    monkeypatch.setattr(topk_search, "SHARD", 100)
    monkeypatch.setattr(topk_search, "GROUP", 7)
    got = sorted(map(tuple, top_k(df, F.col("vec_id") % 20 == 0).collect()))
    assert got == brute(rows, 20, 20)


def test_few_and_no_candidates(spark):
    kind = "vec_id long, embedding array<float>"
    assert top_k(spark.createDataFrame([], kind), F.lit(True)).count() == 0
    two = spark.createDataFrame([(0, [1.0]), (1, [1.0])], kind)
    assert sorted(map(tuple, top_k(two, F.col("vec_id") % 20 == 0).collect())) == [(0, 1, 1, 4096)]


def test_bounds_skip_blocks():
    rng = np.random.default_rng(2)
    centres = rng.integers(-60, 60, (40, 16))
    docs = np.concatenate([c + rng.integers(-3, 4, (64, 16)) for c in centres])
    ids, scores, scored = block_search(docs[:40], np.arange(40), docs, np.arange(len(docs)), 5, block=64)
    want = docs[:40] @ docs.T
    want[np.arange(40), np.arange(40)] = -(10**9)
    assert (scores == -np.sort(-want, 1)[:, :5]).all()
    assert scored < 0.7 * 40 * 40
