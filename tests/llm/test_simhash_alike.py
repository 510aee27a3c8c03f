from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest

from ptree_rules.llm import simhash_alike
from ptree_rules.llm.simhash_alike import near_copies, one_of_each_group, shingles, wide_keys, wide_print

pipeline = pytest.importorskip("corpus_pipeline")


def brute(rows, shingle=5, p=4, q=5):
    """id -> least id of its component, by comparing all sets of shingles."""
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        k = min(shingle, len(w))
        sets.append({b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)} if k else set())
    root = list(range(len(rows)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in combinations(range(len(rows)), 2):
        if q * len(sets[a] & sets[b]) >= p * len(sets[a] | sets[b]):
            root[top(a)] = top(b)
    ids = [-(2**63) if i is None else i for i, _ in rows]
    least = {}
    for i in range(len(rows)):
        least[top(i)] = min(ids[i], least.get(top(i), ids[i]))
    return sorted((ids[i], least[top(i)]) for i in range(len(rows)))


def planted(seed, groups=12):
    """Near copies of 40 to 400 words with one word changed up to what is well under the bound, and texts that share passages."""
    rng = np.random.default_rng(seed)
    words = lambda n: [f"w{i}" for i in rng.integers(0, 3000, n)]
    passage, rows = words(60), []
    for g in range(groups):
        base = words(int(rng.integers(40, 400)))
        for k in range(5):
            text = list(base)
            for at in rng.integers(0, len(text), 1 + k * len(text) // 200):
                text[at] = f"new{g}-{k}-{at}"
            rows.append(text + (passage if k == 4 else []))
    return [(1000 - i, " ".join(t)) for i, t in enumerate(rows)]


def found(df):
    return sorted((r.id, r.component) for r in near_copies(df).collect())


def never_wrong(got, want, least):
    """No component crosses one of brute force, and at least that share of the documents has its component."""
    true, own = dict(want), dict(got)
    assert len(got) == len(want)
    assert all(true[i] == true[c] for i, c in own.items())
    assert sum(own[i] == c for i, c in true.items()) >= least * len(true)


def test_planted_near_copies(spark):
    rows = planted(1)
    want = brute(rows)
    assert 20 < sum(i != c for i, c in want) < 55
    never_wrong(found(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)), want, 0.95)


@pytest.mark.parametrize(("similarity", "least"), [(0.8, 0.75), (0.85, 0.87), (0.9, 0.95), (0.95, 0.99)])
def test_share_of_pairs_that_meet(similarity, least):
    """Sets of 300 shingles with a given similarity, each pair alone."""
    rng = np.random.default_rng(8)
    both = round(300 * 2 * similarity / (1 + similarity))
    met = 0
    for _ in range(200):
        x = rng.integers(0, 2**63, 600 - both, dtype=np.uint64)
        prints = np.stack([wide_print(np.sort(x[:300])), wide_print(np.sort(x[-300:]))])
        who, tokens = wide_keys(prints, np.array([300, 300]))
        met += bool(set((tokens[who == 0] >> 29).tolist()) & set((tokens[who == 1] >> 29).tolist()))
    assert met >= least * 200


def test_sizes_of_two_classes_share_keys():
    """Sets just under and over a power of two meet, for they can be alike; ones too far apart don't."""
    x = np.sort(np.random.default_rng(3).integers(0, 2**63, 260, dtype=np.uint64))
    for small, meet in ((250, True), (100, False)):
        prints = np.stack([wide_print(x)] * 2)
        who, tokens = wide_keys(prints, np.array([small, 260]))
        assert bool(set((tokens[who == 0] >> 29).tolist()) & set((tokens[who == 1] >> 29).tolist())) == meet
        assert len(set(zip(who.tolist(), tokens.tolist(), strict=True))) == len(who)


def test_print_is_the_majority():
    got = wide_print(np.arange(40_000, dtype=np.uint64))
    assert got.dtype == np.uint64 and 60 < int(np.bitwise_count(got).sum()) < 196
    assert wide_print(np.zeros(0, np.uint64)).tolist() == [0, 0, 0, 0]
    assert len(shingles(b"a b c d e f a b c d e")) == 6  # the first and last of seven are one
    assert Counter(shingles(b" A b ").tolist()) == Counter(shingles(b"a B").tolist())


def test_stage_drops_near_copies(spark):
    rows = [(i, t, "en", "s1", len(t)) for i, t in planted(2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id for r in dict(pipeline.STAGES)["near-dedup"](spark, docs, "").collect()}
    stay = {i for i, c in brute([(r[0], r[1]) for r in rows]) if i == c}
    assert stay <= got and len(got - stay) <= 2


def test_large_group_and_chain(spark):
    rng = np.random.default_rng(4)
    base = [f"w{i}" for i in rng.integers(0, 500, 120)]
    rows = []
    for i in range(80):
        if i % 2:
            base = list(base)
            base[rng.integers(0, 120)] = f"new{i}"
        rows.append((i, " ".join([*base[: 118 + i % 3], f"end{i}"])))
    never_wrong(found(spark.createDataFrame(rows, "doc_id long, text string")), brute(rows), 0.95)


@pytest.mark.parametrize("short", [1, 3, 10_000])
def test_lists_gathered_or_alone(spark, monkeypatch, short):
    """Whether lists go by their least class or by themselves changes no component."""
    rng = np.random.default_rng(6)
    base = [f"w{i}" for i in rng.integers(0, 500, 200)]
    rows = []
    for i in range(60):
        text = list(base)
        for at in rng.integers(0, 200, 1 + i % 4):
            text[at] = f"new{i}-{at}"
        rows.append((i, " ".join(text)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = found(docs)
    monkeypatch.setattr(simhash_alike, "SHORT", short)
    assert found(docs) == want


def test_parts_hold_whole_keys_and_lists():
    """Rows of one key, and their lists, stay together over batches of any size."""
    keys, lists = [1, 1, 1, 2, 3, 3, 5, 5, 5, 5], [[i] * (i % 3) for i in range(10)]
    whole = pa.record_batch([pa.array(keys), pa.array(lists, pa.list_(pa.int64()))], ["key", "lists"])
    for size in (1, 2, 3, 10):
        parts = list(simhash_alike._ended((whole.slice(i, size) for i in range(0, 10, size)), lambda c: c["key"]))
        assert [k for p in parts for k in p["key"].tolist()] == keys
        assert [x for p in parts for x in p["lists"].to_pylist()] == lists
        assert all(set(a["key"]).isdisjoint(b["key"]) for a, b in combinations(parts, 2))


def test_hard_input(hard, none):
    assert found(hard) == brute([(r.doc_id, r.text) for r in hard.collect()])
    assert near_copies(none).count() == 0
    kept = one_of_each_group(hard.withColumn("id", hard.doc_id).withColumn("goes", hard.doc_id))
    assert kept.columns == [*hard.columns, "id", "goes"]
