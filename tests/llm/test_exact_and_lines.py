import hashlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from ptree_rules.llm import first_seen
from ptree_rules.llm.exact_dedup import exact_groups
from ptree_rules.llm.line_dedup import _applied, _keyed, drop_repeated_lines, keep_bitmaps

from .conftest import rows_of

SPACE = " \t\n\x0b\x0c\r"
LOW = {ord(c): c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"}


@pytest.mark.parametrize("keep", ["smallest", "largest"])
def test_exact_groups(hard, keep):
    rows = [(r.doc_id, r.text or "") for r in hard.collect()]
    groups = defaultdict(list)
    for i, t in rows:
        groups[t].append(i)
    order = lambda i: (i is not None, i or 0)
    best = {t: (min if keep == "smallest" else max)(ids, key=order) for t, ids in groups.items()}
    want = [(i, best[t], len(groups[t]), best[t] == i, hashlib.sha256(t.encode()).hexdigest()) for i, t in rows]
    assert rows_of(exact_groups(hard, keep)) == sorted(want, key=repr)


def test_exact_groups_of_nothing(none):
    assert exact_groups(none).count() == 0


def brute_lines(rows):
    rows = [(-(2**63) if i is None else i, t or "") for i, t in rows]
    first = {}
    key = lambda x: x.strip(SPACE).translate(LOW)
    for i, t in rows:
        for x in t.split("\n"):
            first[key(x)] = min(i, first.get(key(x), i))
    out = []
    for i, t in rows:
        lines = t.split("\n")
        kept = [x for x in lines if len(key(x)) < 10 or first[key(x)] == i]
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


def digests(docs):
    joined = _keyed(docs).join(keep_bitmaps(docs), ["doc", "tag"]).select("doc", "text", "n_lines", "n_dropped", "keep")
    return rows_of(joined.mapInArrow(_applied(True), "doc long, n_lines long, n_dropped long, kept_sha256 string"))


def test_lines(hard, none):
    assert digests(hard) == brute_lines([(r.doc_id, r.text) for r in hard.collect()])
    assert keep_bitmaps(none).count() == 0


def test_lines_at_random(spark):
    rng = np.random.default_rng(4)
    pool = [f"some shared line number {i}" for i in range(5)] + ["short", "A hot line in nearly all"] * 2
    rows = [(int(i), "\n".join(rng.choice(pool, rng.integers(1, 6)))) for i in range(300)]
    assert digests(spark.createDataFrame(rows, "doc_id long, text string").repartition(7)) == brute_lines(rows)


def test_line_stage_returns_documents(hard):
    out = drop_repeated_lines(hard)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert out.count() == hard.count()
    assert out.where("doc_id = 8").first().text == "own line of eight"


@pytest.mark.parametrize("whole", [True, False])
def test_later_occurrences_split_a_hot_key(spark, whole):
    rng = np.random.default_rng(1)
    rows = {(int(k), 0, int(d), 0, int(p)) for k, d, p in zip(np.where(rng.random(4000) < 0.5, 7, rng.integers(0, 50, 4000)), rng.integers(0, 900, 4000), rng.integers(0, 9, 4000))}
    first = {}
    for r in sorted(rows):
        first.setdefault(r[:2], r)
    want = Counter(r for r in rows if (r[2] != first[r[:2]][2] if whole else r != first[r[:2]]))
    df = spark.createDataFrame([(*r, 1) for r in rows], first_seen.ROWS)
    spark.conf.set("spark.sql.shuffle.partitions", "16")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = Counter(tuple(r)[:5] for r in first_seen.later_occurrences(df, whole).collect())
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")
    assert got == want
