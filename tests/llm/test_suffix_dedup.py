import hashlib
from collections import defaultdict

import numpy as np
import pytest

from ptree_rules.llm.suffix_dedup import anchors, repeated_bytes, suffix_order, windows_that_repeat


def brute(rows, length):
    texts = [(i, (t or "").encode()) for i, t in rows]
    starts = defaultdict(list)
    for n, (_, t) in enumerate(texts):
        for i in range(len(t) - length + 1):
            starts[t[i : i + length]].append((n, i))
    gone = [np.zeros(len(t), bool) for _, t in texts]
    for places in starts.values():
        if len(places) > 1:
            for n, i in places:
                gone[n][i : i + length] = True
    out = []
    for (i, t), g in zip(texts, gone):
        edges = np.flatnonzero(np.diff(np.concatenate([[0], g.view(np.int8), [0]])))
        out.append((i, len(t), int(g.sum()), len(edges) // 2, hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~g])).hexdigest()))
    return sorted(out, key=repr)


@pytest.mark.parametrize("alphabet,n", [(2, 1), (2, 2), (2, 3), (1, 500), (2, 700), (2, 701), (26, 3000), (3, 902)])
def test_suffix_order(alphabet, n):
    rng = np.random.default_rng(n)
    text = rng.integers(97, 97 + alphabet, n).astype(np.uint8)
    order = suffix_order(text, 200)
    assert sorted(order.tolist()) == list(range(n))
    raw = bytes(text)
    ends = [raw[i : i + 200] for i in order.tolist()]
    assert ends == sorted(ends)


def test_windows_that_repeat():
    rng = np.random.default_rng(3)
    base = bytes(rng.integers(97, 100, 400).astype(np.uint8))
    seen = [base[:300], base[50:260], base[120:400], bytes(rng.integers(97, 100, 230).astype(np.uint8)), b"ab" * 110]
    count = defaultdict(int)
    for s in seen:
        for i in range(len(s) - 199):
            count[s[i : i + 200]] += 1
    for s, hit in zip(seen, windows_that_repeat(seen, 200)):
        assert hit.tolist() == [count[s[i : i + 200]] > 1 for i in range(len(s) - 199)]


def test_equal_windows_have_equal_anchors():
    rng = np.random.default_rng(4)
    common = rng.integers(97, 99, 500).astype(np.uint8)
    one, two = np.concatenate([rng.integers(97, 99, 77).astype(np.uint8), common]), np.concatenate([common, rng.integers(97, 99, 50).astype(np.uint8)])

    def of(raw):
        h, pos, lo = anchors(raw, 200, 64)
        at = np.searchsorted(lo, np.arange(len(raw) - 199), "right") - 1
        return [(int(h[a]), int(pos[a] - i)) for i, a in enumerate(at)]

    assert of(one)[77 : 77 + 301] == of(two)[:301]


def run(spark, rows, length=200, parts=4, **options):
    got = repeated_bytes(spark.createDataFrame(rows, "doc_id long, text string").repartition(parts), length, **options)
    return sorted(map(tuple, got.collect()), key=repr)


def test_repeated_bytes(spark):
    rng = np.random.default_rng(5)
    word = lambda: "".join(map(chr, rng.integers(97, 123, rng.integers(2, 9))))
    words = lambda n: " ".join(word() for _ in range(n))
    passage, other = words(60), words(35)
    rows = [(i, words(rng.integers(0, 90))) for i in range(40)]
    rows += [(100 + i, f"{words(rng.integers(0, 30))} {passage} {words(3)}") for i in range(15)]
    rows += [(200 + i, passage[i : 199 + i] + words(9)) for i in range(6)]
    rows += [(300 + i, passage[: 200 + i]) for i in range(3)] + [(310, passage), (311, passage), (312, "short"), (313, "short"), (314, None), (None, other + passage)]
    near = words(150).split()
    for i in range(12):
        near = list(near)
        near[rng.integers(0, 150)] = word()
        rows.append((400 + i, " ".join(near)))
    rows += [(500, "ab" * 150), (501, "x" * 199), (502, "y" * 201), (503, "é" * 101), (504, words(20) + "z" * 230 + words(20)), (505, other + "|" + other)]
    wanted = brute(rows, 200)
    assert run(spark, rows) == wanted
    assert run(spark, rows, crowd=1) == wanted  # every group is cut until its contexts are alone or equal


def test_hard_input(spark, hard, none):
    rows = [(r.doc_id, r.text) for r in hard.collect() if r.doc_id != 11]
    got = repeated_bytes(hard.where("doc_id is null or doc_id != 11"))
    assert sorted(map(tuple, got.collect()), key=repr) == brute(rows, 200)
    assert repeated_bytes(none).count() == 0
    long = {r.doc_id: r for r in repeated_bytes(hard).collect()}[11]
    assert long.n_removed == long.n_bytes and long.n_spans == 1
