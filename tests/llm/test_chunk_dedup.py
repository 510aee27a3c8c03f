import hashlib

import numpy as np

from ptree_rules.llm.chunk_dedup import EVERY, LEAST, _GEAR, _cuts, cut_out, repeated_spans, runs


def slow_cuts(text):
    cuts, previous = [], 0
    h = 0
    for i, b in enumerate(text):
        h = ((h << 1) + int(_GEAR[b])) & 0xFFFFFFFF
        if h < 2**32 // EVERY:
            if i + 1 - previous >= LEAST:
                cuts.append(i + 1)
            previous = i + 1
    return sorted({*cuts, len(text)} - {0})


def test_cuts():
    rng = np.random.default_rng(1)
    texts = [b"", b"a", bytes(rng.integers(97, 123, 5000, dtype=np.uint8)), b"", bytes(100), bytes(rng.integers(97, 100, 700, dtype=np.uint8))]
    who, begins, ends = _cuts(texts)
    for i, t in enumerate(texts):
        assert ends[who == i].tolist() == slow_cuts(t)
        assert begins[who == i].tolist() == [0, *slow_cuts(t)][: (who == i).sum()]


def brute(rows, least):
    seen, out = {}, []
    rows = [(-(2**63) if i is None else i, (t or "").encode()) for i, t in rows]
    parts = [(i, hash(t), a, b, t[a:b], n) for n, (i, t) in enumerate(rows) for a, b in zip([0, *slow_cuts(t)], slow_cuts(t))]
    import xxhash

    tag = lambda t: np.uint64(xxhash.xxh64_intdigest(t, 42)).astype(np.int64)
    for i, _, a, b, chunk, n in parts:
        place = (i, tag(rows[n][1]), a)
        seen[chunk] = min(place, seen.get(chunk, place))
    for n, (i, t) in enumerate(rows):
        drop = [(a, b) for j, _, a, b, chunk, m in parts if m == n and seen[chunk] != (i, tag(t), a)]
        spans = runs(np.array([a for a, _ in drop]), np.array([b for _, b in drop]), least)
        out.append((None if i == -(2**63) else i, len(t), int((spans[:, 1] - spans[:, 0]).sum()) if len(spans) else 0, len(spans), hashlib.sha256(cut_out(t, spans)).hexdigest()))
    return sorted(out, key=repr)


def test_repeated_spans(spark, hard, none):
    rng = np.random.default_rng(2)
    word = lambda: "".join(map(chr, rng.integers(97, 123, rng.integers(2, 9))))
    passage = " ".join(word() for _ in range(60))
    rows = [(i, " ".join(word() for _ in range(rng.integers(0, 80)))) for i in range(60)]
    rows += [(100 + i, f"{' '.join(word() for _ in range(rng.integers(1, 40)))} {passage} {word()}") for i in range(12)]
    got = repeated_spans(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).drop("spans")
    got = sorted(map(tuple, got.collect()), key=repr)
    assert got == brute(rows, 64)
    assert sum(r[2] > 0 for r in got if r[0] > 100) == 11 and not any(r[2] for r in got if r[0] < 100)
    short = [(r.doc_id, r.text) for r in hard.collect() if r.doc_id != 11]
    got = repeated_spans(hard.where("doc_id is null or doc_id != 11")).drop("spans").collect()
    assert sorted(map(tuple, got), key=repr) == brute(short, 64)
    long = {r.doc_id: r for r in repeated_spans(hard).collect()}[11]
    assert long.n_removed > 0.9 * long.n_bytes
    assert repeated_spans(none).count() == 0
