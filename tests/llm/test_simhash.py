import re

import numpy as np
import xxhash

from ptree_rules.llm.components import components
from ptree_rules.llm.simhash import fingerprint, fuzzy_keys, nearest_codeword, near_groups, one_of_each_group


def slow_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute(rows):
    prints = [slow_fingerprint(t or "") for _, t in rows]
    ids = [-(2**63) if i is None else i for i, _ in rows]
    root = list(range(len(rows)))
    for _ in rows:
        for a in range(len(rows)):
            for b in range(len(rows)):
                if (prints[a] ^ prints[b]).bit_count() <= 3:
                    m = min(root[a], root[b], key=lambda r: ids[r])
                    root[a] = root[b] = m
    out = {}
    for i, r in enumerate(root):
        out.setdefault(r, []).append(ids[i])
    least = [min(out[r]) for r in root]
    return sorted(((i, f"{p:016x}", m if m != -(2**63) else None) for (i, _), p, m in zip(rows, prints, least)), key=repr)


def test_fingerprint():
    for t in ["", " \t", "One", "one TWO", "a b c", "É  A\nb\x0bC d e f g É a b", "x " * 50, "ä b c d e"]:
        assert fingerprint(t.encode()) == slow_fingerprint(t)


def test_every_word_has_one_codeword_within_three():
    words = np.arange(0, 1 << 23, 997, dtype=np.uint32)
    assert nearest_codeword(words).max() < 1 << 12
    from ptree_rules.llm.simhash import _decoder

    assert len(np.unique(_decoder())) == 2048 and np.bitwise_count(_decoder()).max() == 3


def test_close_fingerprints_share_a_key():
    rng = np.random.default_rng(0)
    one = rng.integers(0, 2**64, 3000, dtype=np.uint64)
    two = one.copy()
    for i in range(len(two)):
        for b in rng.choice(64, rng.integers(0, 4), replace=False):
            two[i] ^= np.uint64(1) << np.uint64(b)
    keys = [{}, {}]
    for out, prints in zip(keys, (one, two)):
        for who, key in zip(*fuzzy_keys(prints)):
            out.setdefault(who, set()).add(key)
    assert all(keys[0][i] & keys[1][i] for i in range(len(one)))


def test_near_groups(hard, none, spark):
    rows = [(r.doc_id, r.text) for r in hard.collect()]
    assert sorted(map(tuple, near_groups(hard).collect()), key=repr) == brute(rows)
    assert near_groups(none).count() == 0


def test_near_groups_of_a_chain(spark):
    rng = np.random.default_rng(3)
    base = [f"w{i}" for i in rng.integers(0, 500, 120)]
    rows = []
    for i in range(60):
        if i % 6 == 0:
            base = [f"w{j}" for j in rng.integers(0, 500, 120)]
        base = list(base)
        base[rng.integers(0, 120)] = f"new{i}"
        rows.append((1000 - i, " ".join(base)))
    got = near_groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(5))
    assert sorted(map(tuple, got.collect()), key=repr) == brute(rows)


def test_one_of_each_group_keeps_the_least_id(hard):
    kept = [r.doc_id for r in one_of_each_group(hard).collect()]
    assert 4 in kept and 5 not in kept and 8 in kept and 11 in kept


def test_components(spark):
    rng = np.random.default_rng(5)
    links = [(int(a), int(b)) for a, b in rng.integers(0, 400, (330, 2))] + [(1000 + i, 1001 + i) for i in range(60)] + [(-5, 7)]
    least = {}
    for a, b in links:
        least.setdefault(a, a), least.setdefault(b, b)
    for _ in range(200):
        for a, b in links:
            least[a] = least[b] = min(least[a], least[b])
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {n: m for n, m in least.items() if n != m}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
