import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from ptree_rules.llm.byte_bpe import encode_column
from ptree_rules.llm.packing import pack_lengths, packed, reduce_by_dominance, tokenized_pieces

PATHS = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


@pytest.fixture(scope="module")
def reference():
    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


def test_ids_are_those_of_the_reference(reference):
    rng = random.Random(1)
    bits = ["a", "B c", " ", "\n", "\t", "é", "'s", "12", " ", ",", ".", " foo", "<|endoftext|>", "\r", "\x1c"]
    texts = ["", " ", "  ", "a\n b", "\n\n a"] + ["".join(rng.choices(bits, k=rng.randint(0, 12))) for _ in range(2000)]
    ids, at = encode_column(pa.array(texts), *PATHS)
    for t, a, b in zip(texts, at, at[1:]):
        assert reference.encode(t, add_special_tokens=False).ids == ids[a:b].tolist(), repr(t)


def least_bins(items, cap):
    best, items = [len(items)], sorted(items, reverse=True)

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(items):
            best[0] = len(bins)
            return
        for room in set(bins):
            if room >= items[i]:
                j = bins.index(room)
                go(i + 1, [*bins[:j], room - items[i], *bins[j + 1 :]])
        go(i + 1, [*bins, cap - items[i]])

    go(0, [])
    return best[0]


def test_reduction_keeps_an_optimum():
    rng = random.Random(2)
    for _ in range(150):
        cap = rng.choice([10, 17, 30])
        items = [rng.randint(1, cap) for _ in range(rng.randint(1, 9))]
        fixed, rest = reduce_by_dominance(dict(Counter(items)), cap)
        left = [s for s, n in rest.items() for _ in range(n)]
        assert sum(n for _, n in fixed) + least_bins(left, cap) == least_bins(items, cap), items


def test_packing_places_every_item_once():
    rng = random.Random(3)
    for _ in range(100):
        cap = rng.choice([10, 64, 1024])
        want = Counter(rng.randint(1, cap) for _ in range(rng.randint(1, 400)))
        got = Counter()
        for lengths, n in pack_lengths(dict(want), cap):
            assert sum(lengths) <= cap
            for s in lengths:
                got[s] += n
        assert got == want


def test_packed_documents(hard, none, reference):
    out = packed(tokenized_pieces(hard)).collect()
    by_sequence, by_document = defaultdict(list), defaultdict(list)
    for r in out:
        by_sequence[r.sequence_id].append((r.offset, r.length))
        by_document[r.doc_id].append(r)
    for places in by_sequence.values():
        end = 0
        for offset, length in sorted(places):
            assert offset == end
            end += length
        assert end <= 1024
    texts = {r.doc_id: r.text or "" for r in hard.collect() if r.doc_id not in (None, 5)}
    for i, t in texts.items():
        ids = reference.encode(t, add_special_tokens=False).ids + [2]
        pieces = sorted(by_document[i], key=lambda r: r.piece)
        assert [r.piece for r in pieces] == list(range(len(pieces)))
        assert all(r.length == 1024 for r in pieces[1:]) and sum(r.length for r in pieces) == len(ids)
        for r in pieces:
            assert r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes())
    assert len(by_document[5]) == 2 * len(by_document[4])
    assert packed(tokenized_pieces(none)).count() == 0
