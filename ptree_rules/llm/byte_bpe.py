"""Byte-level BPE of whole columns of text: each distinct space-led word of a batch is encoded once."""

from __future__ import annotations

import base64
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Ends a document in the vocabulary of 50,257 ids; its string inside a text is that id, as tokenizers has it by default.
SPECIAL, SPECIAL_ID = "<|endoftext|>", 50256


@lru_cache(2)
def encoding(ranks_path: str, pattern: str):
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    made = tiktoken.Encoding("byte-bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    leads = np.zeros(max(ranks.values()) + 1, bool)
    for token, rank in ranks.items():
        leads[rank] = token[:1] == b" "
    return made, leads


def encode_one(made, text: str) -> np.ndarray:
    parts = [np.array(made.encode_ordinary(x), np.uint32) for x in text.split(SPECIAL)]
    return np.concatenate([y for x in parts for y in (np.array([SPECIAL_ID], np.uint32), x)][1:])


def encode_column(texts: pa.Array, ranks_path: str, pattern: str) -> tuple[np.ndarray, np.ndarray]:
    """The ids of all texts end to end (uint32), and each text's first place in them (one more entry than texts).

    A word with the one space before it is a piece that BPE never looks beyond, unless white space meets white space: texts
    with such words, or with the special string, are encoded whole.
    """
    made, leads = encoding(ranks_path, pattern)
    words = pc.split_pattern(texts, " ")
    flat, starts = words.flatten(), words.offsets.to_numpy()
    starts = starts - starts[0]
    coded = flat.dictionary_encode()
    codes, vocabulary = coded.indices.to_numpy(), coded.dictionary
    head = pc.utf8_slice_codeunits(vocabulary, 0, 1)
    odd = pc.or_(pc.or_(pc.equal(head, ""), pc.utf8_is_space(head)), pc.match_substring(vocabulary, SPECIAL)).to_numpy(zero_copy_only=False)
    # All distinct words in one text: a token that begins with a space begins a word.
    plain = vocabulary.filter(pa.array(~odd))
    joined = pc.binary_join(pa.ListArray.from_arrays([0, len(plain)], plain), " ")[0].as_py()
    run = made.encode_to_numpy(f" {joined}" if len(plain) else "").astype(np.int64)
    at = np.flatnonzero(leads[run]) if len(run) else np.zeros(0, np.int64)
    fine = np.flatnonzero(~odd)
    assert len(at) == len(fine), "a word began elsewhere than at its space"
    begin, size = np.zeros(len(vocabulary), np.int64), np.zeros(len(vocabulary), np.int64)
    begin[fine], size[fine] = at, np.diff(np.append(at, len(run)))
    # A text's first word has no space before it and is encoded by itself, as are odd texts.
    first = starts[:-1]
    bad = odd[codes]
    bad[first] = False
    count = np.concatenate([[0], np.cumsum(bad)])
    whole = count[starts[1:]] > count[first]
    heads = flat.take(pa.array(first)).to_pylist()
    whole |= np.array([SPECIAL in h for h in heads], bool)
    own = [encode_one(made, t) if w else np.array(made.encode_ordinary(h), np.uint32) if h else np.zeros(0, np.uint32) for t, w, h in zip(_rows(texts, whole), whole, heads, strict=True)]
    sizes = size[codes]
    sizes[np.repeat(whole, np.diff(starts))] = 0
    sizes[first] = [len(x) for x in own]
    ends = np.cumsum(sizes)
    places = np.append(0, ends)[starts]
    ids = np.empty(int(ends[-1]) if len(ends) else 0, np.uint32)
    source = begin[codes]
    source[first] = len(run) + np.append(0, np.cumsum([len(x) for x in own]))[:-1]
    pool = np.concatenate([run.astype(np.uint32), *own]) if own else run.astype(np.uint32)
    shift = np.repeat(source - (ends - sizes), sizes)
    np.take(pool, np.arange(len(ids)) + shift, out=ids)
    return ids, places


def _rows(texts: pa.Array, wanted: np.ndarray) -> list[str | None]:
    return [texts[i].as_py() if w else None for i, w in enumerate(wanted)]


def slices(texts: pa.Array, most_bytes: int = 4_000_000):
    """(from, to) of runs of texts that hold about so many bytes."""
    sizes = pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)
    lot = np.cumsum(sizes) // most_bytes
    cuts = np.flatnonzero(np.diff(lot)) + 1
    return zip([0, *cuts], [*cuts, len(sizes)], strict=True)
