"""Substring dedup by content-defined chunks: a gear rolling hash cuts, digests of chunks find what came before."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_back, id_or_least, table, text_or_empty, written
from .first_seen import ROWS, later_occurrences

#: One in so many places is a candidate to cut; a cut is kept if no candidate is within LEAST bytes before it.
EVERY, LEAST = 24, 12
#: A run of repeated chunks goes if it has at least so many bytes.
MIN_RUN = 64
#: Bytes hashed at a time.
_LOT = 4_000_000
#: The gear: a fixed random 32-bit number per byte; 32 shifts later a byte has left the hash.
_GEAR = np.random.default_rng(20240229).integers(0, 2**32, 256, dtype=np.uint32)
_REACH = 32


def _cuts(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text number, start, end) of all chunks. Cuts depend on the 32 bytes before them, and not on where a text begins."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    starts = np.cumsum(sizes + _REACH) - sizes  # a gap that adds nothing to the hash comes before each text
    h = _GEAR[np.frombuffer(b"".join([bytes(_REACH) + t for t in texts]), np.uint8)]
    for s in starts.tolist():
        h[s - _REACH : s] = 0
    for reach in (1, 2, 4, 8, 16):
        h[reach:] = h[reach:] + (h[:-reach] << np.uint32(reach))
    found = np.flatnonzero(h < np.uint32(2**32 // EVERY)) + 1
    owner = np.searchsorted(starts, found - 1, "right") - 1
    inside = (owner >= 0) & (found > starts[owner]) & (found < starts[owner] + sizes[owner])
    found, owner = found[inside], owner[inside]
    previous = np.maximum(np.append(-_REACH, found[:-1])[: len(found)], starts[owner]) if len(found) else found
    keep = found - previous >= LEAST
    found, owner = found[keep], owner[keep]
    full = np.flatnonzero(sizes)
    who = np.concatenate([owner, full])
    ends = np.concatenate([found - starts[owner], sizes[full]])
    order = np.lexsort((ends, who))
    who, ends = who[order], ends[order]
    begins = np.where(np.append(True, who[1:] != who[:-1])[: len(who)], 0, np.append(0, ends[:-1])[: len(who)])
    return who, begins, ends


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    digest = xxhash.xxh3_128_digest
    for batch in batches:
        docs, tags = batch.column("doc").to_numpy(), batch.column("tag").to_numpy()
        texts = [t.encode() for t in batch.column("text").to_pylist()]
        lot = np.cumsum([len(t) for t in texts]) // _LOT if texts else np.zeros(0)
        for lo, hi in zip([0, *(np.flatnonzero(np.diff(lot)) + 1)], [*(np.flatnonzero(np.diff(lot)) + 1), len(texts)], strict=True):
            part = texts[lo:hi]
            who, begins, ends = _cuts(part) if part else (np.zeros(0, np.int64),) * 3
            if len(who):
                k = np.frombuffer(b"".join([digest(part[w][a:b]) for w, a, b in zip(who.tolist(), begins.tolist(), ends.tolist(), strict=True)]), "<i8").reshape(-1, 2)
                yield pa.record_batch([pa.array(np.ascontiguousarray(k[:, 0])), pa.array(np.ascontiguousarray(k[:, 1])), pa.array(docs[lo + who]), pa.array(tags[lo + who]), pa.array(begins.astype(np.int32)), pa.array((ends - begins).astype(np.int32))], ["k1", "k2", "doc", "tag", "pos", "len"])


def _keyed(docs: DataFrame) -> DataFrame:
    text = text_or_empty()
    return docs.select(id_or_least().alias("doc"), F.xxhash64(text).alias("tag"), text.alias("text"))


def runs(begins: np.ndarray, ends: np.ndarray, least: int) -> np.ndarray:
    """Rows (start, end) of the maximal runs of adjoining spans that have at least so many bytes."""
    if not len(begins):
        return np.zeros((0, 2), np.int64)
    order = np.argsort(begins, kind="stable")
    b, e = begins[order].astype(np.int64), np.maximum.accumulate(ends[order].astype(np.int64))
    new = np.append(True, b[1:] > e[:-1])
    out = np.column_stack([b[new], e[np.append(np.flatnonzero(new)[1:] - 1, len(e) - 1)]])
    return out[out[:, 1] - out[:, 0] >= least]


def cut_out(text: bytes, spans: np.ndarray) -> bytes:
    parts, at = [], 0
    for a, b in spans.tolist():
        parts.append(text[at:a])
        at = b
    return b"".join([*parts, text[at:]])


def _applied(min_run: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[str, list] = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept_sha256", "spans")}
            pos, size = batch.column("pos"), batch.column("len")
            for text, p, n in zip(batch.column("text").to_pylist(), pos, size, strict=True):
                raw = text.encode()
                b = p.values.to_numpy() if p.is_valid else np.zeros(0, np.int32)
                spans = runs(b, b + (n.values.to_numpy() if n.is_valid else 0), min_run)
                out["n_bytes"].append(len(raw))
                out["n_removed"].append(int((spans[:, 1] - spans[:, 0]).sum()))
                out["n_spans"].append(len(spans))
                out["kept_sha256"].append(hashlib.sha256(cut_out(raw, spans)).hexdigest())
                out["spans"].append([{"start": a, "end": e} for a, e in spans.tolist()])
            span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
            kinds = dict(n_bytes=pa.int64(), n_removed=pa.int64(), n_spans=pa.int64(), kept_sha256=pa.string(), spans=span)
            yield pa.RecordBatch.from_pydict({"doc": batch.column("doc")} | {k: pa.array(v, kinds[k]) for k, v in out.items()})

    return run


def repeated_spans(docs: DataFrame, min_run: int = MIN_RUN) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and spans (of bytes) for every row of docs(doc_id, text).

    A chunk that occurred before, in document order and then by place, is repeated; runs of repeated chunks of at least
    min_run bytes are taken out, and the first occurrence of a chunk stays. What is found is exact to the chunk: a repeated
    passage loses its chunks that lie in it whole. Null or empty text has no chunks. Rows that repeat an id and its text count
    once. Null ids come first. Chunks travel as 128-bit digests; a text is shuffled once, for the outcome.
    """
    keyed = _keyed(docs)
    later = later_occurrences(keyed.mapInArrow(_chunks, ROWS), whole_document=False)
    later = written(later.select("doc", "tag", "pos", "len").distinct(), "repeated")
    lists = later.groupBy("doc", "tag").agg(F.sort_array(F.collect_list(F.struct("pos", "len"))).alias("x")).select("doc", "tag", "x.pos", "x.len")
    out = keyed.join(lists, ["doc", "tag"], "left").select("doc", "text", "pos", "len")
    kinds = "doc long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,end:long>>"
    return out.mapInArrow(_applied(min_run), kinds).select(id_back("doc").alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans")


def op9_chunk_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_spans(table(spark, sf_dir, "documents", "doc_id", "text")).drop("spans")
