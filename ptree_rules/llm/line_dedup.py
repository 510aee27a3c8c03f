"""Line dedup: first occurrences of line hashes, and a compressed keep bitmap per document."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_back, id_or_least, table, text_or_empty, written
from .first_seen import ROWS, later_occurrences

#: Keys with fewer code points are never dropped.
MIN_KEY_CHARS = 10
_SPACE = b" \t\n\x0b\x0c\r"


def _lines(min_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        space = _SPACE.decode()
        for batch in batches:
            digests, docs, tags, places = [], [], [], []
            for doc, tag, text in zip(batch.column("doc").to_pylist(), batch.column("tag").to_pylist(), batch.column("text").to_pylist(), strict=True):
                for pos, line in enumerate(text.split("\n")):
                    key = line.strip(space)
                    if len(key) >= min_chars:
                        digests.append(xxhash.xxh3_128_digest(key.encode().lower()))
                        docs.append(doc)
                        tags.append(tag)
                        places.append(pos)
            if docs:
                k = np.frombuffer(b"".join(digests), "<i8").reshape(-1, 2)
                yield pa.record_batch(
                    [pa.array(np.ascontiguousarray(k[:, 0])), pa.array(np.ascontiguousarray(k[:, 1])), pa.array(docs, pa.int64()), pa.array(tags, pa.int64()), pa.array(places, pa.int32()), pa.array(np.zeros(len(docs), np.int32))],
                    ["k1", "k2", "doc", "tag", "pos", "len"],
                )

    return run


def _bitmaps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for n, dropped in zip(batch.column("n_lines").to_pylist(), batch.column("dropped"), strict=True):
            keep = np.ones(n, np.uint8)
            if dropped.is_valid:
                keep[dropped.values.to_numpy()] = 0
            out.append(zlib.compress(np.packbits(keep).tobytes(), 1))
        dropped = [len(x) if x.is_valid else 0 for x in batch.column("dropped")]
        yield pa.record_batch([batch.column("doc"), batch.column("tag"), batch.column("n_lines").cast(pa.int64()), pa.array(dropped, pa.int64()), pa.array(out, pa.binary())], ["doc", "tag", "n_lines", "n_dropped", "keep"])


def _keyed(docs: DataFrame) -> DataFrame:
    """doc and tag name a document: its id, and a hash of its text for ids that occur twice."""
    text = text_or_empty()
    return docs.select(id_or_least().alias("doc"), F.xxhash64(text).alias("tag"), text.alias("text"))


def keep_bitmaps(docs: DataFrame, min_chars: int = MIN_KEY_CHARS) -> DataFrame:
    """doc, tag, n_lines, n_dropped and keep, a deflated bitmap with one bit per line (1: the line stays), per document.

    A line's key is the line without white space at its ends, in lower case (A-Z only). Keys of at least min_chars code points
    that several documents hold lose their lines in all but the smallest doc_id. Null or empty text is one empty line. Rows
    that repeat an id and its text count once. Null ids come first. Rows travel as 128-bit hashes, never as text.
    """
    keyed = _keyed(docs)
    drop = later_occurrences(keyed.mapInArrow(_lines(min_chars), ROWS), whole_document=True)
    drop = drop.groupBy("doc", "tag").agg(F.array_sort(F.collect_set("pos")).alias("dropped"))
    count = F.length("text") - F.length(F.translate("text", "\n", "")) + 1
    sizes = keyed.select("doc", "tag", count.cast("int").alias("n_lines")).distinct()
    return sizes.join(drop, ["doc", "tag"], "left").mapInArrow(_bitmaps, "doc long, tag long, n_lines long, n_dropped long, keep binary")


def _kept_text(text: str, keep: bytes) -> str:
    lines = text.split("\n")
    bits = np.unpackbits(np.frombuffer(zlib.decompress(keep), np.uint8), count=len(lines))
    return text if bits.all() else "\n".join(x for x, b in zip(lines, bits, strict=True) if b)


def _applied(digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept = [_kept_text(t, k) for t, k in zip(batch.column("text").to_pylist(), batch.column("keep").to_pylist(), strict=True)]
            if digest:
                cols = {n: batch.column(n) for n in ("doc", "n_lines", "n_dropped")}
                cols["kept_sha256"] = pa.array([hashlib.sha256(x.encode()).hexdigest() for x in kept], pa.string())
            else:
                cols = {n: batch.column(n) for n in batch.schema.names if n not in ("keep", "tag", "n_lines", "n_dropped")} | {"text": pa.array(kept, pa.string())}
            yield pa.RecordBatch.from_pydict(cols)

    return run


def drop_repeated_lines(docs: DataFrame, min_chars: int = MIN_KEY_CHARS) -> DataFrame:
    """docs(doc_id, text, lang, source, n_chars) with the repeated lines gone and n_chars counted anew; a null text becomes
    empty. See keep_bitmaps()."""
    bitmaps = written(keep_bitmaps(docs.select("doc_id", "text"), min_chars), "bitmaps").select("doc", "tag", "keep")
    text = text_or_empty()
    rows = docs.select(id_or_least().alias("doc"), F.xxhash64(text).alias("tag"), text.alias("text"), "lang", "source")
    out = rows.join(bitmaps, ["doc", "tag"]).select("doc", "text", "lang", "source", "keep")
    out = out.mapInArrow(_applied(False), "doc long, text string, lang string, source string")
    return out.select(id_back("doc").alias("doc_id"), "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    bitmaps = written(keep_bitmaps(docs), "bitmaps")
    out = _keyed(docs).join(bitmaps, ["doc", "tag"]).select("doc", "text", "n_lines", "n_dropped", "keep")
    out = out.mapInArrow(_applied(True), "doc long, n_lines long, n_dropped long, kept_sha256 string")
    return out.select(id_back("doc").alias("doc_id"), "n_lines", "n_dropped", "kept_sha256")


SQL = {
    "op7_line_dedup": r"""
        WITH l AS (
            SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
                   unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS pos
            FROM documents),
        k AS (
            SELECT doc_id, pos, line,
                   translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                             'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
            FROM l),
        m AS (
            SELECT *, length(key) >= 10 AND doc_id > min(doc_id) OVER (PARTITION BY key) AS gone FROM k)
        SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
               sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
        FROM m GROUP BY doc_id"""
}
