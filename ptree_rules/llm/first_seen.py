"""First occurrences of 128-bit keys: rows are range-partitioned by key with documents and positions as secondary sort, and
every partition is streamed once. Line dedup and chunk dedup are built on it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

#: Of the rows that go in: the key, the document (its id and a hash of its text), the place in it and a length.
ROWS = "k1 long, k2 long, doc long, tag long, pos int, len int"
_SORT = ("k1", "k2", "doc", "tag", "pos")
_OUT = f"kind int, {ROWS}"
_DROP, _OPEN, _EDGE = 0, 1, 2


def _stream(whole_document: bool):
    """The pass over one sorted partition: rows after the first of their key are dropped. A partition can't judge its first
    key, which may have begun before, so these rows stay open, and the last key's first row tells the partitions after it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in ROWS.split(", ")]
        begun = None  # the partition's first key
        key = head = None  # the key at hand, and its first row as (doc, tag, pos, len)
        for batch in batches:
            if not batch.num_rows:
                continue
            c = {n: batch.column(n).to_numpy() for n in names}
            n = batch.num_rows
            new = np.ones(n, bool)
            new[1:] = (c["k1"][1:] != c["k1"][:-1]) | (c["k2"][1:] != c["k2"][:-1])
            new[0] = key != (c["k1"][0], c["k2"][0])
            begun = begun or (c["k1"][0], c["k2"][0])
            at = np.maximum.accumulate(np.where(new, np.arange(n), -1))  # -1: the key began in an earlier batch
            first = {f: np.where(at >= 0, c[f][np.maximum(at, 0)], head[i] if head else 0) for i, f in enumerate(("doc", "tag", "pos", "len"))}
            own = c["doc"] != first["doc"]
            if not whole_document:
                own |= (c["tag"] != first["tag"]) | (c["pos"] != first["pos"])
            opened = (c["k1"] == begun[0]) & (c["k2"] == begun[1])
            take = np.flatnonzero(opened | own)
            if len(take):
                yield pa.record_batch([pa.array(np.where(opened[take], _OPEN, _DROP).astype(np.int32)), *(pa.array(c[f][take]) for f in names)], ["kind", *names])
            key = (c["k1"][-1], c["k2"][-1])
            head = tuple(first[f][-1] for f in ("doc", "tag", "pos", "len"))
        if key:
            values = [_EDGE, *key, *head]
            kinds = [pa.int32(), *[pa.int64()] * 4, pa.int32(), pa.int32()]
            yield pa.record_batch([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], ["kind", *names])

    return run


def later_occurrences(rows: DataFrame, whole_document: bool) -> DataFrame:
    """The rows (see ROWS) that aren't of the first occurrence of their key.

    whole_document: all rows of the key in its smallest document count as first; else only the very first row does. Rows that
    agree in document, text hash and place are one. A key with a third of all rows is split over many range partitions, as
    document and place belong to the sort key; what its partitions can't tell alone is settled from one row of each.
    """
    spread = rows.repartitionByRange(*_SORT).sortWithinPartitions(*_SORT)
    judged = written(spread.mapInArrow(_stream(whole_document), _OUT), "judged")
    unsure = judged.where(F.col("kind") != _DROP)
    first = unsure.groupBy("k1", "k2").agg(F.min(F.struct("doc", "tag", "pos")).alias("first"))
    # Every partition leaves at most two keys open, so this side is bounded by their number.
    settled = unsure.where(F.col("kind") == _OPEN).join(F.broadcast(first), ["k1", "k2"])
    differs = F.col("doc") != F.col("first.doc")
    if not whole_document:
        differs |= (F.col("tag") != F.col("first.tag")) | (F.col("pos") != F.col("first.pos"))
    names = judged.columns[1:]
    return judged.where(F.col("kind") == _DROP).select(*names).unionByName(settled.where(differs).select(*names))


