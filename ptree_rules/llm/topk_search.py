"""Exact top-k by integer inner product, block at a time with bounds from summed term maxima."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

#: Best candidates of a query, vectors of a block, vectors of a shard and queries of a group (a task gets one of each).
K, BLOCK, SHARD, GROUP = 20, 256, 16_384, 2048
_FOUND = "query_id long, vec_id long, score long"


def block_search(queries: np.ndarray, query_ids: np.ndarray, docs: np.ndarray, doc_ids: np.ndarray, k: int = K, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray, int]:
    """(ids, scores, blocks scored) of the k best docs of each query; id order breaks ties, a query's own id is left out.

    Documents are put in an order that brings like vectors together and cut into ranges. A range's bound for a query sums,
    over the terms, the larger product with the range's greatest and least value. Each query visits its ranges from the
    highest bound down and stops at the first bound below its k-th score; a bound equal to it may hide a smaller id.
    Missing places have score None's stand-in, the least integer.
    """
    least, none = np.iinfo(np.int64).min, np.iinfo(np.int64).max
    best_s, best_i = np.full((len(queries), k), least), np.full((len(queries), k), none)
    if not len(docs) or not len(queries):
        return best_i, best_s, 0
    exact = float(np.abs(queries).max(initial=0)) * float(np.abs(docs).max(initial=0)) * docs.shape[1] < 2**52
    kind = np.float64 if exact else np.int64
    q = queries.astype(kind)
    axes = np.random.default_rng(5).standard_normal((docs.shape[1], 16))
    code = ((docs - docs.mean(0)) @ axes > 0) @ (1 << np.arange(16)[::-1])
    order = np.lexsort((doc_ids, code))
    d, ids = docs[order].astype(kind), doc_ids[order]
    cuts = np.arange(0, len(d), block)
    high, low = np.maximum.reduceat(d, cuts), np.minimum.reduceat(d, cuts)
    bound = np.maximum(q, 0) @ high.T + np.minimum(q, 0) @ low.T
    visit = np.argsort(-bound, 1, kind="stable")
    active, scored = np.arange(len(q)), 0
    for rank in range(len(cuts)):
        now = visit[active, rank]
        more = bound[active, now] >= best_s[active, -1]
        active, now = active[more], now[more]
        if not len(active):
            break
        by = np.argsort(now, kind="stable")
        for part in np.split(by, np.flatnonzero(np.diff(now[by])) + 1):
            rows, b = active[part], now[part[0]]
            lo, hi = cuts[b], min(cuts[b] + block, len(d))
            scored += len(rows)
            s = (q[rows] @ d[lo:hi].T).astype(np.int64)
            i = np.broadcast_to(ids[lo:hi], s.shape)
            own = i == query_ids[rows][:, None]
            s = np.where(own, least, s)
            worth = s.max(1) >= best_s[rows, -1]
            rows, s, i = rows[worth], np.hstack([best_s[rows[worth]], s[worth]]), np.hstack([best_i[rows[worth]], np.where(own, none, i)[worth]])
            top = np.lexsort((i, np.invert(s)))[:, :k]  # ~s falls as s rises, and never overflows
            best_s[rows], best_i[rows] = np.take_along_axis(s, top, 1), np.take_along_axis(i, top, 1)
    return best_i, best_s, scored


def _matrix(t: pa.Table, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and quantised vectors, zero beyond a vector's end; rows repeated whole count once."""
    ids, lists = t.column("vec_id").to_numpy(), t.column("v").combine_chunks()
    out = np.zeros((len(ids), width), np.int64)
    if len(ids):
        sizes = np.diff(lists.offsets.to_numpy())
        out[np.arange(width) < sizes[:, None]] = np.floor(64.0 * lists.flatten().to_numpy().astype(np.float64)).astype(np.int64)
        both = np.unique(np.column_stack([ids, out]), axis=0)
        ids, out = both[:, 0], both[:, 1:]
    return ids, out


def _searched(k: int, width: int):
    def run(key: tuple, docs: pa.Table, queries: pa.Table) -> pa.Table:
        doc_ids, d = _matrix(docs, width)
        query_ids, q = _matrix(queries, width)
        ids, scores, _ = block_search(q, query_ids, d, doc_ids, k)
        real = ids != np.iinfo(np.int64).max
        return pa.table({"query_id": np.repeat(query_ids, k)[real.ravel()], "vec_id": ids[real], "score": scores[real]})

    return run


def top_k(vectors: DataFrame, is_query, k: int = K) -> DataFrame:
    """query_id, rank, vec_id, score of the k best of all vectors(vec_id, embedding) for those that is_query selects.

    Components count as floor(64 x). Null vectors, those with null or non-finite components and null ids take no part; shorter
    vectors are zero beyond their end. A query's own id is no candidate, ties go to the smaller id, and a query with fewer
    candidates has fewer rows. Vectors are dealt to shards and queries to groups by hash, each of a fixed size, so a task's
    memory doesn't grow with the input; a shard's k best are merged by a window that keeps k rows per task first.
    """
    e = F.col("embedding")
    bad = F.exists(e, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    sound = vectors.where(F.col("vec_id").isNotNull() & e.isNotNull() & ~F.coalesce(bad, F.lit(False)))
    rows = sound.select(F.col("vec_id").cast("long"), F.transform(e, lambda x: x.cast("double")).alias("v"))
    n, asked, width = rows.agg(F.count("*"), F.count(F.when(is_query, 1)), F.max(F.size("v"))).collect()[0]
    shards, groups, width = math.ceil(n / SHARD) or 1, math.ceil(asked / GROUP) or 1, width or 1
    dealt = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    docs = rows.select("vec_id", "v", dealt(shards).alias("shard"), each(groups).alias("grp"))
    queries = rows.where(is_query).select("vec_id", "v", dealt(groups).alias("grp"), each(shards).alias("shard"))
    pairs = docs.groupBy("shard", "grp").cogroup(queries.groupBy("shard", "grp"))
    found = pairs.applyInArrow(_searched(k, width), _FOUND)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 20 == 0)


SQL = {
    "op5_exact_topk": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
            FROM embeddings WHERE embedding IS NOT NULL
              AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        p AS (
            SELECT q.vec_id AS query_id, c.vec_id,
                   CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2])) AS BIGINT) AS score
            FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id)
        SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
        FROM p QUALIFY rank <= 20"""
}
