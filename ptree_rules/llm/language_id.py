"""Language ID: multinomial naive Bayes over hashed character n-grams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import giving_back, table

#: Hashed buckets, n-gram lengths in characters, additive smoothing, and the most labelled rows that a fit reads.
BUCKETS, LENGTHS, SMOOTHING, FIT_ROWS = 1 << 15, (1, 2, 3), 0.5, 12_000
UNKNOWN = "und"
#: Characters scored at a time, so that a text of any length needs bounded memory.
_BLOCK = 1 << 18
_MIX = np.uint32(0x9E3779B1)


def _ngrams(texts: list[str], lengths: tuple[int, ...], buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text number, bucket) of all n-grams, a block of characters at a time. A space goes before and after every text."""
    padded = [f" {t.lower()} ".encode("utf-32-le", "surrogatepass") for t in texts]
    sizes = np.array([len(x) // 4 for x in padded], np.int64)
    codes = np.frombuffer(b"".join(padded), "<u4")
    ends = np.cumsum(sizes)
    overlap = max(lengths) - 1
    for lo in range(0, len(codes), _BLOCK):
        part = codes[lo : lo + _BLOCK + overlap]
        owner = np.searchsorted(ends, np.arange(lo, lo + len(part)), "right").astype(np.int32)
        for n in lengths:
            m = min(_BLOCK, len(part) - n + 1)
            if m <= 0:
                continue
            h = np.full(m, n, np.uint32)
            for k in range(n):
                h = (h ^ part[k : k + m]) * _MIX
                h ^= h >> np.uint32(15)
            same = owner[:m] == owner[n - 1 : n - 1 + m]
            yield owner[:m][same], (h & np.uint32(buckets - 1))[same].astype(np.int32)


def _has_letter(text: str | None) -> bool:
    return text is not None and any(map(str.isalpha, text))


def _counts(buckets: int, lengths: tuple[int, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            langs = batch.column("lang").to_pylist()
            names = sorted(set(langs))
            number = np.array([names.index(x) for x in langs], np.int64)
            for owner, bucket in _ngrams([t or "" for t in batch.column("text").to_pylist()], lengths, buckets):
                flat = np.bincount(number[owner] * buckets + bucket, minlength=len(names) * buckets).reshape(-1, buckets)
                for name, row in zip(names, flat, strict=True):
                    sums[name] = sums.get(name, 0) + row
        for name, row in sums.items():
            at = np.flatnonzero(row)
            yield pa.record_batch([pa.array([name] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(row[at].astype(np.int64))], ["lang", "bucket", "n"])

    return run


def fit(labelled: DataFrame, fit_rows: int = FIT_ROWS, buckets: int = BUCKETS, lengths: tuple[int, ...] = LENGTHS, smoothing: float = SMOOTHING) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(languages, log P(bucket | language) of shape (buckets, languages), log P(language)) from labelled(doc_id, text, lang).

    Rows with a null text or language take no part; repeats count each time; other columns are ignored. Counting is
    distributed; it reads the fit_rows rows whose hashed id is least, a bounded sample of the labelled rows. What
    comes to the driver is the count matrix, bounded by buckets times the sample's languages.
    """
    usable = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    draw = usable.select("text", "lang", F.xxhash64(F.lit(3), "doc_id").alias("draw"))
    seen = draw.agg(F.count("*").alias("n")).collect()[0]["n"]
    if seen > fit_rows:
        # Hashes are uniform, so this threshold yields about fit_rows rows and needs no global sort.
        draw = draw.where(F.col("draw") < F.lit(int(-(2**63) + 2**64 * (fit_rows / seen))))
    sample = draw.select("text", "lang")
    prior = {r["lang"]: r["n"] for r in sample.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    langs = sorted(prior)
    counts = np.zeros((buckets, max(1, len(langs))))
    found = sample.mapInArrow(_counts(buckets, lengths), "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    got = found.toPandas()
    if len(got):
        counts[got["bucket"].to_numpy(), got["lang"].map(langs.index).to_numpy()] = got["n"].to_numpy()
    given = np.log(counts + smoothing) - np.log(counts.sum(0) + smoothing * buckets)
    weights = np.array([prior[x] for x in langs], float)
    return langs, given, np.log(weights / weights.sum()) if langs else np.zeros(1)


def _scored(model, lengths: tuple[int, ...]):
    langs, given, prior = model.value

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            known = np.array([bool(langs) and _has_letter(t) for t in texts], bool)
            total = np.tile(prior, (len(texts), 1))
            for lo in range(0, len(texts), 256):
                part = [t if k else "" for t, k in zip(texts[lo : lo + 256], known[lo : lo + 256], strict=True)]
                for owner, bucket in _ngrams(part, lengths, len(given)):
                    if len(owner):  # owners ascend, so a text's n-grams are one run
                        begin = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
                        total[lo + owner[begin]] += np.add.reduceat(given[bucket], begin, axis=0)
            best = total.argmax(1)
            p = 1 / np.exp(total - total.max(1, keepdims=True)).sum(1)
            out = {"r": batch.column("r"), "text": batch.column("text")}
            out["lang_pred"] = pa.array([langs[b] if k else UNKNOWN for b, k in zip(best.tolist(), known, strict=True)], pa.string())
            out["score"] = pa.array(np.where(known, p, 0.0))
            yield pa.RecordBatch.from_pydict(out)

    return run


def identified(rows: DataFrame, model: tuple, lengths: tuple[int, ...] = LENGTHS) -> DataFrame:
    """rows(text, ...) with lang_pred and score, the probability of that language given the whole text; columns of these names
    that rows have already are left out, and others come back as they are, every row once.

    A text that is null or has no letter is 'und' with score 0, as all are where nothing was learned. Ties go to the language
    that is first by name. The matrix is broadcast (its size is fixed by the fit); scoring is narrow. No rows give no rows.
    """
    sent = rows.sparkSession.sparkContext.broadcast((model[0], model[1].astype(np.float32), model[2]))
    kept = [c for c in rows.columns if c not in ("lang_pred", "score")]
    others = [F.col(f"`{c}`") for c in kept if c != "text"] or [F.lit(0).alias("none")]
    boxed = rows.select(F.struct(*others).alias("r"), "text")  # a text goes to Python once
    kinds = f"r {boxed.schema['r'].dataType.simpleString()}, text string, lang_pred string, score double"
    out = boxed.mapInArrow(giving_back(_scored(sent, lengths)), kinds)
    return out.select(*(F.col("text" if c == "text" else f"r.`{c}`") for c in kept), "lang_pred", "score")


def held_out():
    return F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    out = F.coalesce(held_out(), F.lit(False))
    model = fit(docs.where(~out))
    return identified(docs.select("doc_id", "text", out.alias("held_out")), model).select("doc_id", "held_out", "lang_pred", "score")
