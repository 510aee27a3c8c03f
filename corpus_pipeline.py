"""A corpus from raw documents to packed sequences: language ID, line dedup, near-dedup, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ptree_rules.llm import language_id, line_dedup, mixing, packing, simhash_alike
from ptree_rules.llm.common import DOC_COLUMNS, discard, written

#: The language stage rejects what has no letter, and what the model gives a lower probability than this.
LEAST_SCORE = 0.5
#: The mix takes this share of all tokens, each document at most once.
MIX_SHARE, MIX_EPOCHS = 0.9, 1


def keep_known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the model tells; lang becomes the predicted one where it is null."""
    docs = docs.select(*DOC_COLUMNS)
    model = language_id.fit(docs)
    told = language_id.identified(docs, model).where((F.col("lang_pred") != language_id.UNKNOWN) & (F.col("score") >= LEAST_SCORE))
    return told.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*DOC_COLUMNS)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that a document of a smaller id has too; what has no word left goes."""
    out = line_dedup.drop_repeated_lines(docs.select(*DOC_COLUMNS))
    return out.where(F.col("text").rlike(r"[^\x20\x09-\x0D]"))


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The least doc_id of every group of near copies: five-word shingles of a similarity of 0.8 or more."""
    return simhash_alike.one_of_each_group(docs.select(*DOC_COLUMNS))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs.select(*DOC_COLUMNS), budget_share=MIX_SHARE, max_epochs=MIX_EPOCHS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(packing.tokenized_pieces(docs.select("doc_id", "text")))


STAGES = [
    ("language ID", keep_known_language),
    ("line dedup", drop_repeated_lines),
    ("near-dedup", keep_one_of_near_copies),
    ("source mixing", mix_sources),
    ("packing", pack),
]
#: Sets of shingles, the language model and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            out = written(out, name.replace(" ", "-"))
        if i:  # the stage's input is read no more: the last one too has written its pieces by now
            discard(docs)
        docs = out
    return docs
