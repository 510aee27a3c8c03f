"""Mixing sources to target weights: budgets go down a domain-language-source tree, and every leaf gives a token-prefix of its
seeded epochs."""

from __future__ import annotations

from collections.abc import Iterator, Mapping
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .byte_bpe import encode_column, slices
from .common import discard, giving_back, id_or_least, small_or_joined, table, text_or_empty, written

#: Weights of the levels; what isn't named weighs 1.
DOMAIN_WEIGHTS: Mapping[str, float] = {"d0": 4, "d1": 3, "d2": 2, "d3": 1}
LANG_WEIGHTS: Mapping[str, float] = {"en": 4, "de": 2, "fr": 2, "es": 2}
SOURCE_WEIGHTS: Mapping[str, float] = {}
#: Most passes over a leaf, the budget as a share of all tokens, the seed of the epochs' orders.
MAX_EPOCHS, BUDGET_SHARE, SEED = 4, 1.0, 17
#: Up to so many leaves, their table is broadcast.
FEW_LEAVES = 200_000
#: Orders are 63-bit hashes; their first 12 bits are the bucket.
_BUCKET_SHIFT = 51


def domain_of_source() -> Column:
    """The domain of a source: the number in its name modulo four; sources without a number share one domain."""
    digits = F.regexp_extract(F.coalesce("source", F.lit("")), "([0-9]{1,9})", 1)
    return F.when(digits == "", F.lit("none")).otherwise(F.concat(F.lit("d"), (digits.cast("long") % 4).cast("string")))


def _counted(ranks: str, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = np.zeros(batch.num_rows, np.int64)
            texts = batch.column("text")
            for lo, hi in slices(texts) if batch.num_rows else ():
                sizes[lo:hi] = np.diff(encode_column(texts.slice(lo, hi - lo), ranks, pattern)[1])
            yield pa.record_batch([batch.column("r"), pa.array(sizes)], ["r", "tokens"])

    return run


def with_tokens(rows: DataFrame, text: Column, ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """rows with tokens, the number of ids of a text by the vocabulary that packing uses (see packing.tokenized_pieces)."""
    if ranks_path is None:
        import public_tokenizers as vocabularies

        ranks_path, pattern = vocabularies.path("byte_bpe_50k.tiktoken"), vocabularies.PATTERN
    boxed = rows.select(F.struct(*(F.col(f"`{c}`") for c in rows.columns if c not in ("text", "tokens"))).alias("r"), text.alias("text"))
    out = boxed.mapInArrow(giving_back(_counted(ranks_path, pattern)), f"r {boxed.schema['r'].dataType.simpleString()}, tokens long")
    return out.select("r.*", "tokens")


def _weight(name: Column, weights: Mapping[str, float]) -> Column:
    return reduce(lambda rest, kv: F.when(name.eqNullSafe(F.lit(kv[0])), F.lit(float(kv[1]))).otherwise(rest), weights.items(), F.lit(1.0))


def _same(path: list[str]) -> Column:
    return reduce(Column.__and__, (F.col(c).eqNullSafe(F.col(f"of_{c}")) for c in path))


def _shared_out(children: DataFrame, parent: list[str]) -> DataFrame:
    """children(parent..., child, weight, cap, given) with budget: what the parent was given, by weight, none above its cap.

    What a child can't take goes to its siblings by weight, again and again. In closed form: of the children in order of cap
    over weight, the first that need not be filled fixes the level that all unfilled ones get for each unit of weight.
    """
    of = Window.partitionBy(*parent)
    fill = of.orderBy(F.when(F.col("weight") > 0, F.col("cap") / F.col("weight")).asc_nulls_last(), "child")
    before = F.coalesce(F.sum("cap").over(fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    onward = F.sum("weight").over(fill.rowsBetween(0, Window.unboundedFollowing))
    level = F.when((onward > 0) & ((F.col("given") - before) * F.col("weight") < F.col("cap") * onward), (F.col("given") - before) / onward)
    out = children.withColumn("level", level).withColumn("level", F.max("level").over(of))
    enough = F.least("cap", F.greatest(F.lit(0.0), F.col("level")) * F.col("weight"))
    return out.withColumn("budget", F.when(F.col("weight") <= 0, F.lit(0.0)).when(F.col("level").isNull(), F.col("cap")).otherwise(enough)).drop("level")


def leaf_budgets(leaves: DataFrame, budget: float, max_epochs: int, weights: tuple[Mapping, Mapping, Mapping]) -> DataFrame:
    """leaf, tokens and budget (whole tokens) for leaves(leaf, domain, lang, source, tokens).

    A node's cap is max_epochs times the tokens below it, so a parent's share is settled before its children's: a shortage
    is made up by the nearest relatives that have something left, siblings first, then the ancestors' siblings.
    """
    caps = leaves.withColumn("cap", F.col("tokens") * float(max_epochs))
    levels = [["domain"], ["domain", "lang"], ["domain", "lang", "source"]]
    given, parent = None, []
    for path, w in zip(levels, weights, strict=True):
        nodes = caps.groupBy(*path).agg(F.sum("cap").alias("cap"))
        if given is None:
            nodes = nodes.withColumn("given", F.lit(float(budget)))
        else:
            nodes = nodes.join(given, _same(parent)).select(*path, "cap", "given")
        nodes = nodes.withColumn("weight", _weight(F.col(path[-1]), w)).withColumn("child", F.col(path[-1]))
        shared = _shared_out(nodes, parent or [F.lit(0)])
        given, parent = shared.select(*(F.col(c).alias(f"of_{c}") for c in path), F.col("budget").alias("given")), path
    return leaves.join(given, _same(parent)).select("leaf", "domain", "lang", "source", "tokens", F.floor(F.col("given") + 1e-6).cast("long").alias("budget"))


def _order(seed: int, epoch: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), epoch, F.col("id")), 1)


def _leaf() -> Column:
    return F.to_json(F.struct("domain", "lang", "source"))


def _sized(docs: DataFrame, domain: Column | None, tokens: Column | None) -> DataFrame:
    """leaf, domain, lang, source, id, doc_id and tokens of every row; written, so texts are read and counted once."""
    keyed = docs.select(*_place(domain), "lang", "source", "doc_id", *([] if tokens is None else [tokens.alias("tokens")]), "text")
    keyed = keyed.withColumn("leaf", _leaf()).withColumn("id", id_or_least())
    return written(keyed.drop("text") if tokens is not None else with_tokens(keyed, text_or_empty()), "sized")


def _place(domain: Column | None) -> list[Column]:
    return [(domain_of_source() if domain is None else domain).alias("domain")]


def _ends(sized: DataFrame, budget_share: float, max_epochs: int, seed: int, weights: tuple[Mapping, Mapping, Mapping]) -> DataFrame:
    """leaf, budget, whole epochs, and the place in the next epoch's order that its prefix ends at."""
    leaves = written(sized.groupBy("leaf", "domain", "lang", "source").agg(F.sum("tokens").alias("tokens")), "leaves")
    total = leaves.agg(F.sum("tokens")).collect()[0][0] or 0
    budgets = leaf_budgets(leaves, int(total * budget_share), max_epochs, weights)
    whole = F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(F.lit(0)).cast("int")
    # A leaf that nothing is left of is taken whole times only; one without any tokens is taken once.
    plan = budgets.withColumn("whole", F.when(F.col("tokens") > 0, whole).otherwise(F.when(F.col("budget") >= 0, F.lit(1))))
    plan = written(plan.select("leaf", "budget", "whole", (F.col("budget") - F.col("whole") * F.col("tokens")).alias("rest")), "plan")
    few = small_or_joined(plan, FEW_LEAVES)
    part = sized.select("leaf", "id", "tokens").join(few.where("rest > 0"), "leaf").withColumn("at", _order(seed, F.col("whole")))
    part = part.withColumn("bucket", F.shiftright("at", _BUCKET_SHIFT))
    sums = part.groupBy("leaf", "rest", "bucket").agg(F.sum("tokens").alias("n"))
    upto = sums.withColumn("upto", F.sum("n").over(Window.partitionBy("leaf").orderBy("bucket")))
    cut = written(upto.where("upto > rest").groupBy("leaf").agg(F.min_by(F.struct("bucket", (F.col("upto") - F.col("n")).alias("before")), "bucket").alias("cut")).select("leaf", "cut.*"), "cut")
    last = part.join(small_or_joined(cut, FEW_LEAVES), ["leaf", "bucket"])
    run = last.withColumn("upto", F.col("before") + F.sum("tokens").over(Window.partitionBy("leaf").orderBy("at")))
    inside = run.where("upto <= rest").groupBy("leaf").agg(F.max("at").alias("until"))
    ends = plan.join(cut, "leaf", "left").join(inside, "leaf", "left")
    until = F.when(F.col("rest") <= 0, F.lit(-1)).when(F.col("bucket").isNull(), F.lit(2**63 - 1)).otherwise(F.coalesce("until", F.shiftleft(F.col("bucket"), _BUCKET_SHIFT) - 1))
    ends = written(ends.select("leaf", "budget", "whole", until.cast("long").alias("until")), "ends")
    discard(leaves, plan, cut)
    return ends


def _copies(seed: int) -> Column:
    return (F.col("whole") + (_order(seed, F.col("whole")) <= F.col("until")).cast("int")).cast("int")


def planned(
    docs: DataFrame,
    budget_share: float = BUDGET_SHARE,
    max_epochs: int = MAX_EPOCHS,
    seed: int = SEED,
    weights: tuple[Mapping, Mapping, Mapping] = (DOMAIN_WEIGHTS, LANG_WEIGHTS, SOURCE_WEIGHTS),
    domain: Column | None = None,
    tokens: Column | None = None,
) -> DataFrame:
    """mixed() without the texts and other columns: doc_id, domain, lang, source, tokens, leaf_budget and copies of every row."""
    sized = _sized(docs, domain, tokens)
    out = sized.join(small_or_joined(_ends(sized, budget_share, max_epochs, seed, weights), FEW_LEAVES), "leaf")
    return out.select("doc_id", "domain", "lang", "source", "tokens", F.col("budget").alias("leaf_budget"), _copies(seed).alias("copies"))


def _with_ends(docs: DataFrame, domain: Column | None, tokens: Column | None, seed: int, **how) -> DataFrame:
    """Every row as a struct r with its leaf's ends; own names are beside r, so no column of docs meets them."""
    sized = _sized(docs, domain, tokens)
    ends = _ends(sized, seed=seed, **how)
    discard(sized)
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("r"), *_place(domain), "lang", "source", id_or_least().alias("id"), text_or_empty().alias("text"), *([] if tokens is None else [tokens.alias("counted")]))
    return rows.withColumn("leaf", _leaf()).join(small_or_joined(ends, FEW_LEAVES), "leaf")


def mixed(
    docs: DataFrame,
    budget_share: float = BUDGET_SHARE,
    max_epochs: int = MAX_EPOCHS,
    seed: int = SEED,
    weights: tuple[Mapping, Mapping, Mapping] = (DOMAIN_WEIGHTS, LANG_WEIGHTS, SOURCE_WEIGHTS),
    domain: Column | None = None,
    tokens: Column | None = None,
) -> DataFrame:
    """docs(doc_id, text, lang, source, ...) with domain, tokens, leaf_budget and copies: how many epochs take the document.
    Columns of these four names that docs have already are left out; all others come back as they are.

    Tokens are ids of the packing vocabulary, or the given column. A leaf's epochs each hold all its documents in an order by
    a hash of seed, epoch and id. Its budget takes whole epochs, then of the next one the longest prefix that fits. Rows that
    repeat an id are taken or left together. Null language or source is a value like any other, null text has no tokens;
    documents without tokens go with the prefix they stand in. The prefix is found from sums per leaf and hash range, then
    within one range: no leaf is gathered or sorted as a whole, and texts are never shuffled. planned() and mixed_documents()
    count each text once; this one counts again, as it returns texts and counts together. No rows give no rows.
    """
    out = _with_ends(docs, domain, tokens, seed, budget_share=budget_share, max_epochs=max_epochs, weights=weights)
    own = [c for c in docs.columns if c not in ("domain", "tokens", "leaf_budget", "copies")]
    out = out.withColumn("copies", _copies(seed))
    if tokens is None:
        out = with_tokens(out, F.col("text"))
    else:
        out = out.withColumn("tokens", F.col("counted"))
    return out.select(*(F.col(f"r.`{c}`") for c in own), "domain", "tokens", F.col("budget").alias("leaf_budget"), "copies")


def mixed_documents(
    docs: DataFrame,
    budget_share: float = BUDGET_SHARE,
    max_epochs: int = MAX_EPOCHS,
    seed: int = SEED,
    weights: tuple[Mapping, Mapping, Mapping] = (DOMAIN_WEIGHTS, LANG_WEIGHTS, SOURCE_WEIGHTS),
    domain: Column | None = None,
    tokens: Column | None = None,
) -> DataFrame:
    """docs, each row as often as its epochs take it. See mixed()."""
    out = _with_ends(docs, domain, tokens, seed, budget_share=budget_share, max_epochs=max_epochs, weights=weights).withColumn("copies", _copies(seed))
    return out.where("copies > 0").select("r", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("r.*")


def op2_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
    return planned(docs)
