import public_tokenizers
import pytest
from tokenizers import Tokenizer

pipeline = pytest.importorskip("corpus_pipeline")


from ptree_rules.llm.common import DOC_COLUMNS  # noqa: E402

from .test_exact_and_lines import SPACE, LOW  # noqa: E402
from .test_simhash_alike import brute as brute_groups  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_every_stage_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    stages = dict(pipeline.STAGES)
    assert 4 <= len(stages) <= 5
    at = {}
    for name, stage in pipeline.STAGES:
        at[name] = docs = stage(spark, docs, SF).cache()
        if name != "packing":
            assert tuple(docs.columns) == DOC_COLUMNS
    before = spark.read.parquet(f"{SF}/documents.parquet").collect()
    known = {r.doc_id for r in at["language ID"].collect()}
    assert known == {r.doc_id for r in before if r.text and any(map(str.isalpha, r.text))}
    rows = [r for r in before if r.doc_id in known]
    key = lambda x: x.strip(SPACE).translate(LOW)
    first = {}
    for r in rows:
        for x in r.text.split("\n"):
            first[key(x)] = min(r.doc_id, first.get(key(x), r.doc_id))
    text = {r.doc_id: "\n".join(x for x in r.text.split("\n") if len(key(x)) < 10 or first[key(x)] == r.doc_id) for r in rows}
    text = {i: t for i, t in text.items() if t.strip(SPACE)}
    assert {r.doc_id: r.text for r in at["line dedup"].collect()} == text
    true = dict(brute_groups(sorted(text.items())))
    lone = {r.doc_id for r in at["near-dedup"].collect()}
    assert {i for i, c in true.items() if i == c} <= lone and len(lone) <= 1.02 * len(set(true.values()))
    mixed = [r.doc_id for r in at["source mixing"].collect()]
    assert set(mixed) <= lone and len(mixed) == len(set(mixed))
    named = Tokenizer.from_file(str(public_tokenizers.path("byte_bpe_50k.json")))
    tokens = lambda ids: sum(len(named.encode(text[i], add_special_tokens=False).ids) for i in ids)
    assert 0.75 * tokens(lone) < tokens(mixed) <= 0.9 * tokens(lone)
    assert {r.doc_id for r in at["packing"].collect()} == set(mixed)


@pytest.mark.parametrize("stage", [f for _, f in pipeline.STAGES])
def test_stages_take_hard_input(spark, hard, none, stage):
    out = stage(spark, hard, SF)
    assert out.count() > 0
    assert stage(spark, none, SF).count() == 0
