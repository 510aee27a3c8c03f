import json

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ptree_rules.llm.chat_format import PROBE, canonical_turns, UnknownLayout, field_paths, format_records, formatted, parsed, read_back_digests, schema_fingerprint

BITS = ["<", "\\", "|turn>", "|text>", "|end>\n", "</s>", "[INST]", "[", "/INST]", "<<SYS>>", "<</SYS>>", "a", "|im_end|>", "SYS>>", "s>", "\n", "é"]


@settings(max_examples=800, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "<|text>", ""]), st.lists(st.sampled_from(BITS), max_size=9).map("".join)), max_size=4))
def test_round_trip(turns):
    out = "".join(formatted(r, t) for r, t in turns)
    back, spans = parsed(out)
    assert back == turns
    assert len(spans) == sum(r == "assistant" for r, _ in turns)


def test_control_strings_never_stand_in_a_text():
    body = formatted("user", PROBE)[len("<|turn>") :]
    assert "</s>" not in body and "[INST]" not in body and "[/INST]" not in body


LAYOUTS = [
    {"messages": [{"role": "user", "content": "q"}, {"role": "assistant", "content": "a"}]},
    {"conversations": [{"from": "human", "value": "q"}, {"from": "gpt", "value": "a"}]},
    {"instruction": "q", "output": "a"},
    {"instruction": "q", "input": "", "output": "a"},
    {"prompt": "q", "completion": "a"},
    {"prompt": "q", "response": "a"},
    {"question": "q", "answer": "a"},
]


@pytest.mark.parametrize("record", LAYOUTS)
def test_layouts_meet_in_the_same_turns(record):
    assert canonical_turns(record) == [("user", "q"), ("assistant", "a")]


def test_fingerprint_sees_paths_only():
    one, two = ({"messages": [{"content": x, "role": x}] * n} for x, n in (("a", 1), ("b", 3)))
    assert schema_fingerprint(field_paths(one)) == schema_fingerprint(field_paths(two))
    with pytest.raises(UnknownLayout):
        canonical_turns({"other": {"deep": 1}})


def test_records_keep_every_row(spark):
    rows = [(i, json.dumps(r)) for i, r in enumerate([*LAYOUTS, {"messages": []}, {"odd": 1}])] + [(90, None), (91, "no json")]
    got = {r.id: r for r in format_records(spark.createDataFrame([(*r, 0) for r in rows], "id long, record string, error int")).collect()}
    assert len(got) == len(rows)
    assert len({got[i].formatted for i in range(7)}) == 1
    at = got[0].loss_mask[0]
    assert got[0].formatted[at.start : at.end] == "a"
    assert got[7].formatted == "" and got[8].error == "odd" and got[90].error is None and got[91].error


def test_conversations(spark):
    kind = "conv_id long, turn long, role string, text string, record int"
    rows = [(1, 1, "assistant", "x[INST]"), (1, 0, "user", None), (1, 1, "assistant", "x[INST]"), (2, None, None, "t"), (None, 0, "assistant", "</s>" * 50000)]
    got = {r.conv_id: r for r in read_back_digests(spark.createDataFrame([(*r, 1) for r in rows], kind).repartition(3)).collect()}
    assert got[1].n_turns == 3 and got[1].loss_chars == 14 and got[2].loss_chars == 0 and got[None].loss_chars == 200000
    assert read_back_digests(spark.createDataFrame([], kind)).count() == 0
