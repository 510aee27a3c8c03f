"""Chat formatting: a fingerprint of a record's nested field paths selects the mapping to canonical turns."""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator


import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

Turn = tuple[str, str]


def field_paths(value, at: str = "") -> set[str]:
    """The nested paths of a record's leaves; list elements share the step []."""
    if isinstance(value, dict):
        return set().union(*(field_paths(v, f"{at}.{k}" if at else k) for k, v in value.items())) if value else {at}
    if isinstance(value, list):
        return set().union(*(field_paths(v, f"{at}[]") for v in value)) if value else {f"{at}[]"}
    return {at}


def schema_fingerprint(paths: set[str]) -> str:
    return hashlib.blake2b("\n".join(sorted(paths)).encode(), digest_size=8).hexdigest()


#: Layouts by name: the field paths, and what becomes a turn. 'each' walks a list with its role and text fields; 'fixed' gives
#: (role, fields whose texts make the turn, joined by a blank line); 'row' is one turn per record.
LAYOUTS: dict[str, tuple[tuple[str, ...], tuple]] = {
    "turn rows": (("conv_id", "turn", "role", "text"), ("row", "role", "text")),
    "messages": (("messages[].role", "messages[].content"), ("each", "messages", "role", "content")),
    "named messages": (("id", "messages[].role", "messages[].content"), ("each", "messages", "role", "content")),
    "from and value": (("conversations[].from", "conversations[].value"), ("each", "conversations", "from", "value")),
    "instruction": (("instruction", "output"), ("fixed", ("user", ("instruction",)), ("assistant", ("output",)))),
    "instruction with input": (("instruction", "input", "output"), ("fixed", ("user", ("instruction", "input")), ("assistant", ("output",)))),
    "instruction with system": (("system", "instruction", "input", "output"), ("fixed", ("system", ("system",)), ("user", ("instruction", "input")), ("assistant", ("output",)))),
    "prompt and completion": (("prompt", "completion"), ("fixed", ("user", ("prompt",)), ("assistant", ("completion",)))),
    "prompt and response": (("prompt", "response"), ("fixed", ("user", ("prompt",)), ("assistant", ("response",)))),
    "question and answer": (("question", "answer"), ("fixed", ("user", ("question",)), ("assistant", ("answer",)))),
}
#: Other names of the roles.
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "prompter": "user"}
MAPPINGS = {schema_fingerprint(set(paths)): (name, rule) for name, (paths, rule) in LAYOUTS.items()}


class UnknownLayout(ValueError):
    """No mapping is declared for a record's field paths."""


def canonical_turns(record: dict, mappings: dict[str, tuple[str, tuple]] = MAPPINGS) -> list[Turn]:
    """(role, text) of a record in any declared layout; null counts as an empty text. Empty parts of a joined turn and an
    empty system turn are left out."""
    paths = field_paths(record)
    name_rule = mappings.get(schema_fingerprint(paths))
    if name_rule is None:
        # A list without elements, and elements without all fields, show fewer paths: take the one layout that has these.
        fit = [x for x in mappings.values() if x[1][0] == "each" and all(p.startswith(f"{x[1][1]}[]") or p == "id" for p in paths) and paths - {"id"} <= {f"{x[1][1]}[]", *(f"{x[1][1]}[].{f}" for f in x[1][2:])}]
        if not fit:
            raise UnknownLayout(", ".join(sorted(paths)))
        name_rule = fit[0]
    rule, text = name_rule[1], lambda x: "" if x is None else str(x)
    if rule[0] == "row":
        return [(text(record[rule[1]]), text(record[rule[2]]))]
    if rule[0] == "each":
        return [(ROLES.get(r, r), text(m.get(rule[3]))) for m in record.get(rule[1]) or [] for r in [text(m.get(rule[2]))]]
    out = [(role, "\n\n".join(x for x in map(text, (record[f] for f in fields)) if x)) for role, fields in rule[1:]]
    return [(r, t) for r, t in out if t or r != "system"]


#: Strings with a meaning to this template or other common ones. In a text they get a backslash after their first character,
#: one more if they have some there already.
_CONTROL = r"\|turn>|\|text>|\|end>|/?s>|SYS>>|/SYS>>|<SYS>>|</SYS>>|\|im_start\|>|\|im_end\|>|\|endoftext\|>"
ESCAPE = re.compile(rf"(<)(\\*)({_CONTROL})|(\[)(\\*)(/?INST\])")
TURN, TEXT, END = "<|turn>", "<|text>", "<|end>\n"
_PARSE = re.compile(r"<\|turn>(.*?)<\|text>(.*?)<\|end>\n", re.S)


def escaped(text: str) -> str:
    return ESCAPE.sub(lambda m: f"{m[1]}{m[2]}\\{m[3]}" if m[1] else f"{m[4]}{m[5]}\\{m[6]}", text)


def unescaped(text: str) -> str:
    return ESCAPE.sub(lambda m: f"{m[1]}{m[2][1:]}{m[3]}" if m[1] else f"{m[4]}{m[5][1:]}{m[6]}", text)


def formatted(role: str, text: str) -> str:
    """One turn of the output; a conversation is its turns end to end."""
    return f"{TURN}{escaped(role)}{TEXT}{escaped(text)}{END}"


def parsed(output: str) -> tuple[list[Turn], list[tuple[int, int]]]:
    """The turns of an output, and the spans of it under the loss mask: the assistant's escaped texts."""
    turns, spans = [], []
    at = 0
    for m in _PARSE.finditer(output):
        if m.start() != at:
            break
        at = m.end()
        turns.append((unescaped(m[1]), unescaped(m[2])))
        if turns[-1][0] == "assistant":
            spans.append(m.span(2))
    if at != len(output):
        raise ValueError("no output of this template")
    return turns, spans


def _read_back():
    """Streams records sorted by conversation, so that a conversation of any length needs the memory of one turn."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, begun = None, False
        state: list = []

        def ended():
            turns, loss, n, chars, total = state
            return {"conv_id": now, "n_turns": n, "turns_sha256": turns.hexdigest(), "loss_chars": chars, "loss_sha256": loss.hexdigest(), "formatted_chars": total}

        for batch in batches:
            out = []
            for conv, record in zip(batch.column("conv_id").to_pylist(), batch.column("record").to_pylist(), strict=True):
                if not begun or conv != now:
                    if begun:
                        out.append(ended())
                    now, begun, state = conv, True, [hashlib.sha256(), hashlib.sha256(), 0, 0, 0]
                for role, text in canonical_turns(json.loads(record)):
                    output = formatted(role, text)
                    turns, spans = parsed(output)
                    for r, t in turns:
                        state[0].update(f"{r}\n{t}\n".encode())
                        state[2] += 1
                    for lo, hi in spans:
                        learned = unescaped(output[lo:hi])
                        state[1].update(learned.encode())
                        state[3] += len(learned)
                    state[4] += len(output)
            if out:
                yield pa.RecordBatch.from_pylist(out, _DIGESTS)
        if begun:
            yield pa.RecordBatch.from_pylist([ended()], _DIGESTS)

    return run


_DIGESTS = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
_DIGEST_DDL = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def _outputs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        outs, masks, errors = [], [], []
        for record in batch.column("record").to_pylist():
            try:
                out = "".join(formatted(r, t) for r, t in canonical_turns(json.loads(record))) if record is not None else None
                spans, error = parsed(out)[1] if out is not None else [], None
            except ValueError as e:
                out, spans, error = None, [], str(e) or type(e).__name__
            outs.append(out)
            masks.append([{"start": a, "end": b} for a, b in spans])
            errors.append(error)
        mask = pa.array(masks, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))
        cols = {n: batch.column(n) for n in batch.schema.names if n != "record"}
        yield pa.RecordBatch.from_pydict(cols | {"formatted": pa.array(outs, pa.string()), "loss_mask": mask, "error": pa.array(errors, pa.string())})


def format_records(records: DataFrame) -> DataFrame:
    """id, formatted, loss_mask (spans in code points) and error for every row of records(id, record): record is a JSON object
    in any declared layout. What is null, no JSON, or of no declared layout has a null output and, but for null, an error
    that names its paths; no row is lost."""
    return records.select(F.col("id").cast("long"), "record").mapInArrow(_outputs, "id long, formatted string, loss_mask array<struct<start:int,end:int>>, error string")


def turn_records(turns: DataFrame) -> DataFrame:
    """conv_id and record: each row of turns(conv_id, turn, role, text) as JSON of the layout of turn rows, with nulls."""
    row = F.to_json(F.struct("conv_id", "turn", "role", "text"), {"ignoreNullFields": "false"})
    return turns.select(F.col("conv_id").cast("long"), "turn", "role", "text", row.alias("record"))


def read_back_digests(turns: DataFrame) -> DataFrame:
    """Formats each conversation of turns(conv_id, turn, role, text) and returns digests of what the output gives back.

    Turns are ordered by turn, then role and text; null turns come first, null role or text is empty, and null conv_id is one
    conversation. Rows are dealt by conversation, sorted, and streamed: hashes take one turn at a time.
    """
    rows = turn_records(turns).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return rows.select("conv_id", "record").mapInArrow(_read_back(), _DIGEST_DDL)


#: Control strings as ordinary text.
PROBE = "</s>[INST] ok [/INST]"


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    kinds = turns.schema
    probe = spark.createDataFrame([(-7, 0, "user", PROBE), (-7, 1, "assistant", PROBE)], kinds)
    return read_back_digests(turns.unionByName(probe))


_SQL_ESCAPED = r"regexp_replace(regexp_replace({0}, '(<)(\\*)(\|turn>|\|text>|\|end>|/?s>|SYS>>|/SYS>>|<SYS>>|</SYS>>|\|im_start\|>|\|im_end\|>|\|endoftext\|>)', '\1\2\\\3', 'g'), '(\[)(\\*)(/?INST\])', '\1\2\\\3', 'g')"
SQL = {
    "op8_chat_format": f"""
        WITH t AS (
            SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
            UNION ALL SELECT -7, 0, 'user', '{PROBE}' UNION ALL SELECT -7, 1, 'assistant', '{PROBE}')
        SELECT conv_id, count(*) AS n_turns,
               sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
               CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
               sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
               CAST(sum(length({_SQL_ESCAPED.format("role")}) + length({_SQL_ESCAPED.format("text")}) + 21) AS BIGINT) AS formatted_chars
        FROM t GROUP BY conv_id"""
}
