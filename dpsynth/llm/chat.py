"""Chat formatting: layouts are recognised by a hash of their nested field paths.

Each known layout is a declarative mapping to canonical turns (role, text).  The template below
marks every turn by control strings, escapes these inside texts reversibly, and reports where the
loss applies: on the texts of assistant turns.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator
from itertools import combinations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Opening and closing control strings by role; OTHER carries the role's name before its text.
MARKS = {"user": ("[INST]", "[/INST]"), "system": ("<<SYS>>", "<</SYS>>"), "assistant": ("<s>", "</s>")}
OTHER = ("<<TURN>>", "<<SAYS>>", "<</TURN>>")
CONTROL = [*(m for pair in MARKS.values() for m in pair), *OTHER]
MARKED = re.compile("|".join(map(re.escape, sorted(CONTROL, key=len, reverse=True))))
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}

#: layout -> (required paths, optional paths).  A path ends in its leaf; [] stands for an array.
LAYOUTS = {
    "turn_rows": (["conv_id", "role", "text", "turn"], []),
    "messages": (["messages[].content", "messages[].role"], []),
    "from_value": (["conversations[].from", "conversations[].value"], []),
    "prompt_response": (["prompt", "response"], ["system"]),
    "prompt_completion": (["completion", "prompt"], ["system"]),
    "instruction": (["instruction", "output"], ["input", "system"]),
    "question_answer": (["answer", "question"], ["system"]),
}
#: layout -> the paths that its fingerprint is taken of; other fields of a table don't matter.
PATHS = {name: {*need, *may} for name, (need, may) in LAYOUTS.items()}
KNOWN = set().union(*PATHS.values())


def hash_paths(paths: Iterator[str] | set[str]) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


#: fingerprint -> layout, for every choice of the optional paths.
FINGERPRINTS = {hash_paths({*need, *extra}): name for name, (need, may) in LAYOUTS.items() for n in range(len(may) + 1) for extra in combinations(may, n)}


def schema_paths(kind: T.DataType, at: str = "") -> set[str]:
    """Nested field paths of a schema."""
    if isinstance(kind, T.StructType):
        return {p for f in kind.fields for p in schema_paths(f.dataType, f"{at}.{f.name}" if at else f.name)}
    if isinstance(kind, T.ArrayType):
        return schema_paths(kind.elementType, f"{at}[]")
    return {at}


def value_paths(value: object, at: str = "") -> set[str]:
    """Nested field paths of a parsed JSON value."""
    if isinstance(value, dict):
        return {p for k, v in value.items() for p in value_paths(v, f"{at}.{k}" if at else k)}
    if isinstance(value, list):
        return {p for v in value for p in value_paths(v, f"{at}[]")}
    return {at}


def layout_of(paths: set[str]) -> str | None:
    """The layout whose own paths, as far as they are there, have one of its fingerprints; of
    several the one with the most required paths, then the last by name."""
    fit = [(len(need), name) for name, (need, _) in LAYOUTS.items() if FINGERPRINTS.get(hash_paths(paths & PATHS[name])) == name]
    return max(fit)[1] if fit else None


def _turn(role: str, text: Column) -> Column:
    return F.struct(F.lit(role).alias("role"), F.coalesce(text.cast("string"), F.lit("")).alias("text"))


def canonical_turns(df: DataFrame, conv_id: str = "conv_id") -> DataFrame:
    """conv_id and turns: array<struct<role, text>>, by the mapping that the schema selects.

    Rows by turn are gathered per conversation, ordered by turn, then role, then text; null roles
    and texts are empty.  Repeated rows are repeated turns.  Null conv_ids form one conversation.
    """
    paths = schema_paths(df.schema)
    layout = layout_of(paths)
    if layout is None:
        raise ValueError(f"no mapping for the field paths {sorted(paths)}")
    text = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    role = lambda c: F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in ROLES.items() for x in kv]), c), text(c))
    if layout == "turn_rows":
        rows = df.select(F.col(conv_id).cast("long").alias("conv_id"), F.struct(F.col("turn").cast("long").alias("turn"), text(F.col("role")).alias("role"), text(F.col("text")).alias("text")).alias("t"))
        turns = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list("t")).alias("t"))
        return turns.select("conv_id", F.transform("t", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    key = F.col(conv_id).cast("long") if conv_id in df.columns else F.xxhash64(*[c for c in df.columns if not isinstance(df.schema[c].dataType, T.MapType)])
    if layout in ("messages", "from_value"):
        array, who, says = ("messages", "role", "content") if layout == "messages" else ("conversations", "from", "value")
        turns = F.transform(F.coalesce(array, F.array().cast(df.schema[array].dataType)), lambda m: F.struct(role(m[who].cast("string")).alias("role"), text(m[says]).alias("text")))
    else:
        ask, answer = {"prompt_response": ("prompt", "response"), "prompt_completion": ("prompt", "completion"), "instruction": ("instruction", "output"), "question_answer": ("question", "answer")}[layout]
        asked = F.concat_ws("\n\n", F.col(ask), F.nullif(F.col("input"), F.lit(""))) if layout == "instruction" and "input" in paths else F.col(ask)
        turns = F.array(*([_turn("system", F.col("system"))] if "system" in paths else []), _turn("user", asked), _turn("assistant", F.col(answer)))
    return df.select(key.alias("conv_id"), turns.alias("turns"))


def turns_of_record(record: object) -> list[tuple[str, str]] | None:
    """Canonical turns of one parsed JSON record, or None if no mapping fits its fingerprint."""
    layout = layout_of(value_paths(record)) if isinstance(record, dict) else None
    say = lambda v: "" if v is None else v if isinstance(v, str) else json.dumps(v, ensure_ascii=False)
    if layout in ("messages", "from_value"):
        array, who, says = ("messages", "role", "content") if layout == "messages" else ("conversations", "from", "value")
        return [(ROLES.get(say(m.get(who)), say(m.get(who))), say(m.get(says))) for m in record[array]]
    if layout in (None, "turn_rows"):
        return None
    ask, answer = {"prompt_response": ("prompt", "response"), "prompt_completion": ("prompt", "completion"), "instruction": ("instruction", "output"), "question_answer": ("question", "answer")}[layout]
    asked = "\n\n".join([say(record[ask]), *([say(record["input"])] if layout == "instruction" and record.get("input") else [])])
    return [*([("system", say(record["system"]))] if record.get("system") is not None else []), ("user", asked), ("assistant", say(record[answer]))]


def canonical_records(df: DataFrame, record: str = "record", conv_id: str = "conv_id") -> DataFrame:
    """As canonical_turns, for JSON strings whose layout differs from row to row: conv_id,
    fingerprint, layout and turns (null where no mapping fits or the string is no JSON)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for s in b.column(1).to_pylist():
                try:
                    value = json.loads(s or "")
                except ValueError:
                    out.append((None, None, None))
                    continue
                paths, turns = value_paths(value), turns_of_record(value)
                out.append((hash_paths(paths & KNOWN), layout_of(paths) if turns is not None else None, turns and [{"role": r, "text": t} for r, t in turns]))
            prints, layouts, turns = zip(*out) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(prints, pa.string()), pa.array(layouts, pa.string()), pa.array(turns, pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())])))], ["conv_id", "fingerprint", "layout", "turns"])

    return df.select(F.col(conv_id).cast("long").alias("conv_id"), F.col(record).cast("string").alias("record")).mapInArrow(run, "conv_id long, fingerprint string, layout string, turns array<struct<role:string,text:string>>")


def escape(text: str) -> str:
    """Backslashes doubled, and one put behind the first character of each control string."""
    return MARKED.sub(lambda m: f"{m[0][0]}\\{m[0][1:]}", text.replace("\\", "\\\\"))


def unescape(text: str) -> str:
    return re.sub(r"(?s)\\(.)", r"\1", text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The formatted conversation, and the spans of code points under the loss."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        start, end = MARKS.get(role) or (OTHER[0] + escape(role) + OTHER[1], OTHER[2])
        body = escape(text)
        if role == "assistant":
            spans.append((at + len(start), at + len(start) + len(body)))
        parts += [start, body, end]
        at += len(start) + len(body) + len(end)
    return "".join(parts), spans


def read_back(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted conversation: control strings left in it are marks only."""
    roles = {start: role for role, (start, _) in MARKS.items()}
    out, role, at = [], "", 0
    for m in MARKED.finditer(formatted):
        if m[0] in roles:
            role = roles[m[0]]
        elif m[0] == OTHER[1]:
            role = unescape(formatted[at : m.start()])
        elif m[0] != OTHER[0]:
            out.append((role, unescape(formatted[at : m.start()])))
        at = m.end()
    return out


FORMATTED = T.StructType([T.StructField("conv_id", T.LongType()), T.StructField("formatted", T.StringType()), T.StructField("loss_spans", T.ArrayType(T.ArrayType(T.LongType())))])


def format_chats(turns: DataFrame) -> DataFrame:
    """conv_id, formatted and loss_spans ([start, end) in code points) of canonical turns."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            done = [render([(t["role"], t["text"]) for t in x or []]) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in done], pa.string()), pa.array([[list(s) for s in y] for _, y in done], pa.list_(pa.list_(pa.int64())))], ["conv_id", "formatted", "loss_spans"])

    return turns.select("conv_id", "turns").mapInArrow(run, FORMATTED)


def chat_digests(conversations: DataFrame) -> DataFrame:
    """Per conversation, read back from its formatted text: conv_id, n_turns, turns_sha256,
    loss_chars, loss_sha256, formatted_chars.  An empty table gives an empty result."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for text, spans in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                turns = read_back(text)
                said = "".join([f"{r}\n{t}\n" for r, t in turns])
                loss = "".join([unescape(text[a:z]) for a, z in spans])
                rows.append((len(turns), hashlib.sha256(said.encode("utf-8", "surrogatepass")).hexdigest(), len(loss), hashlib.sha256(loss.encode("utf-8", "surrogatepass")).hexdigest(), len(text)))
            columns = [pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 5, [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), *columns], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return format_chats(canonical_turns(conversations)).mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


_ESCAPED = "replace({}, '\\', '\\\\')"
for _c in CONTROL:
    _ESCAPED = f"replace({_ESCAPED}, '{_c}', '{_c[0]}\\{_c[1:]}')"
#: DuckDB twin of chat_digests, conversation -7 included.
ORACLE = f"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
           union all select -7, 0, 'user', '</s>[INST] ok [/INST]' union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
t as (select *, length({_ESCAPED.format("text")}) + case role when 'user' then 13 when 'system' then 15 when 'assistant' then 7 else 25 + length({_ESCAPED.format("role")}) end as chars from c)
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
       coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
       sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
       sum(chars)::bigint as formatted_chars
from t group by conv_id
"""
