"""Chat formatting: schema fingerprints pick a declarative mapping from a record layout to canonical turns.

A fingerprint is a hash over the sorted nested field paths of a record. ``LAYOUTS`` holds, for each known layout,
the paths it has and how they become (role, text) turns. ``canonicalise`` picks one mapping for a typed
DataFrame, ``canonicalise_json`` one for each JSON record. ``render`` writes turns with a template whose control
strings cannot occur unescaped inside texts, and ``read_back`` parses the output to turns and loss text.

Defined results: null roles and texts are empty strings; turns with equal numbers come in order of role, then
text; null turn numbers come first; repeated rows stay; a record of unknown layout keeps its row, with no turns;
texts are read and written whole, whatever their length (a conversation is one record, and so in one place); an empty
table gives an empty result; columns other than the mapped ones are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import arrow

TURNS = "array<struct<role:string,text:string>>"


@dataclass(frozen=True)
class Layout:
    """``paths``: the nested field paths. ``items``: path of the list of messages with its role and text fields,
    or ``fixed``: (role, fields joined by a blank line) for layouts with a field for each turn."""

    name: str
    paths: tuple[str, ...]
    items: tuple[str, str, str] | None = None
    fixed: tuple[tuple[str, tuple[str, ...]], ...] = ()
    dialect: bool = False

    @property
    def fingerprint(self) -> str:
        return fingerprint(self.paths)


def fingerprint(paths) -> str:
    """Hash of a set of nested field paths, whatever their order."""
    return hashlib.sha256("\n".join(sorted(set(paths))).encode()).hexdigest()[:16]


#: Role names of layouts that have a dialect of their own (``dialect``), by canonical role; others keep theirs.
ROLES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}
LAYOUTS = (
    Layout("messages", ("messages", "messages[].role", "messages[].content"), items=("messages", "role", "content")),
    Layout("conversations", ("conversations", "conversations[].from", "conversations[].value"), items=("conversations", "from", "value"), dialect=True),
    Layout("prompt_response", ("prompt", "response"), fixed=(("user", ("prompt",)), ("assistant", ("response",)))),
    Layout("prompt_completion", ("prompt", "completion"), fixed=(("user", ("prompt",)), ("assistant", ("completion",)))),
    Layout("question_answer", ("question", "answer"), fixed=(("user", ("question",)), ("assistant", ("answer",)))),
    Layout("instruction", ("instruction", "output"), fixed=(("user", ("instruction",)), ("assistant", ("output",)))),
    Layout("instruction_input", ("instruction", "input", "output"), fixed=(("user", ("instruction", "input")), ("assistant", ("output",)))),
    Layout("system_prompt", ("system", "prompt", "response"), fixed=(("system", ("system",)), ("user", ("prompt",)), ("assistant", ("response",)))),
)
BY_FINGERPRINT = {x.fingerprint: x for x in LAYOUTS}


def schema_paths(kind: T.DataType, at: str = "") -> set[str]:
    """Nested field paths of a Spark type; ``[]`` steps into a list."""
    if isinstance(kind, T.StructType):
        out = set()
        for f in kind.fields:
            path = f"{at}.{f.name}" if at else f.name
            out |= {path} | schema_paths(f.dataType, path)
        return out
    return schema_paths(kind.elementType, f"{at}[]") if isinstance(kind, T.ArrayType) else set()


def value_paths(value, at: str = "") -> set[str]:
    """Nested field paths of a parsed JSON value."""
    if isinstance(value, dict):
        out = set()
        for k, v in value.items():
            path = f"{at}.{k}" if at else k
            out |= {path} | value_paths(v, path)
        return out
    if isinstance(value, list):
        return set().union(*[value_paths(v, f"{at}[]") for v in value])
    return set()


def canonicalise(df: DataFrame, id_col: str) -> DataFrame:
    """``df`` with a ``turns`` column for the layout that its schema, without ``id_col``, has."""
    paths = schema_paths(T.StructType([f for f in df.schema.fields if f.name != id_col]))
    layout = BY_FINGERPRINT.get(fingerprint(paths))
    if layout is None:
        raise ValueError(f"no layout has the fields {sorted(paths)}")
    text = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    canonical = lambda c: c if not layout.dialect else F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in ROLES.items() for x in kv]), c), c)
    if layout.items:
        at, role, body = layout.items
        turns = F.transform(F.coalesce(F.col(at), F.array().cast(df.schema[at].dataType)), lambda m: F.struct(canonical(text(m[role])).alias("role"), text(m[body]).alias("text")))
    else:
        turns = F.array(*[F.struct(F.lit(r).alias("role"), F.array_join(F.filter(F.array(*[text(F.col(f)) for f in fields]), lambda x, i: (i == 0) | (x != "")), "\n\n").alias("text")) for r, fields in layout.fixed])
    return df.select(F.col(id_col), F.lit(layout.name).alias("layout"), turns.cast(TURNS).alias("turns"))


def turns_of(record) -> tuple[str | None, list[dict]]:
    """Layout name and turns of one parsed JSON record; no name and no turns where no layout fits."""
    layout = BY_FINGERPRINT.get(fingerprint(value_paths(record)))
    if layout is None:
        return None, []
    say = lambda v: "" if v is None else v if isinstance(v, str) else json.dumps(v, ensure_ascii=False)
    if layout.items:
        at, role, body = layout.items
        names = ROLES if layout.dialect else {}
        return layout.name, [{"role": names.get(say(m.get(role)), say(m.get(role))), "text": say(m.get(body))} for m in record[at]]
    return layout.name, [{"role": r, "text": "\n\n".join(x for i, x in enumerate(say(record.get(f)) for f in fields) if x or not i)} for r, fields in layout.fixed]


def canonicalise_json(df: DataFrame, id_col: str, json_col: str) -> DataFrame:
    """id, layout and turns of JSON records of mixed layouts; each record's own fingerprint picks its mapping.

    Records that don't parse or fit no layout stay, with a null layout and no turns.
    """
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, turns = [], []
            for x in b.column(1).to_pylist():
                try:
                    name, said = turns_of(json.loads(x or ""))
                except (ValueError, AttributeError, TypeError):
                    name, said = None, []
                names.append(name)
                turns.append(said)
            kinds = pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.string()), pa.array(turns, kinds)], names=[id_col, "layout", "turns"])

    return arrow(df.select(id_col, json_col), run, f"{id_col} {kind}, layout string, turns {TURNS}")


def from_turn_rows(rows: DataFrame, id_col: str = "conv_id", order_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One record for each conversation from a row for each turn: id and ``messages``."""
    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    one = F.struct(F.col(order_col).alias("o"), text(role_col).alias("role"), text(text_col).alias("content"))
    got = rows.groupBy(F.col(id_col)).agg(F.sort_array(F.collect_list(one)).alias("m"))
    return got.select(id_col, F.transform("m", lambda m: F.struct(m["role"].alias("role"), m["content"].alias("content"))).alias("messages"))


def to_records(rows: DataFrame, id_col: str = "conv_id", order_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One JSON record for each conversation from a row for each turn, in the plainest layout that holds it: a prompt
    and a response, these with a system text, or a list of messages."""
    got = from_turn_rows(rows, id_col, order_col, role_col, text_col)
    roles = F.transform("messages", lambda m: m["role"])
    is_ = lambda *names: roles == F.array(*[F.lit(n) for n in names])
    field = lambda i, name: F.get("messages", F.lit(i))["content"].alias(name)
    pair = F.to_json(F.struct(field(0, "prompt"), field(1, "response")))
    three = F.to_json(F.struct(field(0, "system"), field(1, "prompt"), field(2, "response")))
    record = F.when(is_("user", "assistant"), pair).when(is_("system", "user", "assistant"), three).otherwise(F.to_json(F.struct("messages")))
    return got.select(id_col, record.alias("record"))


#: The template: a head with the role, the text, a tail. Inside roles and texts ``\``, ``<`` and ``>`` get a
#: backslash before them (and a role's newline becomes ``\n``), so that an unescaped ``<`` is always a mark.
HEAD, HEAD_END, TAIL = "<turn ", ">\n", "\n</turn>\n"
_TURN = re.compile(r"<turn ((?:[^\\>]|\\.)*)>\n(.*?)\n</turn>\n", re.S)


def escape(text: str) -> str:
    return re.sub(r"([\\<>])", r"\\\1", text)


def unescape(text: str) -> str:
    return re.sub(r"\\([\\<>n])", lambda m: "\n" if m[1] == "n" else m[1], text)


def render_turns(turns: list[dict], loss_roles=("assistant",)) -> tuple[str, list[int], list[int]]:
    """The formatted text, and start and length (code points) of the parts under the loss mask."""
    parts, starts, lengths, at = [], [], [], 0
    for t in turns:
        head, body = HEAD + escape(t["role"]).replace("\n", "\\n") + HEAD_END, escape(t["text"])
        if t["role"] in loss_roles:
            starts.append(at + len(head))
            lengths.append(len(body))
        parts += [head, body, TAIL]
        at += len(head) + len(body) + len(TAIL)
    return "".join(parts), starts, lengths


def parse(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a formatted text."""
    return [(unescape(m[1]), unescape(m[2])) for m in _TURN.finditer(formatted)]


def render(df: DataFrame, id_col: str, loss_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """id, formatted, loss_starts, loss_lengths from a ``turns`` column."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [render_turns(t or [], loss_roles) for t in b.column(1).to_pylist()]
            cols = [pa.array([x[0] for x in out], pa.string()), *[pa.array([x[i] for x in out], pa.list_(pa.int64())) for i in (1, 2)]]
            yield pa.RecordBatch.from_arrays([b.column(0), *cols], names=[id_col, "formatted", "loss_starts", "loss_lengths"])

    return arrow(df.select(id_col, "turns"), run, f"{id_col} {kind}, formatted string, loss_starts array<bigint>, loss_lengths array<bigint>")


def read_back(df: DataFrame, id_col: str) -> DataFrame:
    """Digests of what a reader gets out of formatted texts: turns, and the text under the loss mask."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for text, starts, lengths in zip(*[b.column(i).to_pylist() for i in (1, 2, 3)], strict=True):
                turns, h = parse(text), hashlib.sha256()
                for role, said in turns:
                    h.update(f"{role}\n{said}\n".encode())
                loss = "".join(unescape(text[s : s + n]) for s, n in zip(starts, lengths, strict=True))
                rows.append((len(turns), h.hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]], names=[id_col, "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return arrow(df.select(id_col, "formatted", "loss_starts", "loss_lengths"), run, f"{id_col} {kind}, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint")
