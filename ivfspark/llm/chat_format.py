"""Chat formatting: layouts known by a hash of their field paths, one template, reversible escapes.

A record's layout is the sorted list of its nested field paths, as far as any mapping knows them; the
list's hash picks a declarative mapping (where each turn's role and text come from). A layout without a
mapping of its own falls to the mapping that uses most of its paths.

The template writes a turn as start mark, role, line end, text, end mark. Inside roles and texts a
backslash is doubled and a mark's opening is broken by a backslash, so marks never occur in content and
every text can be read back. The loss mask is a list of character ranges over the formatted string: the
(escaped) assistant texts.

Turns are in order of turn, then role and text; null turn first. Null role or text counts as empty;
a null conversation id is a conversation. Repeated rows are turns of their own. An empty table gives an
empty result. Fields that no mapping knows, of whatever name, are ignored.
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

START, END = "<|turn|>", "<|end|>\n"
LEARNED_ROLE = "assistant"
ROLE_NAMES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "prompter": "user"}


@dataclass(frozen=True)
class Mapping:
    """Where turns come from: ``rows`` (a turn a row), ``list`` (a list of turns) or ``fields`` (fixed roles)."""

    name: str
    kind: str
    parts: tuple[tuple[str, str], ...]

    @property
    def paths(self) -> frozenset[str]:
        return frozenset(path for _, path in self.parts)


MAPPINGS = (
    Mapping("rows", "rows", (("id", "conv_id"), ("turn", "turn"), ("role", "role"), ("text", "text"))),
    Mapping("messages", "list", (("role", "messages[].role"), ("text", "messages[].content"))),
    Mapping("conversations", "list", (("role", "conversations[].from"), ("text", "conversations[].value"))),
    Mapping("instruction_input", "fields", (("user", "instruction"), ("user", "input"), ("assistant", "output"))),
    Mapping("instruction", "fields", (("user", "instruction"), ("assistant", "output"))),
    Mapping("instruction_response", "fields", (("user", "instruction"), ("assistant", "response"))),
    Mapping("system_prompt", "fields", (("system", "system"), ("user", "prompt"), ("assistant", "completion"))),
    Mapping("prompt", "fields", (("user", "prompt"), ("assistant", "completion"))),
    Mapping("prompt_response", "fields", (("user", "prompt"), ("assistant", "response"))),
    Mapping("question", "fields", (("user", "question"), ("assistant", "answer"))),
)
_KNOWN_PATHS = frozenset().union(*(m.paths for m in MAPPINGS))


def fingerprint(paths) -> str:
    """Hash of the known field paths among ``paths``, whatever their order."""
    return hashlib.sha256("\n".join(sorted(set(paths) & _KNOWN_PATHS)).encode()).hexdigest()[:16]


BY_FINGERPRINT = {fingerprint(m.paths): m for m in MAPPINGS}


def mapping_for(paths) -> Mapping | None:
    """The mapping of a layout; the one with most paths present where no fingerprint matches."""
    paths = set(paths)
    exact = BY_FINGERPRINT.get(fingerprint(paths))
    if exact:
        return exact
    fitting = [m for m in MAPPINGS if m.paths <= paths]
    return max(fitting, key=lambda m: len(m.paths), default=None)


def schema_paths(schema: T.DataType, prefix: str = "") -> list[str]:
    """Leaf field paths of a Spark type; list items are marked ``[]``."""
    if isinstance(schema, T.StructType):
        return [p for f in schema for p in schema_paths(f.dataType, f"{prefix}.{f.name}" if prefix else f.name)]
    if isinstance(schema, T.ArrayType):
        return schema_paths(schema.elementType, prefix + "[]")
    return [prefix]


def value_paths(value, prefix: str = "") -> set[str]:
    """Leaf field paths of a parsed JSON value."""
    if isinstance(value, dict):
        return {p for k, v in value.items() for p in value_paths(v, f"{prefix}.{k}" if prefix else k)}
    if isinstance(value, list):
        return {p for v in value for p in value_paths(v, prefix + "[]")} or {prefix + "[]"}
    return {prefix}


def turns_of(record: dict, mapping: Mapping) -> list[tuple[str, str]]:
    """Canonical (role, text) turns of one record under a list or fields mapping."""
    text = lambda v: "" if v is None else v if isinstance(v, str) else json.dumps(v, ensure_ascii=False)
    if mapping.kind == "list":
        (_, role_path), (_, text_path) = mapping.parts
        outer, role_key, text_key = role_path.split("[]")[0], role_path.rpartition(".")[2], text_path.rpartition(".")[2]
        rows = [r for r in record.get(outer) or [] if isinstance(r, dict)]
        return [(ROLE_NAMES.get(text(r.get(role_key)), text(r.get(role_key))), text(r.get(text_key))) for r in rows]
    turns: list[tuple[str, str]] = []
    for role, path in mapping.parts:
        value = text(record.get(path))
        if turns and turns[-1][0] == role:
            turns[-1] = (role, "\n\n".join(x for x in (turns[-1][1], value) if x))
        elif value or role != "system":
            turns.append((role, value))
    return turns


def escape(text: str) -> str:
    return text.replace("\\", "\\\\").replace("<|", "<\\|")


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.DOTALL)


def format_turns(turns: list[tuple[str, str]]) -> tuple[str, list[int], list[int]]:
    """The formatted string, and the starts and ends of the learned ranges in it."""
    out, starts, ends, at = [], [], [], 0
    for role, text in turns:
        head = START + escape(role).replace("\n", "\\n") + "\n"
        body = escape(text)
        out += [head, body, END]
        if role == LEARNED_ROLE:
            starts.append(at + len(head))
            ends.append(at + len(head) + len(body))
        at += len(head) + len(body) + len(END)
    return "".join(out), starts, ends


def parse_turns(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted string."""
    turns = []
    for piece in formatted.split(START)[1:]:
        head, _, body = piece.partition("\n")
        role = re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], head, flags=re.DOTALL)
        turns.append((role, unescape(body.removesuffix(END))))
    return turns


def _formatted_batch(rows: list[tuple[object, list[tuple[str, str]]]]) -> pa.RecordBatch:
    made = [format_turns(turns) for _, turns in rows]
    long_list = pa.list_(pa.int64())
    return pa.RecordBatch.from_arrays(
        [
            pa.array([i for i, _ in rows], pa.int64()),
            pa.array([m[0] for m in made], pa.string()),
            pa.array([m[1] for m in made], long_list),
            pa.array([m[2] for m in made], long_list),
        ],
        ["conv_id", "formatted", "loss_starts", "loss_ends"],
    )


_FORMATTED = "conv_id long, formatted string, loss_starts array<long>, loss_ends array<long>"


def format_rows(df: DataFrame) -> DataFrame:
    """Format a table whose layout has a turn a row; one output row a conversation.

    Rows are dealt by conversation and streamed in order; a task holds one conversation at a time.
    """
    mapping = mapping_for(schema_paths(df.schema))
    if mapping is None or mapping.kind != "rows":
        raise ValueError(f"no mapping by rows for the layout {fingerprint(schema_paths(df.schema))}")
    column = dict(mapping.parts)
    rows = df.select(
        F.col(column["id"]).cast("long").alias("id"),
        F.col(column["turn"]).alias("turn"),
        F.coalesce(F.col(column["role"]).cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col(column["text"]).cast("string"), F.lit("")).alias("text"),
    )

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, turns, done = None, [], []
        for batch in batches:
            for conv, role, text in zip(*(batch.column(c).to_pylist() for c in ("id", "role", "text")), strict=True):
                if turns and conv != now:
                    done.append((now, turns))
                    turns = []
                now = conv
                turns.append((role, text))
            if done:
                yield _formatted_batch(done)
                done = []
        if turns:
            yield _formatted_batch([(now, turns)])

    dealt = rows.repartition("id").sortWithinPartitions("id", "turn", "role", "text")
    return dealt.mapInArrow(kernel, _FORMATTED)


def format_json(df: DataFrame, json_col: str = "record", id_col: str = "conv_id") -> DataFrame:
    """Format JSON records of mixed layouts, one conversation a row; adds ``layout`` (the fingerprint).

    A record that is null, broken or of a layout without mapping gives an empty string.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, layouts = [], []
            for conv, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    record = json.loads(raw) if raw is not None else None
                except ValueError:
                    record = None
                paths = value_paths(record) if isinstance(record, dict) else set()
                mapping = mapping_for(paths) if paths else None
                rows.append((conv, turns_of(record, mapping) if mapping and mapping.kind != "rows" else []))
                layouts.append(fingerprint(paths) if paths else None)
            made = _formatted_batch(rows)
            yield pa.RecordBatch.from_arrays([*made.columns, pa.array(layouts, pa.string())], [*made.schema.names, "layout"])

    source = df.select(F.col(id_col).cast("long").alias("conv_id"), F.col(json_col).cast("string").alias("record"))
    return source.mapInArrow(kernel, _FORMATTED + ", layout string")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the formatted strings and their loss masks hold."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for conv, text, starts, ends in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                turns = parse_turns(text)
                said = "".join(unescape(text[s:e]) for s, e in zip(starts, ends, strict=True))
                digest = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
                out.append((conv, len(turns), digest, len(said), hashlib.sha256(said.encode()).hexdigest(), len(text)))
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            columns = list(zip(*out, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, types, strict=True)], names)

    return formatted.select("conv_id", "formatted", "loss_starts", "loss_ends").mapInArrow(
        kernel, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
