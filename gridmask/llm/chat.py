"""Chat formatting: heterogeneous records -> canonical turns -> one marked-up text with a loss mask, and back.

A record's shape is told by a fingerprint: the hash of its sorted nested field paths with their kinds. A registry
maps fingerprints to declarative mappings (which paths hold the messages, roles and texts); a shape that is not
registered is matched once by the paths that the mappings need, and then known by its fingerprint.

The template marks turns with control strings. A backslash inside a text is doubled and the opening of a control
string gets a backslash in front, so that no text can forge a mark, and reading undoes it exactly. The loss mask
covers each assistant text, and nothing between.

Conversations in rows are streamed in order of conv_id and turn (nulls first, ties by the other columns) and never held
whole: the output is a table of parts of bounded length, and reading goes through them in order. A row is a record of
its own: all its columns but conv_id and turn, under their names, nested or not. Its fingerprint selects the mapping
that makes it one or more turns, so tables of role and text, of from and value or of prompt and response are read
alike, and rows of one table may differ in what they fill. Null texts and roles count as empty; repeated rows are turns
of their own; columns that no mapping names are passed by; an empty table gives an empty result. A null conv_id is a
conversation of its own. A table none of whose columns suits any mapping is an error.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .shared import exchange_size

#: The marks; fixed values of the template.
OPEN, MIDDLE, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
#: Marks of other templates that must not appear unescaped either.
FOREIGN = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|")
_GUARDED = re.compile("|".join(map(re.escape, (*FOREIGN, "\\"))))
_ESCAPED = re.compile(r"\\(.)", re.S)


def escape(text: str) -> str:
    """Reversible: a backslash goes before a backslash and before the opening of any control string."""
    return _GUARDED.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


# ---- shapes -----------------------------------------------------------------------------------------------------


def field_paths(value: Any, at: str = "") -> set[str]:
    """Nested field paths with kinds; elements of a list share the path with []."""
    if isinstance(value, dict):
        return {p for k, v in value.items() for p in field_paths(v, f"{at}.{k}" if at else str(k))}
    if isinstance(value, list):
        return {p for v in value for p in field_paths(v, f"{at}[]")} or {f"{at}[]"}
    kind = "none" if value is None else "text" if isinstance(value, str) else "number" if isinstance(value, int | float) else "other"
    return {f"{at}:{kind}"}


def fingerprint(record: dict) -> str:
    """16 hex digits of the hash of the record's field paths."""
    return hashlib.sha256("\n".join(sorted(field_paths(record))).encode()).hexdigest()[:16]


@dataclass(frozen=True)
class Mapping:
    """How a layout becomes turns. messages: path of a list, with role and text keys in it; or fields: (role, paths)
    pairs in order, whose non-empty texts are joined by a blank line into one turn; or neither: the record is itself one
    message."""

    name: str
    messages: str | None = None
    role_key: str = ""
    text_key: str = ""
    fields: tuple[tuple[str, tuple[str, ...]], ...] = ()
    roles_as_they_are: bool = False

    def needs(self) -> set[str]:
        if self.messages is not None:
            return {f"{self.messages}[].{self.role_key}", f"{self.messages}[].{self.text_key}"}
        if not self.fields:
            return {self.role_key, self.text_key}
        return {paths[0] for _, paths in self.fields if paths}

    def turns(self, record: dict) -> list[tuple[str, str]]:
        if self.messages is not None:
            found = record.get(self.messages) or []
            name = as_text if self.roles_as_they_are else canonical_role
            return [(name(m.get(self.role_key)), as_text(m.get(self.text_key))) for m in found]
        if not self.fields:
            name = as_text if self.roles_as_they_are else canonical_role
            return [(name(record.get(self.role_key)), as_text(record.get(self.text_key)))]
        out = []
        for role, paths in self.fields:
            text = "\n\n".join(t for t in (as_text(record.get(p)) for p in paths) if t)
            if text or role != "system":
                out.append((role, text))
        return out


#: The layouts known from public instruction sets.
MAPPINGS = (
    Mapping("messages", messages="messages", role_key="role", text_key="content"),
    Mapping("messages_text", messages="messages", role_key="role", text_key="text"),
    Mapping("conversations", messages="conversations", role_key="from", text_key="value"),
    Mapping("dialog", messages="dialog", role_key="speaker", text_key="text"),
    Mapping("instruction", fields=(("system", ("system",)), ("user", ("instruction", "input")), ("assistant", ("output",)))),
    Mapping("instruction_response", fields=(("user", ("instruction", "context")), ("assistant", ("response",)))),
    Mapping("prompt_completion", fields=(("user", ("prompt",)), ("assistant", ("completion",)))),
    Mapping("prompt_response", fields=(("user", ("prompt",)), ("assistant", ("response",)))),
    Mapping("question_answer", fields=(("user", ("context", "question")), ("assistant", ("answer",)))),
    Mapping("turns", messages="turns", role_key="role", text_key="text", roles_as_they_are=True),
    Mapping("row_role_text", role_key="role", text_key="text", roles_as_they_are=True),
    Mapping("row_role_content", role_key="role", text_key="content"),
    Mapping("row_from_value", role_key="from", text_key="value"),
    Mapping("row_speaker_text", role_key="speaker", text_key="text"),
)
#: Other names of roles, as public sets use them.
ROLES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "ai": "assistant"}


def canonical_role(role: Any) -> str:
    return ROLES.get(as_text(role).lower(), as_text(role))


def as_text(value: Any) -> str:
    """Text as it is; a list of parts with text is joined; null is empty; anything else is JSON."""
    if value is None or isinstance(value, str):
        return value or ""
    if isinstance(value, list) and all(isinstance(v, dict) and "text" in v for v in value):
        return "".join(as_text(v["text"]) for v in value)
    return json.dumps(value, ensure_ascii=False, sort_keys=True)


class Registry:
    """fingerprint -> mapping, learned as shapes appear."""

    def __init__(self, mappings: Iterable[Mapping] = MAPPINGS) -> None:
        self.mappings = tuple(mappings)
        self.known: dict[str, Mapping | None] = {}
        self.row_kinds: dict[tuple, Mapping | None] = {}

    def mapping(self, record: dict) -> Mapping | None:
        key = fingerprint(record)
        if key not in self.known:
            paths = {p.split(":")[0] for p in field_paths(record)}
            fits = [m for m in self.mappings if all(any(p == n or p.startswith((n + "[", n + ".")) for p in paths) for n in m.needs() if not n.startswith("system"))]
            self.known[key] = max(fits, key=lambda m: (len(m.needs()), -self.mappings.index(m)), default=None)
        return self.known[key]

    def row_mapping(self, names: tuple[str, ...], record: dict) -> Mapping | None:
        """mapping() of a flat row: rows whose columns are of the same kinds have the same fingerprint."""
        if any(isinstance(v, dict | list) for v in record.values()):
            return self.mapping(record)
        kinds = (names, tuple(map(type, record.values())))
        if kinds not in self.row_kinds:
            self.row_kinds[kinds] = self.mapping(record)
        return self.row_kinds[kinds]

    def turns(self, record: dict) -> list[tuple[str, str]] | None:
        m = self.mapping(record)
        return None if m is None else m.turns(record)


def format_turn(role: str, text: str) -> tuple[str, int, int]:
    """The turn's formatted text, and start and end of its text in it."""
    head = f"{OPEN}{escape(role)}{MIDDLE}"
    body = escape(text)
    return f"{head}{body}{CLOSE}\n", len(head), len(head) + len(body)


def format_records(df: DataFrame, record: str = "record") -> DataFrame:
    """JSON records of any registered layout -> the same columns and fingerprint, layout, n_turns, formatted, loss_spans.

    A record that is no JSON object or of an unknown layout gets nulls (and its fingerprint, if it has one).
    """
    added = "fingerprint string, layout string, n_turns int, formatted string, loss_spans array<struct<start:long,end:long>>"
    taken = {c.lower() for c in df.columns}
    if clash := taken & {x.split()[0] for x in added.split(", ")}:
        df = df.drop(*clash)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        registry = Registry()
        span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for b in batches:
            rows = []
            for raw in b.column(record).to_pylist():
                try:
                    value = json.loads(raw) if raw else None
                except ValueError:
                    value = None
                turns = registry.turns(value) if isinstance(value, dict) else None
                if turns is None:
                    rows.append((fingerprint(value) if isinstance(value, dict) else None, None, None, None, None))
                    continue
                text, spans = "", []
                for role, body in turns:
                    piece, s, e = format_turn(role, body)
                    if role == "assistant":
                        spans.append({"start": len(text) + s, "end": len(text) + e})
                    text += piece
                rows.append((fingerprint(value), registry.mapping(value).name, len(turns), text, spans))
            cols = list(zip(*rows)) or [()] * 5
            types = (pa.string(), pa.string(), pa.int32(), pa.string(), span)
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(c, t) for c, t in zip(cols, types))], names=[*b.schema.names, *(x.split()[0] for x in ("fingerprint", "layout", "n_turns", "formatted", "loss_spans"))])

    return df.mapInArrow(run, StructType([*df.schema.fields, *StructType.fromDDL(added).fields]))


# ---- conversations in rows --------------------------------------------------------------------------------------


def format_conversations(rows: DataFrame, part_chars: int = 1 << 20) -> DataFrame:
    """rows(conv_id, turn, columns of a layout) -> (conv_id, part, formatted, spans): the formatted text in parts, in order.

    A part ends with a turn and has part_chars code points or one turn; spans are the loss mask within the part. The
    parts of a conversation lie in one partition, one after the other.
    """
    names = tuple(c for c in rows.columns if c not in ("conv_id", "turn"))
    if Registry().mapping({c: "" for c in names}) is None and not any(t.startswith(("array", "struct", "map")) for _, t in rows.dtypes):
        raise ValueError(f"no known layout has the columns {names}")
    needed = {n.split("[")[0].split(".")[0] for m in MAPPINGS for n in m.needs()} | {p for m in MAPPINGS for _, paths in m.fields for p in paths}
    names = tuple(c for c in names if c in needed)
    order = [F.col(c).asc_nulls_first() for c in ("conv_id", "turn", *(c for c, t in rows.dtypes if c in names and not t.startswith("map")))]
    dealt = rows.select("conv_id", F.col("turn").cast("long").alias("turn"), *names).repartition(exchange_size(rows.sparkSession), "conv_id").sortWithinPartitions(*order)
    span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        registry, out, conv, part = Registry(), [], object(), 0
        texts: list[str] = []
        spans: list[dict[str, int]] = []
        size = 0

        def close() -> None:
            nonlocal texts, spans, size, part
            if texts:
                out.append((conv, part, "".join(texts), spans))
                texts, spans, size, part = [], [], 0, part + 1

        def batch() -> pa.RecordBatch:
            cols = list(zip(*out))
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.string(), span))], names=["conv_id", "part", "formatted", "spans"])

        for b in batches:
            for c, *values in zip(*(b.column(i).to_pylist() for i in (0, *range(2, b.num_columns)))):
                if c != conv:
                    close()
                    conv, part = c, 0
                record = dict(zip(names, values))
                mapping = registry.row_mapping(names, record)
                for role, text in mapping.turns(record) if mapping else ():
                    piece, s, e = format_turn(role, text)
                    if role == "assistant":
                        spans.append({"start": size + s, "end": size + e})
                    texts.append(piece)
                    size += len(piece)
                    if size >= part_chars:
                        close()
            if len(out) >= 1000 or sum(len(o[2]) for o in out) >= part_chars:
                yield batch()
        close()
        if out:
            yield batch()

    return dealt.mapInArrow(run, "conv_id long, part long, formatted string, spans array<struct<start:long,end:long>>")


#: Bodies are runs of escaped characters and of characters that open no mark.
_BODY = r"((?:\\.|[^\\<]|<(?!\|))*)"
_TURN = re.compile(re.escape(OPEN) + _BODY + re.escape(MIDDLE) + _BODY + re.escape(CLOSE) + "\n", re.S)


def parse(formatted: str) -> list[tuple[str, str]]:
    """Turns of a formatted text. Marks inside texts were escaped, so the first mark met is a real one."""
    out, at = [], 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if m is None:
            raise ValueError(f"no turn at {at}")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return out


def read_digests(parts: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, read back from the parts alone.

    parts must come as format_conversations gives them: a conversation's parts in one partition, in order.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv: Any = object()
        state: list[Any] = []
        out: list[tuple] = []

        def close() -> None:
            if state:
                n, turns, loss_n, loss, size = state
                out.append((conv, n, turns.hexdigest(), loss_n, loss.hexdigest(), size))

        def batch() -> pa.RecordBatch:
            cols = list(zip(*out))
            out.clear()
            types = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

        for b in batches:
            for c, formatted, spans in zip(*(b.column(i).to_pylist() for i in (0, 2, 3))):
                if c != conv:
                    close()
                    conv, state[:] = c, [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                for role, text in parse(formatted):
                    state[0] += 1
                    state[1].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
                for s in spans:
                    text = unescape(formatted[s["start"] : s["end"]])
                    state[2] += len(text)
                    state[3].update(text.encode("utf-8", "surrogatepass"))
                state[4] += len(formatted)
            if len(out) >= 1000:
                yield batch()
        close()
        if out:
            yield batch()

    return parts.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
