"""Chat formatting: schema fingerprints choose declarative mappings from many layouts to canonical turns.

A record's fingerprint is a hash of its nested field paths.  ``LAYOUTS`` holds declarative mappings; each is registered for the
fingerprints of all sets of paths that it explains.  A record whose fingerprint is new is matched once against the mappings'
required paths, and the answer kept.  Canonical turns (role, text) are rendered with a template that marks turns and escapes
its own control strings inside texts, so that the formatted text can be read back without loss.

Null texts and roles are empty.  Turns of one conversation with equal numbers are ordered by role, then text; null turn
numbers come first; repeated rows are repeated turns; a null conv_id is one conversation.  Extra columns are left out
before anything else happens.  An unknown layout gives no turns and the status 'unknown'.  An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import storage

#: Other names of the canonical roles (fixed values).
ROLES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "chatbot": "assistant", "ai": "assistant"}


@dataclass(frozen=True)
class Layout:
    """How a record becomes turns.

    ``turns``: for flat records, (role, path) in order.  ``each``: path of a list whose items are turns, with the names of
    their role and text fields.  ``optional``: paths that may be missing.  A list's items have the path part '[]'.
    """

    name: str
    turns: tuple[tuple[str, str], ...] = ()
    each: str = ""
    role: str = ""
    text: str = ""
    optional: tuple[str, ...] = ()
    joined: tuple[str, str] = field(default=("", ""))

    def paths(self) -> set[str]:
        if self.each or self.role:
            stem = f"{self.each}[]." if self.each else ""
            return {stem + self.role, stem + self.text}
        return {p for _, p in self.turns}

    def required(self) -> set[str]:
        return self.paths() - set(self.optional)


LAYOUTS = (
    Layout("turn rows", role="role", text="text"),
    Layout("messages", each="messages", role="role", text="content"),
    Layout("chosen messages", each="conversation", role="role", text="content"),
    Layout("from and value", each="conversations", role="from", text="value"),
    Layout("instruction", turns=(("system", "system"), ("user", "instruction"), ("user", "input"), ("assistant", "output")), optional=("system", "input"), joined=("instruction", "input")),
    Layout("instruction and response", turns=(("user", "instruction"), ("user", "context"), ("assistant", "response")), optional=("context",), joined=("instruction", "context")),
    Layout("prompt and completion", turns=(("system", "system"), ("user", "prompt"), ("assistant", "completion")), optional=("system",)),
    Layout("prompt and response", turns=(("system", "system"), ("user", "prompt"), ("assistant", "response")), optional=("system",)),
    Layout("question and answer", turns=(("system", "system_prompt"), ("user", "question"), ("assistant", "answer")), optional=("system_prompt",)),
    Layout("plain text", turns=(("assistant", "text"),)),
)


# ---------------------------------------------------------------- fingerprints

def record_paths(record, stem: str = "") -> set[str]:
    """Nested field paths of a parsed record; null fields count as missing."""
    if isinstance(record, dict):
        inner = [record_paths(v, f"{stem}.{k}" if stem else k) for k, v in record.items() if v is not None]
        return set().union(*inner) if inner else set()
    if isinstance(record, list):
        return set().union(*(record_paths(v, f"{stem}[]") for v in record)) if record else {f"{stem}[]"}
    return {stem}


def schema_paths(kind: T.DataType, stem: str = "") -> set[str]:
    """The same of a table's schema."""
    if isinstance(kind, T.StructType):
        return set().union(*(schema_paths(f.dataType, f"{stem}.{f.name}" if stem else f.name) for f in kind))
    if isinstance(kind, T.ArrayType):
        return schema_paths(kind.elementType, f"{stem}[]")
    return {stem}


def fingerprint(paths: set[str]) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()[:16]


class Mappings:
    """Layouts by fingerprint."""

    def __init__(self, layouts=LAYOUTS):
        self.layouts = layouts
        self.by_print: dict[str, Layout | None] = {}
        for lay in reversed(layouts):
            extra = sorted(lay.paths() & set(lay.optional))
            for bits in range(1 << len(extra)):
                self.by_print[fingerprint(lay.required() | {p for k, p in enumerate(extra) if bits >> k & 1})] = lay

    def choose(self, paths: set[str]) -> Layout | None:
        """The layout for a fingerprint; a new one takes the layout that explains most of its paths, first in order among equals."""
        mark = fingerprint(paths)
        if mark not in self.by_print:
            fitting = [lay for lay in self.layouts if lay.required() <= paths]
            self.by_print[mark] = max(fitting, key=lambda lay: len(lay.paths() & paths), default=None)
        return self.by_print[mark]


def canonical_role(role) -> str:
    role = "" if role is None else str(role)
    return ROLES.get(role.lower(), role)


def canonical_turns(record: dict, layout: Layout) -> list[tuple[str, str]]:
    def get(path):
        return record.get(path)

    if layout.each:
        return [(canonical_role(m.get(layout.role)), "" if m.get(layout.text) is None else str(m[layout.text])) for m in record.get(layout.each) or [] if isinstance(m, dict)]
    if layout.role:
        return [(canonical_role(get(layout.role)), get(layout.text) or "")]
    out: list[tuple[str, str]] = []
    for role, path in layout.turns:
        text = get(path)
        if text is None or (path in layout.optional and text == ""):
            continue
        if path == layout.joined[1] and out:
            out[-1] = (role, out[-1][1] + "\n\n" + str(text))
        else:
            out.append((role, str(text)))
    return out


# ---------------------------------------------------------------- template

OPEN, CLOSE = "### ", "</turn>\n"
_TURN = re.compile(r"### ((?:\\.|[^\\:])*): (.*?)</turn>\n", re.S)
_ESCAPED = re.compile(r"\\(.)", re.S)


def escape(text: str) -> str:
    """No '#' without a backslash, and no '</' are left, so no control string can start inside a text."""
    return text.replace("\\", "\\\\").replace("#", "\\#").replace("</", "<\\/")


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def render(role: str, text: str) -> tuple[str, str]:
    """Both parts of a formatted turn: what only the model reads, and what it is trained on if the turn is the assistant's."""
    return f"{OPEN}{escape(role).replace(':', chr(92) + ':')}: ", escape(text) + CLOSE


def read_back(formatted: str) -> Iterator[tuple[str, str, bool]]:
    """(role, text, under the loss mask) of each turn of a formatted text."""
    for m in _TURN.finditer(formatted):
        role = unescape(m[1])
        yield role, unescape(m[2]), role == "assistant"


# ---------------------------------------------------------------- operators

def format_records(df: DataFrame, column: str, layouts=LAYOUTS) -> DataFrame:
    """For JSON records in ``column``: all other columns, then layout, status, turns and formatted."""
    keep = [c for c in df.columns if c not in (column, "layout", "status", "turns", "formatted")]
    turn = "array<struct<role:string,text:string>>"
    text = F.lit(None).cast("string")
    schema = df.select(*keep, text.alias("layout"), text.alias("status"), F.lit(None).cast(turn).alias("turns"), text.alias("formatted")).schema

    def run(batches):
        mappings = Mappings(layouts)
        kind = pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())]))
        for batch in batches:
            names, states, turns, formatted = [], [], [], []
            for raw in batch.column(column).to_pylist():
                try:
                    record = json.loads(raw) if raw is not None else None
                except ValueError:
                    record = None
                record = record if isinstance(record, dict) else {"messages": record} if isinstance(record, list) else None
                layout = mappings.choose(record_paths(record)) if record else None
                got = canonical_turns(record, layout) if layout else []
                names.append(layout.name if layout else None)
                states.append("ok" if layout else "unreadable" if record is None else "unknown")
                turns.append([{"role": r, "text": t} for r, t in got])
                formatted.append("".join("".join(render(r, t)) for r, t in got))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], pa.array(names, pa.string()), pa.array(states), pa.array(turns, kind), pa.array(formatted)], [*keep, "layout", "status", "turns", "formatted"])

    return df.mapInArrow(run, schema)


def format_turn_rows(df: DataFrame, key: str = "conv_id", order: str = "turn") -> DataFrame:
    """``df`` with the canonical columns role and text and the formatted turn, one row a turn.

    The table's schema is the layout: its fingerprint selects the mapping once, for all rows.  A turn is formatted by itself
    and a conversation's formatted text is its turns' in order, so no task ever holds a whole conversation.
    """
    layout = Mappings().choose(schema_paths(df.select([c for c in df.columns if c not in (key, order)]).schema))
    if layout is None or layout.each or not layout.role:
        raise ValueError("no mapping for these columns")
    slim = df.select(F.col(key).cast("long").alias("conv_id"), F.col(order).cast("long").alias("turn"), F.col(layout.role).cast("string").alias("role"), F.col(layout.text).cast("string").alias("text"))

    def run(batches):
        for batch in batches:
            turns = [canonical_turns({layout.role: r, layout.text: t}, layout)[0] for r, t in zip(batch.column("role").to_pylist(), batch.column("text").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("conv_id"), batch.column("turn"), pa.array([r for r, _ in turns], pa.string()), pa.array([t for _, t in turns], pa.string()), pa.array(["".join(render(r, t)) for r, t in turns], pa.string())], ["conv_id", "turn", "role", "text", "formatted"])

    return slim.mapInArrow(run, "conv_id long, turn long, role string, text string, formatted string")


DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def digest_conversations(turns: DataFrame) -> DataFrame:
    """Digests of what is read back from the formatted turns, a row for each conversation.

    Conversations are hashed in order as their turns stream by; a task holds one turn and three running digests, however
    long a conversation is.
    """
    placed = turns.select("conv_id", "turn", "role", "text", "formatted").repartition(storage.width(turns.sparkSession), "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "formatted")

    def run(batches):
        done: list[tuple] = []
        key, n, every, loss, loss_chars, chars, open_ = None, 0, None, None, 0, 0, False

        def close():
            if open_:
                done.append((key, n, every.hexdigest(), loss_chars, loss.hexdigest(), chars))

        def flush():
            cols = list(zip(*done, strict=True)) if done else [[]] * 6
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)], [x.split()[0] for x in DIGESTS.split(", ")])
            done.clear()
            return out

        for batch in batches:
            for k, formatted in zip(batch.column("conv_id").to_pylist(), batch.column("formatted").to_pylist(), strict=True):
                if not open_ or k != key:
                    close()
                    key, n, every, loss, loss_chars, chars, open_ = k, 0, hashlib.sha256(), hashlib.sha256(), 0, 0, True
                chars += len(formatted)
                for role, text, masked in read_back(formatted):
                    n += 1
                    every.update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
                    if masked:
                        loss_chars += len(text)
                        loss.update(text.encode("utf-8", "surrogatepass"))
            yield flush()
        close()
        yield flush()

    return placed.mapInArrow(run, DIGESTS)


def op2_chat(spark, sf_dir: str) -> DataFrame:
    probe = r"\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", probe), (-7, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    rows = storage.table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text").unionByName(extra)
    return digest_conversations(format_turn_rows(rows))


ORACLE = r"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
m AS (
  SELECT *, CASE WHEN lower(role) IN ('human', 'prompter') THEN 'user' WHEN lower(role) IN ('gpt', 'bot', 'model', 'chatbot', 'ai') THEN 'assistant' ELSE role END AS part FROM r),
e AS (
  SELECT *, length(replace(replace(replace(text, '\', '\\'), '#', '\#'), '</', '<\/'))
    + length(replace(replace(replace(replace(part, '\', '\\'), '#', '\#'), '</', '<\/'), ':', '\:')) + 14 AS size FROM m)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(part || chr(10) || text || chr(10), '' ORDER BY turn, part, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (part = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, part, text) FILTER (part = 'assistant'), '')) AS loss_sha256,
  CAST(sum(size) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
