"""Chat formatting with typed content parts.

A conversation's turns become one string. A visitor flattens the parts of a turn: texts are escaped, images, audio and
documents become numbered placeholders, whose references and token counts are kept beside the string. Turns stand
between control strings that all begin with "<"; inside texts and roles the characters \\, < and > are escaped, so that
the string can be read back. The loss mask is a list of code-point ranges that cover the assistants' escaped texts.

Defined cases: a null text or role is empty, turns with equal numbers go by role and text, null turn numbers come
first, null conversation ids form one conversation, a part of a kind that is not known keeps its text and reference, repeated rows are repeated turns, an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_ESCAPED = {"\\": "\\\\", "<": "\\l", ">": "\\g"}
_TABLE = str.maketrans(_ESCAPED)
_BACK = {v: k for k, v in _ESCAPED.items()}
_CODE = re.compile(r"\\[\\lg]")
_TURN = re.compile(r"<turn ([^<>]*)>\n([^<>]*(?:<(?:image|audio|document|other):[0-9]+>[^<>]*)*)\n</turn>\n")
PARTS = "array<struct<kind:string,text:string,ref:string,width:int,height:int,seconds:double,pages:int>>"
VISITED = ("text", "image", "audio", "document")
FORMATTED = "conv_id bigint, formatted string, loss_spans array<struct<start:bigint,end:bigint>>, attachments array<struct<ordinal:int,kind:string,ref:string,turn:bigint,start:bigint,n_tokens:bigint>>, n_turns bigint, expanded_tokens bigint"
_ARROW = pa.schema([
    ("conv_id", pa.int64()), ("formatted", pa.string()), ("loss_spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))),
    ("attachments", pa.list_(pa.struct([("ordinal", pa.int32()), ("kind", pa.string()), ("ref", pa.string()), ("turn", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())]))),
    ("n_turns", pa.int64()), ("expanded_tokens", pa.int64()),
])


def escape(text: str) -> str:
    return text.translate(_TABLE)


def unescape(text: str) -> str:
    return _CODE.sub(lambda m: _BACK[m[0]], text)


@dataclass(frozen=True)
class TokenCosts:
    """How many tokens a placeholder stands for."""

    patch: int = 14
    audio_per_second: float = 25.0
    per_page: int = 512

    def of(self, part: dict) -> int:
        kind = part["kind"]
        if kind == "image":
            return max(1, -(-(part.get("width") or 0) // self.patch)) * max(1, -(-(part.get("height") or 0) // self.patch))
        if kind == "audio":
            return max(1, round((part.get("seconds") or 0.0) * self.audio_per_second))
        return max(1, part.get("pages") or 0) * self.per_page


@dataclass
class PartVisitor:
    """Flattens the parts of one conversation in order. pos: code points written so far."""

    costs: TokenCosts = field(default_factory=TokenCosts)
    pos: int = 0
    attachments: list[dict] = field(default_factory=list)

    def visit(self, part: dict, turn: int) -> str:
        kind = part.get("kind") or "text"
        out = (getattr(self, f"visit_{kind}") if kind in VISITED else self.visit_other)(part, turn)
        self.pos += len(out)
        return out

    def visit_text(self, part: dict, turn: int) -> str:
        return escape(part.get("text") or "")

    def _attach(self, part: dict, turn: int) -> str:
        ordinal = len(self.attachments)
        self.attachments.append({"ordinal": ordinal, "kind": part["kind"], "ref": part.get("ref"), "turn": turn, "start": self.pos, "n_tokens": self.costs.of(part)})
        return f"<{part['kind']}:{ordinal}>"

    visit_image = visit_audio = visit_document = _attach

    def visit_other(self, part: dict, turn: int) -> str:
        """A kind that is not known: its text stays text, its reference is kept behind a placeholder of its own."""
        text = self.visit_text(part, turn)
        if part.get("ref") is None:
            return text
        ordinal = len(self.attachments)
        self.attachments.append({"ordinal": ordinal, "kind": part["kind"], "ref": part["ref"], "turn": turn, "start": self.pos + len(text), "n_tokens": 1})
        return f"{text}<other:{ordinal}>"


class Conversation:
    """Takes the turns of one conversation in order and writes its string, loss ranges and attachments."""

    def __init__(self, conv_id: int | None, costs: TokenCosts):
        self.conv_id, self.visitor, self.out, self.loss, self.turns = conv_id, PartVisitor(costs), [], [], 0

    def put(self, text: str) -> None:
        self.out.append(text)
        self.visitor.pos += len(text)

    def add(self, role: str | None, parts: list[dict]) -> None:
        self.put(f"<turn {escape(role or '')}>\n")
        start = self.visitor.pos
        self.out.extend(self.visitor.visit(p, self.turns) for p in parts)
        if role == "assistant":
            self.loss.append({"start": start, "end": self.visitor.pos})
        self.put("\n</turn>\n")
        self.turns += 1

    def row(self) -> dict:
        return {"conv_id": self.conv_id, "formatted": "".join(self.out), "loss_spans": self.loss, "attachments": self.visitor.attachments, "n_turns": self.turns, "expanded_tokens": sum(a["n_tokens"] for a in self.visitor.attachments)}


def format_conversations(turns: DataFrame, costs: TokenCosts | None = None) -> DataFrame:
    """One row per conversation (columns in FORMATTED) from (conv_id, turn, role, text) or (conv_id, turn, role, parts).

    One shuffle by conversation and a sort that can spill; a task streams through its sorted turns and holds no more
    than the conversation it writes.
    """
    costs = costs or TokenCosts()
    typed = "parts" in turns.columns
    content = F.col("parts").cast(PARTS) if typed else F.col("text")
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), content.alias("content"))
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", *([] if typed else ["content"]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: Conversation | None = None
        done, held = [], 0
        for batch in batches:
            columns = [batch.column(n).to_pylist() for n in ("conv_id", "role", "content")]
            for conv_id, role, content in zip(*columns, strict=True):
                if now is None or now.conv_id != conv_id:
                    if now is not None:
                        done.append(now.row())
                        held += now.visitor.pos
                        if held > 2 << 20:
                            yield pa.RecordBatch.from_pylist(done, _ARROW)
                            done, held = [], 0
                    now = Conversation(conv_id, costs)
                now.add(role, (content or []) if typed else [{"kind": "text", "text": content}])
        if now is not None:
            done.append(now.row())
        yield pa.RecordBatch.from_pylist(done, _ARROW)

    return rows.mapInArrow(run, FORMATTED)


def parse_formatted(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of every turn, read back from the string; placeholders stay as they are."""
    out, at = [], 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if not m:
            raise ValueError(f"no turn starts at {at}")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return out


def conversation_digests(formatted: DataFrame) -> DataFrame:
    """(conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars), all read back from the strings."""
    schema = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for conv_id, text, spans in zip(*(batch.column(n).to_pylist() for n in ("conv_id", "formatted", "loss_spans")), strict=True):
                turns, loss = hashlib.sha256(), hashlib.sha256()
                read = parse_formatted(text)
                for role, said in read:
                    turns.update(f"{role}\n{said}\n".encode())
                chars = 0
                for s in spans:
                    own = unescape(text[s["start"] : s["end"]])
                    chars += len(own)
                    loss.update(own.encode())
                rows.append((conv_id, len(read), turns.hexdigest(), chars, loss.hexdigest(), len(text)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 6, schema.types, strict=True)], schema=schema)

    return formatted.select("conv_id", "formatted", "loss_spans").mapInArrow(run, "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint")
