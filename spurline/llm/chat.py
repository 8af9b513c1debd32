"""Chat formatting with typed content parts.

A visitor flattens each message's text, image, audio and document parts, in order, into one string with placeholders; it
records what each placeholder refers to and how many tokens it will expand to. The template marks turns; control strings
inside texts are escaped, reversibly. Turns are formatted row by row; only their offsets in the conversation need order.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.arrow import _arrow_schema

#: What the template writes, and control strings of common templates.
TURN, END = "<|turn|>", "<|end|>\n"
_control = re.compile(r"(<)(\\*)(/?s>|\|[^|<>\[]*\|>)|(\[)(\\*)(/?INST\])")
_escaped = re.compile(r"(<)\\(\\*)(/?s>|\|[^|<>\[]*\|>)|(\[)\\(\\*)(/?INST\])")
_segment = re.compile(r"<\|turn\|>([^\n]*)\n(.*)<\|end\|>\n", re.DOTALL)
PARTS = "array<struct<type:string,text:string,ref:string,units:int>>"
SEGMENTS = "conv_id long, turn_no long, role string, formatted string, offset long, loss_start long, loss_end long, tokens_expanded long, attachments array<struct<slot:int,kind:string,ref:string,position:int,tokens:int>>"


def escape(text: str) -> str:
    """One backslash more after the first character of every control string."""
    return _control.sub(lambda m: f"{m[1] or m[4]}\\{m[2] or m[5] or ''}{m[3] or m[6]}", text)


def unescape(text: str) -> str:
    return _escaped.sub(lambda m: f"{m[1] or m[4]}{m[2] or m[5] or ''}{m[3] or m[6]}", text)


def escape_role(role: str) -> str:
    return escape(role).replace("\\", "\\\\").replace("\n", "\\n")


def unescape_role(role: str) -> str:
    return unescape(re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], role))


class PartVisitor:
    """Visits the parts of one message. Tokens: an image ``units`` (tiles) times ``per_tile``, audio ``units`` (seconds) times
    ``per_second``, a document ``units`` (pages) times ``per_page``; unknown types become generic placeholders of one token."""

    def __init__(self, per_tile: int = 256, per_second: int = 25, per_page: int = 512):
        self.rate = {"image": per_tile, "audio": per_second, "document": per_page}

    def visit(self, parts: list[dict] | None) -> tuple[str, list[dict], int]:
        self.out, self.found, self.tokens, self.length = [], [], 0, 0
        for part in parts or []:
            kind = (part or {}).get("type") or "text"
            getattr(self, f"visit_{kind}", self.visit_attachment)(part or {}, kind)
        return "".join(self.out), self.found, self.tokens

    def _put(self, s: str) -> None:
        self.out.append(s)
        self.length += len(s)

    def visit_text(self, part: dict, _: str) -> None:
        self._put(escape(part.get("text") or ""))

    def visit_attachment(self, part: dict, kind: str) -> None:
        kind = kind if kind in self.rate else "attachment"
        tokens = max(1, part.get("units") or 1) * self.rate.get(kind, 1)
        self.found.append({"slot": len(self.found), "kind": kind, "ref": part.get("ref"), "position": self.length, "tokens": tokens})
        self.tokens += tokens
        self._put(f"<|{kind}:{len(self.found) - 1}|>")


def text_parts(text: F.Column) -> F.Column:
    """A plain text as a message of one text part; null: one empty text."""
    return F.array(F.struct(F.lit("text").alias("type"), F.coalesce(text, F.lit("")).alias("text"), F.lit(None).cast("string").alias("ref"), F.lit(None).cast("int").alias("units")))


def format_conversations(messages: DataFrame) -> DataFrame:
    """The segments of all conversations, a row for each message, in order within each partition.

    ``messages``: ``conv_id, turn, role`` and either ``parts`` (see PARTS) or a plain ``text``. Order: turn (nulls first), then
    role, then the formatted text, so ties and repeated rows have a fixed order. A null role is empty; a null conversation id is a
    conversation. ``loss_start`` and ``loss_end`` are code points of the conversation's formatted text: what an assistant's
    message covers; both null for other roles. The formatted text of a conversation is its segments' texts in order.

    Sorting spills and the pass over the sorted rows keeps one offset, so a conversation of any length fits a task; its
    turns cannot be dealt out further, as each offset needs the ones before it.
    """
    parts = F.col("parts").cast(PARTS) if "parts" in messages.columns else text_parts(F.col("text").cast("string"))
    fields = _arrow_schema(messages, "conv_id long, turn long, role string, formatted string, tokens_expanded long, attachments array<struct<slot:int,kind:string,ref:string,position:int,tokens:int>>")

    def flatten(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        visitor = PartVisitor()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                piece = batch.slice(at, 512)
                roles = [r or "" for r in piece.column(2).to_pylist()]
                seen = [visitor.visit(p) for p in piece.column(3).to_pylist()]
                texts = [f"{TURN}{escape_role(r)}\n{s[0]}{END}" for r, s in zip(roles, seen, strict=True)]
                yield pa.RecordBatch.from_arrays([piece.column(0), piece.column(1), pa.array(roles, pa.string()), pa.array(texts, pa.string()), pa.array([s[2] for s in seen], pa.int64()), pa.array([s[1] for s in seen], fields.field("attachments").type)], schema=fields)

    out = _arrow_schema(messages, SEGMENTS)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, at, turn = object(), 0, 0
        for batch in batches:
            offsets, starts, ends, turns = [], [], [], []
            for conv, role, text in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                if conv != now:
                    now, at, turn = conv, 0, 0
                offsets.append(at)
                turns.append(turn)
                own = role == "assistant"
                starts.append(at + len(TURN) + len(escape_role(role)) + 1 if own else None)
                at += len(text)
                turn += 1
                ends.append(at - len(END) if own else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(turns, pa.int64()), batch.column(2), batch.column(3), pa.array(offsets, pa.int64()), pa.array(starts, pa.int64()), pa.array(ends, pa.int64()), batch.column(4), batch.column(5).cast(out.field("attachments").type)], schema=out)

    flat = messages.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), parts.alias("parts")).mapInArrow(flatten, "conv_id long, turn long, role string, formatted string, tokens_expanded long, attachments array<struct<slot:int,kind:string,ref:string,position:int,tokens:int>>")
    return flat.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "formatted").mapInArrow(place, SEGMENTS)


def parse_segment(segment: str) -> tuple[str, str]:
    """Role and text of one formatted turn; placeholders of attachments stay as they are."""
    m = _segment.fullmatch(segment)
    if not m:
        raise ValueError("not a formatted turn")
    return unescape_role(m[1]), unescape(m[2])


def read_back(segments: DataFrame) -> DataFrame:
    """``(conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars)``, read from the output of
    :func:`format_conversations` alone, whose order within partitions it relies on: turns parsed back, and the text under the loss
    mask, unescaped."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, out = None, []
        for batch in batches:
            for conv, text, offset, lo, hi in zip(*(batch.column(i).to_pylist() for i in (0, 3, 4, 5, 6)), strict=True):
                if state is None or state[0] != conv:
                    if state:
                        out.append(close(state))
                    state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                role, said = parse_segment(text)
                state[1] += 1
                state[2].update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
                if lo is not None:
                    masked = unescape(text[lo - offset : hi - offset])
                    state[3] += len(masked)
                    state[4].update(masked.encode("utf-8", "surrogatepass"))
                state[5] += len(text)
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=fields)
                out = []
        if state:
            yield pa.RecordBatch.from_pylist([close(state)], schema=fields)

    def close(s: list) -> dict:
        return dict(zip(fields.names, (s[0], s[1], s[2].hexdigest(), s[3], s[4].hexdigest(), s[5]), strict=True))

    schema = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    fields = _arrow_schema(segments, schema)
    return segments.mapInArrow(run, schema)
