"""Chat formatting: a finite-state machine over roles and a declarative template.

`segments_of` turns rows (conversation, turn, role, text) into text segments, each with a flag that says whether it counts
for the loss. The template states how a turn begins and ends and which roles count for the loss; control strings inside
roles and texts are escaped reversibly. `parse` reads the formatted text back. The machine checks the order of turns:
optional system turns first, then user and assistant in alternation; tool turns may follow assistant turns.

Rows are dealt by conversation and sorted, then pass through the machine one at a time, so a conversation of any length
needs no memory but for its current turn. Defined results: a null text or role counts as empty; an unknown role is
formatted and makes the conversation invalid; rows with the same turn are ordered by role and text and all stay; a null
conversation id is a conversation of its own; an empty table gives no rows; only the four named columns are read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Template:
    """How turns look. A turn is `begin`, role, `middle`, text, `end`; loss_roles give text that counts for the loss."""

    begin: str = "### "
    middle: str = ": "
    end: str = "</turn>\n"
    escape: str = "\\"
    loss_roles: frozenset[str] = frozenset({"assistant"})
    #: State and role to next state; what is missing is an invalid turn.
    moves: dict[tuple[str, str], str] = field(
        default_factory=lambda: {
            ("start", "system"): "start",
            ("start", "user"): "asked",
            ("asked", "assistant"): "answered",
            ("answered", "user"): "asked",
            ("answered", "tool"): "asked",
        }
    )
    final: frozenset[str] = frozenset({"answered"})

    @cached_property
    def _special(self) -> re.Pattern:
        marks = sorted({self.escape, self.begin.strip(), self.middle.strip(), self.end.strip()}, key=len, reverse=True)
        return re.compile("|".join(map(re.escape, marks)))

    @cached_property
    def _scan(self) -> re.Pattern:
        """An escape with what it protects, or a mark."""
        marks = "|".join(map(re.escape, sorted((self.begin, self.middle, self.end), key=len, reverse=True)))
        return re.compile(rf"{re.escape(self.escape)}(?P<kept>.)|(?P<mark>{marks})", re.DOTALL)

    def escaped(self, text: str) -> str:
        return self._special.sub(lambda m: self.escape + m[0], text)

    def unescaped(self, text: str) -> str:
        return re.sub(rf"{re.escape(self.escape)}(.)", r"\1", text, flags=re.DOTALL)

    def turn(self, role: str, text: str) -> tuple[tuple[str, bool], ...]:
        """The segments of a turn, with their loss flags."""
        return (f"{self.begin}{self.escaped(role)}{self.middle}", False), (self.escaped(text), role in self.loss_roles), (self.end, False)

    def parse(self, formatted: str) -> list[tuple[str, str]]:
        """Roles and texts of a formatted conversation."""
        turns, parts, at, wanted = [], [], 0, self.begin
        for m in self._scan.finditer(formatted):
            if m["mark"] == wanted:
                parts.append(self.unescaped(formatted[at : m.start()]))
                at = m.end()
                wanted = {self.begin: self.middle, self.middle: self.end, self.end: self.begin}[wanted]
                if wanted == self.begin:
                    turns.append((parts[1], parts[2]))
                    parts = []
        if at != len(formatted):
            raise ValueError("text after the last turn")
        return turns


SEGMENTS = "conv_id bigint, turn_no int, part int, text string, loss boolean, valid boolean"


def _sorted_turns(df: DataFrame, conv: str, turn: str, role: str, text: str) -> DataFrame:
    """One row for each turn, dealt by conversation and in its order."""
    picked = df.select(
        F.col(conv).cast("bigint").alias("conv_id"),
        F.col(turn).cast("bigint").alias("turn"),
        F.coalesce(F.col(role).cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"),
    )
    return picked.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def _turns(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for batch in batches:
        for lo in range(0, batch.num_rows, 1024):
            few = batch.slice(lo, 1024)
            yield from zip(few.column(0).to_pylist(), few.column(2).to_pylist(), few.column(3).to_pylist(), strict=True)


def _formatted(batches: Iterator[pa.RecordBatch], template: Template) -> Iterator[tuple]:
    """(conversation, turn number, segments, whether the turns up to here are in a valid order)."""
    last, state, number = (), "start", 0
    for conv, role, text in _turns(batches):
        if last != (conv,):
            last, state, number = (conv,), "start", 0
        state = template.moves.get((state, role), "invalid")
        yield conv, number, template.turn(role, text), state != "invalid"
        number += 1


def segments_of(df: DataFrame, template: Template | None = None, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Rows (conv_id, turn_no, part, text, loss, valid): the segments of every turn, in order within a partition."""
    t = template or Template()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for conv_id, number, parts, valid in _formatted(batches, t):
            rows += [(conv_id, number, k, s, loss, valid) for k, (s, loss) in enumerate(parts)]
            held += sum(len(s) for s, _ in parts)
            if held > 1 << 22 or len(rows) > 4096:
                yield _batch(rows, SEGMENT_FIELDS)
                rows, held = [], 0
        yield _batch(rows, SEGMENT_FIELDS)

    return _sorted_turns(df, conv, turn, role, text).mapInArrow(kernel, SEGMENTS)


SEGMENT_FIELDS = pa.schema([("conv_id", pa.int64()), ("turn_no", pa.int32()), ("part", pa.int32()), ("text", pa.string()), ("loss", pa.bool_()), ("valid", pa.bool_())])
DIGEST_FIELDS = pa.schema(
    [("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64()), ("valid", pa.bool_())]
)


def _batch(rows: list[tuple], fields: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, fields, strict=True)], schema=fields)


class _Digest:
    """What is read back from the segments of one conversation."""

    def __init__(self, conv):
        self.conv, self.turns, self.loss_chars, self.chars, self.last = conv, 0, 0, 0, True
        self.text, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, parts, template: Template) -> None:
        whole = "".join(s for s, _ in parts)
        self.chars += len(whole)
        for role, text in template.parse(whole):
            self.turns += 1
            self.text.update(f"{role}\n{text}\n".encode())
        for s, loss in parts:
            if loss:
                text = template.unescaped(s)
                self.loss_chars += len(text)
                self.loss.update(text.encode())

    def row(self, valid: bool) -> tuple:
        return self.conv, self.turns, self.text.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars, valid


def digests(df: DataFrame, template: Template | None = None, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """One row for each conversation, read back from its formatted segments; the conversation is valid if the machine ends well."""
    t = template or Template()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        now: _Digest | None = None
        state = "start"
        for conv_id, number, parts, _ in _formatted(batches, t):
            if number == 0:
                if now:
                    rows.append(now.row(state in t.final))
                now, state = _Digest(conv_id), "start"
            now.add(parts, t)
            state = t.moves.get((state, t.parse("".join(s for s, _ in parts))[0][0]), "invalid")
            if len(rows) > 2048:
                yield _batch(rows, DIGEST_FIELDS)
                rows = []
        if now:
            rows.append(now.row(state in t.final))
        yield _batch(rows, DIGEST_FIELDS)

    return _sorted_turns(df, conv, turn, role, text).mapInArrow(kernel, "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint, valid boolean")
