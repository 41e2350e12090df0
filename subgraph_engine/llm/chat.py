"""Chat formatting by a finite-state machine over roles and a declarative template.

The template names the marks around each role's text, which roles' texts carry loss, and which
role may follow which. Formatting emits segments (text, loss flag) turn by turn; ``Reader`` takes
formatted text and gives the turns back. Control strings inside texts are broken by a backslash
behind their first character (backslashes are doubled), so a text can hold any mark and still
come back unchanged.

Turns of a conversation go by ``turn``, then role, then text, nulls first; repeated turns are kept.
Null texts and roles count as empty. Conversations whose roles come in an order that the machine
doesn't allow are formatted as they are and have ``valid`` false. A conversation is one stream of
rows through one task, never held as a whole, so its length is not bound by memory.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import slices


@dataclass(frozen=True)
class Template:
    """Marks by role; ``other`` frames roles without marks of their own, with the role's name inside."""

    begin: str = "<s>"
    marks: dict[str, tuple[str, str]] = field(default_factory=lambda: {"system": ("<<SYS>>", "<</SYS>>"), "user": ("[INST]", "[/INST]"), "assistant": ("[ANS]", "</s>")})
    other: tuple[str, str, str] = ("[ROLE]", "[/ROLE]", "[END]")
    loss_roles: frozenset[str] = frozenset({"assistant"})
    follows: dict[str, frozenset[str]] = field(default_factory=lambda: {"": frozenset({"system", "user"}), "system": frozenset({"user"}), "user": frozenset({"assistant"}), "assistant": frozenset({"user"})})
    last: frozenset[str] = frozenset({"assistant"})

    def control(self) -> list[str]:
        """All strings that texts must not hold as they are, longest first."""
        found = {self.begin, *self.other, *(m for pair in self.marks.values() for m in pair)}
        return sorted(found - {""}, key=lambda x: (-len(x), x))


class Formatter:
    """Emits a conversation's segments, and keeps the machine's state."""

    def __init__(self, template: Template) -> None:
        self.template = template
        self._control = re.compile("|".join(map(re.escape, ["\\", *template.control()])))
        self.state, self.valid, self.turns = "", True, 0

    def escape(self, text: str) -> str:
        return self._control.sub(lambda m: m[0][0] + "\\" + m[0][1:], text)

    def turn(self, role: str, text: str) -> Iterator[tuple[str, bool]]:
        t = self.template
        self.valid &= role in t.follows.get(self.state, ())
        self.state = role
        if not self.turns:
            yield t.begin, False
        self.turns += 1
        if role in t.marks:
            start, end = t.marks[role]
        else:
            start, end = t.other[0] + self.escape(role) + t.other[1], t.other[2]
        yield start, False
        yield self.escape(text), role in t.loss_roles
        yield end, False

    def ended(self) -> bool:
        """Whether the whole conversation was valid."""
        return self.valid and self.state in self.template.last


class Reader:
    """Turns of formatted text, which may come in parts."""

    def __init__(self, template: Template) -> None:
        self.template, self._rest, self._begun = template, "", False
        self._starts = {start: role for role, (start, _) in template.marks.items()}

    def _turn(self) -> tuple[str, str] | None:
        t, text = self.template, self._rest
        for start, role in self._starts.items():
            if text.startswith(start):
                at, end = len(start), t.marks[role][1]
                break
        else:
            if not text.startswith(t.other[0]):
                if text and not any(x.startswith(text) for x in (*self._starts, t.other[0])):
                    raise ValueError(f"no turn starts at {text[:40]!r}")
                return None
            if (stop := text.find(t.other[1], len(t.other[0]))) < 0:
                return None
            role, at, end = unescape(text[len(t.other[0]) : stop]), stop + len(t.other[1]), t.other[2]
        if (stop := text.find(end, at)) < 0:
            return None
        self._rest = text[stop + len(end) :]
        return role, unescape(text[at:stop])

    def feed(self, part: str) -> Iterator[tuple[str, str]]:
        """The turns that this part completes."""
        self._rest += part
        if not self._begun:
            if len(self._rest) < len(self.template.begin):
                return
            if not self._rest.startswith(self.template.begin):
                raise ValueError("the text doesn't begin as the template says")
            self._rest, self._begun = self._rest[len(self.template.begin) :], True
        while (turn := self._turn()) is not None:
            yield turn


def unescape(text: str) -> str:
    """What ``Formatter.escape`` took: a doubled backslash is one, a single one goes."""
    return re.sub(r"\\(\\?)", r"\1", text) if "\\" in text else text


def _ordered(conversations: DataFrame) -> DataFrame:
    picked = conversations.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    return picked.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def format_segments(conversations: DataFrame, template: Template | None = None) -> DataFrame:
    """``conv_id, segment, text, loss``: the formatted conversations, segment by segment."""
    template = template or Template()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, own, n = object(), Formatter(template), 0
        for batch in slices(batches):
            out: list[tuple] = []
            for x in batch.to_pylist():
                if x["conv_id"] != conv:
                    conv, own, n = x["conv_id"], Formatter(template), 0
                for text, loss in own.turn(x["role"], x["text"]):
                    out.append((conv, n, text, loss))
                    n += 1
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["conv_id", "segment", "text", "loss"])

    return _ordered(conversations).mapInArrow(rows, "conv_id long, segment long, text string, loss boolean")


class _Digest:
    """What one conversation comes to, read back from its formatted segments."""

    def __init__(self, template: Template) -> None:
        self.own, self.reader = Formatter(template), Reader(template)
        self.turns, self.loss = hashlib.sha256(), hashlib.sha256()
        self.n, self.loss_chars, self.chars = 0, 0, 0

    def add(self, role: str, text: str) -> None:
        for segment, loss in self.own.turn(role, text):
            self.chars += len(segment)
            if loss:
                bare = unescape(segment)
                self.loss_chars += len(bare)
                self.loss.update(bare.encode())
            for read_role, read_text in self.reader.feed(segment):
                self.n += 1
                self.turns.update(f"{read_role}\n{read_text}\n".encode())

    def row(self, conv: int | None) -> tuple:
        return conv, self.n, self.turns.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars, self.own.ended()


def format_digests(conversations: DataFrame, template: Template | None = None) -> DataFrame:
    """A row for each conversation, read back from its formatted segments.

    conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, valid.
    """
    template = template or Template()
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "valid"]
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.bool_())

    def batch_of(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, own, out = None, None, []
        for batch in slices(batches):
            for x in batch.to_pylist():
                if own is None or x["conv_id"] != conv:
                    if own is not None:
                        out.append(own.row(conv))
                    conv, own = x["conv_id"], _Digest(template)
                own.add(x["role"], x["text"])
            if len(out) >= 1000:
                yield batch_of(out)
                out = []
        if own is not None:
            out.append(own.row(conv))
        if out:
            yield batch_of(out)

    return _ordered(conversations).mapInArrow(rows, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, valid boolean")
