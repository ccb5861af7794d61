"""Chat formatting: a finite-state machine over roles and a declarative template.

The machine's states are the roles that may come next; a turn that is not allowed marks its
conversation as invalid but is formatted all the same, so nothing is lost. Every turn gives three
segments (opening mark, text, closing mark), each with its loss flag; only assistant texts carry
loss. Control strings inside texts are escaped: backslashes are doubled and a backslash is put after
the first character of each control string, which is undone exactly when the output is read.

Turns are streamed in order of conversation and turn, so memory holds one turn at a time, whatever
a conversation's length.

Defined results: null text is empty text; a null role is the empty role; rows with equal conversation
and turn are ordered by role, then text, and all kept; a null turn sorts first; a null conversation
is a conversation of its own; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.llm.common import ship


@dataclass(frozen=True)
class Template:
    """What surrounds each role's text, which roles carry loss, and which role may follow which."""

    # fixed values: the public instruction template with a header for roles it does not know
    marks: dict[str, tuple[str, str]] = field(
        default_factory=lambda: {
            "system": ("<<SYS>>", "<</SYS>>"),
            "user": ("<s>[INST]", "[/INST]"),
            "assistant": ("<ANS>", "</s>"),
        }
    )
    other: tuple[str, str, str] = ("<ROLE>", "</ROLE>", "<END>")
    loss: tuple[str, ...] = ("assistant",)
    follows: dict[str, tuple[str, ...]] = field(
        default_factory=lambda: {
            "": ("system", "user"),
            "system": ("user",),
            "user": ("assistant",),
            "assistant": ("user",),
        }
    )
    final: tuple[str, ...] = ("assistant",)

    def controls(self) -> list[str]:
        return sorted({"<s>", "[INST]", *[m for pair in self.marks.values() for m in pair], *self.other}, key=lambda x: (-len(x), x))


class Formatter:
    def __init__(self, template: Template | None = None):
        self.template = template or Template()
        controls = self.template.controls()
        self._find = re.compile("|".join(map(re.escape, controls)))
        self._open = {start: role for role, (start, _) in self.template.marks.items()}
        self._token = re.compile("|".join(map(re.escape, controls)))

    def escape(self, text: str) -> str:
        doubled = text.replace("\\", "\\\\")
        out = self._find.sub(lambda m: m[0][0] + "\\" + m[0][1:], doubled)
        while self._find.search(out):  # a control string that overlapped one just broken
            out = self._find.sub(lambda m: m[0][0] + "\\" + m[0][1:], out)
        return out

    @staticmethod
    def unescape(text: str) -> str:
        return re.sub(r"\\(\\?)", r"\1", text)

    def segments(self, role: str, text: str) -> list[tuple[str, bool]]:
        """(text, loss) pieces of one turn: opening mark, text, closing mark."""
        if role in self.template.marks:
            start, end = self.template.marks[role]
        else:
            a, b, end = self.template.other
            start = a + self.escape(role) + b
        return [(start, False), (self.escape(text), role in self.template.loss), (end, False)]

    def parse(self, formatted: str) -> list[tuple[str, str]]:
        """The turns of a formatted conversation."""
        turns, at = [], 0
        a, b, end = self.template.other
        while at < len(formatted):
            if formatted.startswith(a, at):
                middle = formatted.index(b, at)
                role, at, stop = self.unescape(formatted[at + len(a) : middle]), middle + len(b), end
            else:
                start = next(m for m in self._open if formatted.startswith(m, at))
                role, at = self._open[start], at + len(start)
                stop = self.template.marks[role][1]
            close = formatted.index(stop, at)
            turns.append((role, self.unescape(formatted[at:close])))
            at = close + len(stop)
        return turns

    def allowed(self, before: str, role: str) -> bool:
        return role in self.template.follows.get(before, ())


_SEGMENT = "conv_id long, turn_no long, segment_no int, text string, loss boolean, valid boolean"


def _ordered(batches) -> Iterator[tuple]:
    for batch in batches:
        yield from zip(*[c.to_pylist() for c in batch.columns])


def _flush(rows: list[tuple], names: list[str], types: list[pa.DataType]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=names)


def _emit(template: Template):
    def run(batches):
        form = Formatter(template)
        names = ["conv_id", "turn_no", "segment_no", "text", "loss", "valid"]
        types = [pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.bool_(), pa.bool_()]
        held, weight, seen, state, number = [], 0, (), "", 0
        for conv, _, role, text in _ordered(batches):
            if seen != (conv,):
                seen, state, number = (conv,), "", 0
            valid = form.allowed(state, role)
            for k, (piece, loss) in enumerate(form.segments(role, text)):
                held.append((conv, number, k, piece, loss, valid))
                weight += len(piece) + 40
            state, number = role, number + 1
            if weight > 1 << 22:
                yield _flush(held, names, types)
                held, weight = [], 0
        if held:
            yield _flush(held, names, types)

    return run


def in_order(conversations: DataFrame) -> DataFrame:
    """Turns with nulls replaced, each conversation whole and sorted in one partition."""
    text = [F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in ("role", "text")]
    turns = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), *text)
    return turns.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def format_chats(conversations: DataFrame, template: Template | None = None) -> DataFrame:
    """Segments in order within each partition: conv_id, turn_no, segment_no, text, loss, valid."""
    ship(conversations.sparkSession)
    return in_order(conversations).mapInArrow(_emit(template or Template()), _SEGMENT)


def _digest(template: Template):
    def run(batches):
        form = Formatter(template)
        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "valid"]
        types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.bool_()]
        done: list[tuple] = []
        seen, now = (), None

        def close():
            done.append((seen[0], now["n"], now["turns"].hexdigest(), now["loss_chars"], now["loss"].hexdigest(), now["chars"], now["valid"] and now["last"] in form.template.final))

        buffer: list[str] = []
        for conv, _, segment, text, loss, valid in _ordered(batches):
            if seen != (conv,):
                if now:
                    close()
                seen, now = (conv,), {"n": 0, "turns": hashlib.sha256(), "loss_chars": 0, "loss": hashlib.sha256(), "chars": 0, "valid": True, "last": ""}
            buffer = [text] if segment == 0 else [*buffer, text]
            now["chars"] += len(text)
            if loss:
                plain = form.unescape(text)
                now["loss_chars"] += len(plain)
                now["loss"].update(plain.encode("utf-8", "surrogatepass"))
            if segment == 2:
                for role, plain in form.parse("".join(buffer)):
                    now["n"] += 1
                    now["turns"].update(f"{role}\n{plain}\n".encode("utf-8", "surrogatepass"))
                    now["last"] = role
                now["valid"] &= valid
            if len(done) >= 5000:
                yield _flush(done, names, types)
                done = []
        if now:
            close()
        if done:
            yield _flush(done, names, types)

    return run


def read_back(segments: DataFrame, template: Template | None = None) -> DataFrame:
    """One row per conversation, from the formatted output alone.

    conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, valid. segments must be
    in the order in which format_chats leaves them.
    """
    kinds = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, valid boolean"
    return segments.mapInArrow(_digest(template or Template()), kinds)
