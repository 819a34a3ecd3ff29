"""Chat formatting (operator 10): a finite-state machine over roles and a declarative template.

The template says how each role's turn opens and closes and whether its text counts for the loss.
Control strings inside texts are escaped by a backslash after their first character (and one more for
each that stands there already), which ``unescape`` takes back. Formatting streams over turns that
are sorted by conversation; it holds one turn at a time, however long a conversation is.

Cases: null text or role: empty; unknown roles get a named frame and no loss, and make the
conversation invalid; a turn order that the machine forbids is formatted all the same, and flagged;
rows with equal ``(conv_id, turn)`` are all kept, ordered by role and text; null ``turn`` comes first;
rows with null ``conv_id`` form one conversation; further columns are ignored; no rows: no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from blockpress.llm.common import free_columns


@dataclass(frozen=True)
class Frame:
    """What stands around a turn's text, and whether the text is learnt."""

    opening: str
    closing: str
    loss: bool = False


@dataclass(frozen=True)
class Template:
    frames: dict[str, Frame]
    #: Role of the turn before ("" at the start) -> roles that may follow.
    follows: dict[str, tuple[str, ...]]
    #: Strings with a meaning; none may have another's first character after its own first.
    control: tuple[str, ...]
    #: Around the name of a role without a frame.
    naming: tuple[str, str] = ("[ROLE]", "[/ROLE]")
    ends: tuple[str, ...] = ("assistant",)
    _find: re.Pattern = field(init=False, repr=False, compare=False)
    _back: re.Pattern = field(init=False, repr=False, compare=False)

    def __post_init__(self):
        either = "|".join(rf"{re.escape(c[0])}(?=\\*{re.escape(c[1:])})" for c in self.control)
        object.__setattr__(self, "_find", re.compile(either))
        object.__setattr__(self, "_back", re.compile("|".join(rf"(?<={re.escape(c[0])})\\(?=\\*{re.escape(c[1:])})" for c in self.control)))

    def escape(self, text: str) -> str:
        return self._find.sub(lambda m: m[0] + "\\", text)

    def unescape(self, text: str) -> str:
        return self._back.sub("", text)


TEMPLATE = Template(
    frames={
        "system": Frame("[SYS] ", " [/SYS]\n"),
        "user": Frame("[INST] ", " [/INST]\n"),
        "assistant": Frame("<s> ", " </s>\n", loss=True),
    },
    follows={"": ("system", "user"), "system": ("user",), "user": ("assistant",), "assistant": ("user",)},
    control=("[SYS]", "[/SYS]", "[INST]", "[/INST]", "<s>", "</s>", "[ROLE]", "[/ROLE]", "[/TURN]"),
)

SEGMENTS = "conv_id long, turn long, segments array<struct<text:string,loss:boolean>>, allowed boolean"
DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, valid boolean"


def turn_segments(role: str, text: str, template: Template) -> list[dict]:
    """Opening, text and closing of a turn, each with its loss flag."""
    frame = template.frames.get(role)
    if frame is None:
        a, b = template.naming
        frame = Frame(f"{a} {template.escape(role)} {b} ", " [/TURN]\n")
    return [{"text": frame.opening, "loss": False}, {"text": template.escape(text), "loss": frame.loss}, {"text": frame.closing, "loss": False}]


def read_turn(formatted: str, template: Template) -> tuple[str, str]:
    """Role and text of one formatted turn."""
    for role, frame in template.frames.items():
        if formatted.startswith(frame.opening) and formatted.endswith(frame.closing):
            return role, template.unescape(formatted[len(frame.opening) : len(formatted) - len(frame.closing)])
    a, b = template.naming
    name, _, rest = formatted[len(a) + 1 :].partition(f" {b} ")
    return template.unescape(name), template.unescape(rest[: -len(" [/TURN]\n")])


def format_conversations(turns: DataFrame, template: Template = TEMPLATE) -> DataFrame:
    """Segments with loss flags for each turn, in order within each conversation and partition.

    ``allowed`` says whether the machine lets this turn follow the turn before. One shuffle, by
    conversation; partitions come out sorted.
    """
    ordered = free_columns(turns, ["conv_id", "turn", "role", "text"]).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, conv, begun = "", None, False
        for batch in batches:
            ids, numbers = batch.column("conv_id").to_pylist(), batch.column("turn").to_pylist()
            roles, texts = (batch.column(c).fill_null("").to_pylist() for c in ("role", "text"))
            segments, allowed = [], []
            for i, role, text in zip(ids, roles, texts, strict=True):
                if not begun or i != conv:
                    state, conv, begun = "", i, True
                allowed.append(role in template.follows.get(state, ()))
                segments.append(turn_segments(role, text, template))
                state = role
            kind = pa.list_(pa.struct([("text", pa.string()), ("loss", pa.bool_())]))
            yield pa.record_batch([pa.array(ids, pa.int64()), pa.array(numbers, pa.int64()), pa.array(segments, kind), pa.array(allowed, pa.bool_())], names=["conv_id", "turn", "segments", "allowed"])

    return ordered.mapInArrow(emit, SEGMENTS)


def conversation_digests(formatted: DataFrame, template: Template = TEMPLATE) -> DataFrame:
    """Read formatted conversations back, turn by turn, and digest what they hold.

    Takes ``format_conversations``'s result as it is: conversations whole and in order in each partition.
    """

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, open_ = None, None
        done: list[tuple] = []

        def close() -> None:
            done.append((conv, open_["n"], open_["turns"].hexdigest(), open_["chars"], open_["loss"].hexdigest(), open_["all"], open_["valid"] and open_["last"] in template.ends))

        def flush() -> pa.RecordBatch:
            cols = list(zip(*done, strict=True)) or [()] * 7
            done.clear()
            types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.bool_()]
            return pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=[f.split()[0] for f in DIGESTS.split(", ")])

        for batch in batches:
            for i, segments, allowed in zip(batch.column("conv_id").to_pylist(), batch.column("segments").to_pylist(), batch.column("allowed").to_pylist(), strict=True):
                if open_ is None or i != conv:
                    if open_ is not None:
                        close()
                    conv, open_ = i, {"n": 0, "turns": hashlib.sha256(), "chars": 0, "loss": hashlib.sha256(), "all": 0, "valid": True, "last": ""}
                whole = "".join(s["text"] for s in segments)
                role, text = read_turn(whole, template)
                learnt = template.unescape("".join(s["text"] for s in segments if s["loss"]))
                open_["n"] += 1
                open_["turns"].update(f"{role}\n{text}\n".encode())
                open_["chars"] += len(learnt)
                open_["loss"].update(learnt.encode())
                open_["all"] += len(whole)
                open_["valid"] &= allowed
                open_["last"] = role
            yield flush()
        if open_ is not None:
            close()
            yield flush()

    return formatted.mapInArrow(emit, DIGESTS)
