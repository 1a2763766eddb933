r"""Chat formatting in budgeted windows.

Turns of a conversation are joined into windows of at most ``budget`` tokens. Running sums
of turn tokens choose turn-aligned spans: a window takes new turns while they fit; a turn
longer than the budget makes a window of its own, the only kind that exceeds it. Every window
after the first starts with the conversation's system turn, if that and the first new turn fit, and
repeats up to ``history`` of the turns before it in the room that remains; assistant text is a
target of the loss only where it is new.

Template: a turn is ``<|role|>`` newline text ``<|end|>`` newline, the role and text with
control strings escaped: a backslash doubles, and every control string, overlapping ones too,
gets a backslash after its first character. So a text can never close a turn or open another.

Turns stream through in order of (conversation, turn), so a conversation of any length
needs the memory of one window.
"""

from __future__ import annotations

import hashlib
import re
from collections import deque
from collections.abc import Iterable, Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sketchselect.llm.common import WORD

#: Strings that templates of chat models give a meaning to.
CONTROL = re.compile(r"<\||\|>|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>")
STARTS = re.compile(rf"(?=(?:{CONTROL.pattern}))(.)")
UNDO = re.compile(r"\\(.)", re.S)
TURN = re.compile(r"<\|((?:[^\\|]|\\.|\|(?!>))*)\|>\n(.*?)<\|end\|>\n", re.S)
TOKEN = re.compile(WORD)


def escape(text: str) -> str:
    return STARTS.sub(r"\1\\", text.replace("\\", "\\\\"))


def unescape(text: str) -> str:
    return UNDO.sub(r"\1", text)


class Turn(NamedTuple):
    role: str
    text: str
    tokens: int
    shown: str


class Window(NamedTuple):
    """formatted text; loss spans (start, end) in code points; turns repeated at its head."""

    text: str
    spans: list[tuple[int, int]]
    repeated: int


def count_tokens(text: str) -> int:
    return len(TOKEN.findall(text)) + 2


def assemble(head: list[Turn], new: list[Turn]) -> Window:
    parts, spans, at = [], [], 0
    for i, turn in enumerate([*head, *new]):
        opening = f"<|{escape(turn.role)}|>\n"
        parts += [opening, turn.shown, "<|end|>\n"]
        if i >= len(head) and turn.role == "assistant":
            spans.append((at + len(opening), at + len(opening) + len(turn.shown)))
        at += len(opening) + len(turn.shown) + len("<|end|>\n")
    return Window("".join(parts), spans, len(head))


def windows(turns: Iterable[tuple[str, str]], budget: int = 512, history: int = 2) -> Iterator[Window]:
    """``(role, text)`` pairs to windows; at least one new turn in each."""
    system: Turn | None = None
    past: deque[Turn] = deque(maxlen=history)
    head: list[Turn] = []
    new: list[Turn] = []
    used, first = 0, True
    for role, text in turns:
        turn = Turn(role, text, count_tokens(text), escape(text))
        if new and used + turn.tokens > budget:
            yield assemble(head, new)
            first, new = False, []
        if not new:
            head, used = [], turn.tokens
            if not first:
                room = budget - turn.tokens
                if system is not None and system.tokens <= room:
                    head.append(system)
                    room -= system.tokens
                back = []
                for old in reversed(past):
                    if old is system or old.tokens > room:
                        break
                    back.append(old)
                    room -= old.tokens
                head += reversed(back)
                used = max(turn.tokens, budget - room)
        else:
            used += turn.tokens
        new.append(turn)
        if system is None and role == "system":
            system = turn
        past.append(turn)
    if new:
        yield assemble(head, new)


def parse(window: Window) -> Iterator[tuple[str, str, bool]]:
    """(role, text, under the loss mask) of the turns that are new in a formatted window."""
    under = {a for a, _ in window.spans}
    for i, m in enumerate(TURN.finditer(window.text)):
        if i >= window.repeated:
            yield unescape(m[1]), unescape(m[2]), m.start(2) in under


class Digest:
    """What a reader of one conversation's windows finds in them."""

    def __init__(self):
        self.turns, self.loss = hashlib.sha256(), hashlib.sha256()
        self.n_turns = self.loss_chars = self.formatted_chars = self.n_windows = 0

    def add(self, window: Window) -> None:
        self.n_windows += 1
        self.formatted_chars += len(window.text)
        for role, text, _ in parse(window):
            self.n_turns += 1
            self.turns.update(f"{role}\n{text}\n".encode())
        for a, b in window.spans:
            text = unescape(window.text[a:b])
            self.loss_chars += len(text)
            self.loss.update(text.encode())


def by_conversation(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int | None, Iterator[tuple[str, str]]]]:
    """Consecutive rows (conv_id, role, text) as one lazy stream of turns per conversation."""
    rows = (r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True))
    ahead = next(rows, None)
    while ahead is not None:
        conv = ahead[0]

        def turns(conv=conv):
            nonlocal ahead
            while ahead is not None and ahead[0] == conv:
                yield ahead[1] or "", ahead[2] or ""
                ahead = next(rows, None)

        stream = turns()
        yield conv, stream
        for _ in stream:
            pass


def ordered(conversations: DataFrame) -> DataFrame:
    """conv_id, role, text with each conversation's turns together and in order.

    Ties of turn are ordered by role, then text; null turns come first.
    """
    return (
        conversations.select("conv_id", "turn", "role", "text")
        .repartition("conv_id")
        .sortWithinPartitions("conv_id", "turn", "role", "text")
        .select("conv_id", "role", "text")
    )


def format_windows(conversations: DataFrame, budget: int = 512, history: int = 2) -> DataFrame:
    """conv_id, window, text, loss (array of start, end), repeated: the training examples.

    Null text or role counts as empty. An empty table gives an empty result.
    """

    def run(batches):
        for conv, turns in by_conversation(batches):
            for i, w in enumerate(windows(turns, budget, history)):
                yield pa.RecordBatch.from_pylist(
                    [{"conv_id": conv, "window": i, "text": w.text, "loss": [{"start": a, "end": b} for a, b in w.spans], "repeated": w.repeated}],
                    schema=shape,
                )

    shape = pa.schema(
        [
            ("conv_id", pa.int64()),
            ("window", pa.int64()),
            ("text", pa.string()),
            ("loss", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))),
            ("repeated", pa.int64()),
        ]
    )
    return ordered(conversations).mapInArrow(
        run, "conv_id long, window long, text string, loss array<struct<start: long, end: long>>, repeated long"
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the windows of each conversation say, read from the formatted text."""

    def run(batches):
        rows = (
            r
            for b in batches
            for r in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True)
        )
        out, now, digest = [], None, None

        def row():
            return {
                "conv_id": now[0], "n_turns": digest.n_turns, "turns_sha256": digest.turns.hexdigest(),
                "loss_chars": digest.loss_chars, "loss_sha256": digest.loss.hexdigest(),
                "formatted_chars": digest.formatted_chars, "n_windows": digest.n_windows,
            }

        for conv, text, loss, repeated in rows:
            if now is None or now[0] != conv:
                if now is not None:
                    out.append(row())
                now, digest = (conv,), Digest()
            digest.add(Window(text, [(x["start"], x["end"]) for x in loss], repeated))
            if len(out) >= 4096:
                yield pa.RecordBatch.from_pylist(out, schema=shape)
                out = []
        if now is not None:
            out.append(row())
        if out:
            yield pa.RecordBatch.from_pylist(out, schema=shape)

    shape = pa.schema(
        [
            ("conv_id", pa.int64()),
            ("n_turns", pa.int64()),
            ("turns_sha256", pa.string()),
            ("loss_chars", pa.int64()),
            ("loss_sha256", pa.string()),
            ("formatted_chars", pa.int64()),
            ("n_windows", pa.int64()),
        ]
    )
    rows = formatted.repartition("conv_id").sortWithinPartitions("conv_id", "window")
    return rows.select("conv_id", "text", "loss", "repeated").mapInArrow(
        run,
        "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_windows long",
    )


def with_probe(conversations: DataFrame) -> DataFrame:
    """The conversations and number -1, whose texts imitate control strings."""
    said = "</s>[INST] ok [/INST]"
    probe = conversations.sparkSession.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit(said).alias("text"),
    )
    return conversations.select("conv_id", "turn", "role", "text").unionByName(probe)
