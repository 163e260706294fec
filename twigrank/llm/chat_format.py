"""Chat formatting in budgeted windows.

Prefix sums of turn tokens choose turn-aligned spans; each window starts with the system turn (if the conversation opens
with one) and repeats a bounded run of earlier turns, masked, so that each assistant text bears loss exactly once.

Template: ``<turn:ROLE>`` newline TEXT newline ``</turn>`` newline. In roles and texts a backslash becomes two, ``<`` becomes
``\\<`` and, in roles, ``>`` becomes ``\\>``: an unescaped ``<`` only ever opens a mark, so texts that hold control strings
are read back exactly.
"""

from __future__ import annotations

import hashlib
import re
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.llm.common import by_bytes, slices
from twigrank.llm.token_output import encoder_of

TOKEN = re.compile(r"\w+|[^\w\s]")
MARK = re.compile(r"<turn:((?:[^\\>]|\\.)*)>\n((?:[^\\<]|\\.)*)\n</turn>\n", re.S)
UNESCAPE = re.compile(r"\\(.)", re.S)
WINDOWS = "conv_id long, window long, first_turn long, n_repeated long, n_tokens long, over_budget boolean, text string, loss array<struct<lo:long,hi:long>>"
TURNS = 64  # turns that are read at once; batches are joined up to a megabyte of text


def escape(text: str) -> str:
    return text.replace("\\", "\\\\").replace("<", "\\<")


def unescape(text: str) -> str:
    return UNESCAPE.sub(r"\1", text)


@dataclass(frozen=True)
class Turn:
    role: str
    rendered: str
    lo: int  # of the escaped text within the rendered turn
    hi: int
    tokens: int

    @classmethod
    def all_of(cls, roles: list[str | None], texts: list[str | None], vocabulary: str | None) -> list["Turn"]:
        heads = [f"<turn:{escape(r or '').replace('>', chr(92) + '>')}>\n" for r in roles]
        bodies = [escape(t or "") for t in texts]
        rendered = [f"{head}{body}\n</turn>\n" for head, body in zip(heads, bodies)]
        if vocabulary:
            # the line end after a turn is a token of its own: it follows a mark, and a mark follows it
            encoder = encoder_of(vocabulary)
            last = len(encoder.library(["\n"])[0])
            tokens = (encoder.encode_column(pa.array([x[:-1] for x in rendered], pa.string()))[1] + last).tolist()
        else:
            tokens = [sum(1 for _ in TOKEN.finditer(x)) for x in rendered]
        return [cls(r or "", x, len(h), len(h) + len(b), n) for r, x, h, b, n in zip(roles, rendered, heads, bodies, tokens)]


@dataclass(frozen=True)
class WindowBudget:
    """Tokens of the rendered turn: those of a tokenizers file that every executor has, or else runs of word characters and
    single other characters."""

    vocabulary: str | None = None
    tokens: int = 1024
    history: int = 256  # at most so many of them for repeated turns
    trained_role: str = "assistant"
    system_role: str = "system"


class Windows:
    """Cuts one conversation into windows while its turns stream in; holds one window and the history."""

    def __init__(self, conv: int | None, budget: WindowBudget):
        self.conv, self.budget = conv, budget
        self.system: Turn | None = None
        self.history: deque[Turn] = deque()
        self.repeated: list[Turn] = []
        self.own: list[Turn] = []
        self.seen = self.window = self.first = 0
        self.prefix = [0]  # prefix sums of tokens over the turns of this window

    def room(self) -> int:
        kept = sum(t.tokens for t in self.repeated) + (self.system.tokens if self.system else 0)
        return self.budget.tokens - kept

    def add(self, turn: Turn) -> Iterator[tuple]:
        if not self.seen and turn.role == self.budget.system_role:
            self.system = turn
        elif self.own and self.prefix[-1] + turn.tokens > self.room():
            yield self.close()
        if turn is not self.system:
            # repeated turns give way to a new turn that is long
            while self.repeated and not self.own and turn.tokens > self.room():
                self.repeated.pop(0)
            self.own.append(turn)
            self.prefix.append(self.prefix[-1] + turn.tokens)
            self.history.append(turn)
            # the longest run of latest turns within the history's budget
            while self.history and sum(t.tokens for t in self.history) > self.budget.history:
                self.history.popleft()
        self.seen += 1

    def close(self) -> tuple:
        parts, loss, at = [], [], 0
        lead = [self.system] if self.system else []
        for k, turn in enumerate([*lead, *self.repeated, *self.own]):
            if k >= len(lead) + len(self.repeated) and turn.role == self.budget.trained_role:
                loss.append({"lo": at + turn.lo, "hi": at + turn.hi})
            parts.append(turn.rendered)
            at += len(turn.rendered)
        tokens = self.budget.tokens - self.room() + self.prefix[-1]
        row = (self.conv, self.window, self.first, len(lead) * (self.window > 0) + len(self.repeated), tokens, tokens > self.budget.tokens, "".join(parts), loss)
        self.first = self.seen
        self.window += 1
        self.repeated, self.own, self.prefix = list(self.history), [], [0]
        return row

    def end(self) -> Iterator[tuple]:
        if self.own or not self.window:
            yield self.close()


def format_conversations(df: DataFrame, budget: WindowBudget = WindowBudget()) -> DataFrame:
    """Windows of all conversations: conv_id, window, first_turn (index of the first new turn), n_repeated, n_tokens,
    over_budget (one turn alone exceeds it; turns are never cut), text and loss (spans of text that bear loss).

    Turns go by turn, then role and text (ties, repeated rows: each is a turn); null turns come last. Null text and role
    are empty. Rows with a null conv_id are one conversation of null id. Rows are dealt by conversation and sorted there
    on disk, and a conversation streams through one task with one window in memory, however long it is. Other columns of
    df are not read.
    """
    arrow = pa.schema([("conv_id", pa.int64()), ("window", pa.int64()), ("first_turn", pa.int64()), ("n_repeated", pa.int64()), ("n_tokens", pa.int64()), ("over_budget", pa.bool_()), ("text", pa.string()), ("loss", pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())])))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: Windows | None = None
        rows: list[tuple] = []
        for batch in by_bytes(batches, "text", 1 << 20, TURNS):
            turns = Turn.all_of(batch.column("role").to_pylist(), batch.column("text").to_pylist(), budget.vocabulary)
            for conv, turn in zip(batch.column("conv_id").to_pylist(), turns):
                if state is None or conv != state.conv:
                    if state:
                        rows.extend(state.end())
                    state = Windows(conv, budget)
                rows.extend(state.add(turn))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)
                rows = []
        if state:
            rows.extend(state.end())
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    turns = df.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    order = [F.col("conv_id").asc_nulls_first(), F.col("turn").asc_nulls_last(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first()]
    return turns.repartition("conv_id").sortWithinPartitions(*order).mapInArrow(run, WINDOWS)


class ReadBack:
    """Turns and loss text of one conversation, from its windows in order."""

    def __init__(self, conv: int | None):
        self.conv, self.turns, self.chars, self.loss_chars = conv, 0, 0, 0
        self.all, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, text: str, repeated: int, loss: list[dict]) -> None:
        self.chars += len(text)
        at = 0
        for k, m in enumerate(MARK.finditer(text)):
            if m.start() != at:
                raise ValueError(f"conversation {self.conv}: window text is no sequence of turns at {at}")
            at = m.end()
            if k >= repeated:
                self.turns += 1
                self.all.update(f"{unescape(m[1])}\n{unescape(m[2])}\n".encode())
        if at != len(text):
            raise ValueError(f"conversation {self.conv}: window text is no sequence of turns at {at}")
        for span in loss:
            plain = unescape(text[span["lo"] : span["hi"]])
            self.loss_chars += len(plain)
            self.loss.update(plain.encode())

    def row(self) -> tuple:
        return self.conv, self.turns, self.all.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars


DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def read_back(windows: DataFrame) -> DataFrame:
    """What the windows hold, for each conversation, by parsing and unescaping their texts. An empty table gives none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, state, rows = [x.split()[0] for x in DIGEST.split(", ")], None, []
        for batch in slices(batches, TURNS):
            for conv, text, repeated, loss in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "text", "n_repeated", "loss"))):
                if state is None or conv != state.conv:
                    if state:
                        rows.append(state.row())
                    state = ReadBack(conv)
                state.add(text, repeated, loss)
        if state:
            rows.append(state.row())
        if rows:
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)

    order = [F.col("conv_id").asc_nulls_first(), F.col("window").asc()]
    return windows.select("conv_id", "window", "text", "n_repeated", "loss").repartition("conv_id").sortWithinPartitions(*order).mapInArrow(run, DIGEST)
