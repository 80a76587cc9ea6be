"""Chat formatting in budgeted windows.

Each conversation is cut into windows of at most `budget` tokens. Prefix sums of the turns' tokens choose
turn-aligned spans: a window takes the system turn (if the conversation begins with one), then repeats the
latest earlier turns that fit in `history` tokens, then takes new turns while they fit. The loss mask covers
the assistant texts of new turns alone, so that a repeated target is never learned twice. A single turn
above the budget gets a window of its own and is flagged, never cut.

Control strings inside texts are replaced by numbered escapes, which are undone on reading.
Rows may come in any order; turns are read by turn, then role, then text, nulls first. A null text or role
is empty; null conversation ids form one conversation. Repeated rows are repeated turns. An empty table
gives no rows. Memory is bounded by the budget plus the longest turn, however long a conversation is.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

NEW, AGAIN, END = "<|turn|>", "<|again|>", "<|end|>"
# The template's own marks, then marks of well-known chat formats.
CONTROL = [
    NEW, AGAIN, END, "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<|startoftext|>", "<s>", "</s>", "<unk>", "<pad>",
    "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<start_of_turn>", "<end_of_turn>",
]
_PLACE = {c: i for i, c in enumerate(CONTROL)}
_TO_ESCAPE = re.compile("|".join(["\\\\", *map(re.escape, sorted(CONTROL, key=len, reverse=True))]))
_ESCAPED = re.compile(r"\\(\\|n|\d+;)")
_TURN = re.compile(r"<\|(turn|again)\|>([^\n]*)\n(.*?)<\|end\|>", re.DOTALL)
_WORD = re.compile(r"\S+")

WINDOWS = "conv_id long, window_no long, formatted string, loss_spans array<long>, n_new int, n_repeated int, n_tokens long, over_budget boolean"
DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_windows long"


def escape(text: str) -> str:
    return _TO_ESCAPE.sub(lambda m: "\\\\" if m[0] == "\\" else f"\\{_PLACE[m[0]]};", text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(lambda m: "\\" if m[1] == "\\" else "\n" if m[1] == "n" else CONTROL[int(m[1][:-1])], text)


def count_tokens(text: str) -> int:
    """Words, and four for the turn's marks."""
    return 4 + sum(1 for _ in _WORD.finditer(text))


class _Conversation:
    """The turns of one conversation, one after another; keeps no more turns than a window may need."""

    def __init__(self, conv_id: int | None, budget: int, history: int):
        self.conv_id, self.budget, self.history = conv_id, budget, history
        self.system: tuple[str, str, int] | None = None
        self.turns: list[tuple[str, str, int]] = []
        self.sums = [0]  # tokens of turns[:i]
        self.fresh = 0  # turns from here on are new in the open window
        self.start = 0  # the open window begins here
        self.windows = self.seen = 0

    def room(self) -> int:
        return self.budget - (self.system[2] if self.system and self.windows else 0)

    def add(self, role: str, text: str) -> tuple | None:
        """Takes a turn; returns the window that it closed."""
        turn, done = (role, text, count_tokens(text)), None
        if len(self.turns) > self.fresh and self.sums[-1] - self.sums[self.start] + turn[2] > self.room():
            done = self.close()
            left = max(0, min(self.history, self.room() - turn[2]))
            self.start = bisect_left(self.sums, self.sums[-1] - left)
            if self.system and self.first_kept == 0 and self.start == 0:
                self.start = 1  # the system turn is repeated anyhow
            self.first_kept += self.start
            self.turns, base = self.turns[self.start :], self.sums[self.start]
            self.sums = [s - base for s in self.sums[self.start :]]
            self.start, self.fresh = 0, len(self.turns)
        if not self.seen:
            self.first_kept = 0
            if role == "system":
                self.system = turn
        self.seen += 1
        self.turns.append(turn)
        self.sums.append(self.sums[-1] + turn[2])
        return done

    def close(self) -> tuple:
        parts, spans, size = [], [], 0
        again = ([self.system] if self.system and self.windows else []) + self.turns[self.start : self.fresh]
        for i, (role, text, _) in enumerate(again + self.turns[self.fresh :]):
            head = f"{NEW if i >= len(again) else AGAIN}{escape(role).replace(chr(10), chr(92) + 'n')}\n"
            body = escape(text)
            if i >= len(again) and role == "assistant":
                spans += [size + len(head), size + len(head) + len(body)]
            parts.append(f"{head}{body}{END}")
            size += len(parts[-1])
        tokens = sum(t[2] for t in again) + self.sums[-1] - self.sums[self.fresh]
        out = (self.conv_id, self.windows, "".join(parts), spans, len(self.turns) - self.fresh, len(again), tokens, tokens > self.budget)
        self.windows += 1
        return out


def _same(a: object, b: object) -> bool:
    return a == b or (pd.isna(a) and pd.isna(b))


def format_windows(conversations: DataFrame, budget: int = 512, history: int = 128) -> DataFrame:
    """One row a window: the text with its marks, the loss mask as start and end offsets, and what it holds."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at: _Conversation | None = None
        out: list[tuple] = []
        columns = [x.split()[0] for x in WINDOWS.split(", ")]
        for frame in frames:
            for conv_id, role, text in zip(frame["conv_id"], frame["role"], frame["text"], strict=True):
                conv_id = None if pd.isna(conv_id) else int(conv_id)
                if at is None or at.conv_id != conv_id:
                    if at is not None:
                        out.append(at.close())
                    at = _Conversation(conv_id, budget, history)
                if done := at.add(role, text):
                    out.append(done)
                if len(out) >= 2000:
                    yield pd.DataFrame(out, columns=columns).astype({"conv_id": "Int64"})
                    out = []
        if at is not None:
            out.append(at.close())
        if out:
            yield pd.DataFrame(out, columns=columns).astype({"conv_id": "Int64"})

    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text").mapInPandas(work, WINDOWS)


def read_windows(formatted: str, spans: list[int]) -> Iterator[tuple[str, str, bool]]:
    """The new turns of a window as (role, text, under the loss mask), unescaped."""
    masked = {spans[i]: spans[i + 1] for i in range(0, len(spans), 2)}
    at = 0
    for m in _TURN.finditer(formatted):
        if m.start() != at:
            raise ValueError("text between turns")
        at = m.end()
        if m[1] == "turn":
            yield unescape(m[2]), unescape(m[3]), m.start(3) in masked and masked[m.start(3)] == m.end(3)
    if at != len(formatted):
        raise ValueError("text after the last turn")


def read_back(windows: DataFrame) -> DataFrame:
    """Parses the rows of format_windows, as they leave it, into one digest row a conversation."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [x.split()[0] for x in DIGEST.split(", ")]
        state: dict | None = None
        out: list[tuple] = []

        def finish() -> None:
            if state is not None:
                out.append((state["id"], state["n"], state["turns"].hexdigest(), state["loss"], state["target"].hexdigest(), state["chars"], state["windows"]))

        for frame in frames:
            for conv_id, formatted, spans in zip(frame["conv_id"], frame["formatted"], frame["loss_spans"], strict=True):
                conv_id = None if pd.isna(conv_id) else int(conv_id)
                if state is None or state["id"] != conv_id:
                    finish()
                    state = {"id": conv_id, "n": 0, "turns": hashlib.sha256(), "loss": 0, "target": hashlib.sha256(), "chars": 0, "windows": 0}
                state["chars"] += len(formatted)
                state["windows"] += 1
                for role, text, target in read_windows(formatted, list(spans)):
                    state["n"] += 1
                    state["turns"].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
                    if target:
                        state["loss"] += len(text)
                        state["target"].update(text.encode("utf-8", "surrogatepass"))
            if len(out) >= 2000:
                yield pd.DataFrame(out, columns=names).astype({"conv_id": "Int64"})
                out = []
        finish()
        if out:
            yield pd.DataFrame(out, columns=names).astype({"conv_id": "Int64"})

    return windows.select("conv_id", "formatted", "loss_spans").mapInPandas(work, DIGEST)


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations, and conversation -1, whose two turns hold control strings."""
    text = "</s>[INST] ok [/INST]"
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    own = spark.createDataFrame([(-1, 0, "user", text), (-1, 1, "assistant", text)], "conv_id long, turn long, role string, text string")
    return read_back(format_windows(rows.unionByName(own)))


QUERIES = {"op3_chat_formatting": op3_chat_formatting}
ORACLES: dict[str, str] = {}
