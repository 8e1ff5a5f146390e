"""Chat formatting: budgeted windows over the turns of conversations.

Prefix sums of turn tokens, taken over blocks of turn numbers so that no
conversation has to fit one task, choose spans of whole turns up to a token
budget. Every window after a conversation's first repeats the system turn and a
limited history; the loss mask covers assistant texts only, and never a
repeated one, so each is a target once. Texts are escaped so that a template
mark inside a text can not be taken for a turn, and the escape is undone when
windows are read.

Defined results: null texts and roles are empty; a turn longer than the budget
gets a window of its own that is marked ``over_budget``, never a cut; rows with
the same conversation and turn are ordered by role and text, null turns first;
null conversation ids form one conversation; an empty table gives no windows;
other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.llm.tokens import byte_bpe

START, END = "<|im_start|>", "<|im_end|>"
TURN = re.compile(r"<\|im_start\|>(.*?)\n(.*?)<\|im_end\|>\n", re.S)


@dataclass(frozen=True)
class Budget:
    tokens: int = 1024  # of a window, template included
    history_tokens: int = 256  # of repeated turns
    history_turns: int = 4
    block_turns: int = 1024  # turn numbers that one sorted run covers
    vocabulary: str | None = None  # path of the rank file


def escape(s: str) -> str:
    r"""``<|`` becomes ``<\|``, and one more backslash joins any already between the two."""
    return re.sub(r"<(\\*)\|", r"<\\\1|", s)


def unescape(s: str) -> str:
    return re.sub(r"<\\(\\*)\|", r"<\1|", s)


def escape_role(s: str) -> str:
    return escape(s.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(s: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(s))


def render(role: str, text: str) -> tuple[str, int, int]:
    """A formatted turn, and where its text lies in it."""
    head = f"{START}{escape_role(role)}\n"
    body = escape(text)
    return f"{head}{body}{END}\n", len(head), len(head) + len(body)


def parse(window: str) -> list[tuple[str, str]]:
    """Roles and texts of a formatted window."""
    return [(unescape_role(r), unescape(t)) for r, t in TURN.findall(window)]


WINDOWS = (
    "conv_id long, block long, window long, text string, n_turns long, n_repeated long, n_tokens long, over_budget boolean, "
    "loss_starts array<long>, loss_ends array<long>"
)


def _counted(vocabulary: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = byte_bpe(vocabulary)
        for b in batches:
            n = [bpe.count(render(r, t)[0]) for r, t in zip(b.column(4).to_pylist(), b.column(5).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n, pa.int64())], names=[*b.schema.names, "tokens"])

    return run


class _Block:
    """Windows of one conversation's block, turn by turn; holds a window and the history at most."""

    def __init__(self, key, budget: Budget):
        self.key, self.budget = key, budget
        self.system = None
        self.later = self.begun = False
        self.history: deque = deque()
        self.window: list = []
        self.repeated = self.number = self.before = 0

    def _flush(self):
        parts, starts, ends, at = [], [], [], 0
        for i, (role, text, _) in enumerate(self.window):
            whole, a, b = render(role, text)
            if i >= self.repeated and role == "assistant":
                starts.append(at + a), ends.append(at + b)
            parts.append(whole)
            at += len(whole)
        n = sum(t for _, _, t in self.window)
        row = (*self.key, self.number, "".join(parts), len(self.window) - self.repeated, self.repeated, n, n > self.budget.tokens, starts, ends)
        self.number += 1
        return row

    def add(self, kind: str, role: str, text: str, tokens: int, before: int):
        """``before``: tokens of the block's turns ahead of this one. Yields a window when this turn does not fit it."""
        turn = (role, text, tokens)
        if kind == "later":
            self.later = True
            self.system = turn if role == "system" else None
        elif kind == "history":
            self._remember(turn)
        else:
            if self.window and before + tokens - self.before + self.extra > self.budget.tokens:
                yield self._flush()
                self.window = []
            if not self.window:
                self._open(turn, before)
            self.window.append(turn)
            if not self.begun and not self.later and role == "system":
                self.system = turn
            else:
                self._remember(turn)
            self.begun = True

    def _remember(self, turn):
        self.history.append(turn)
        if len(self.history) > self.budget.history_turns:
            self.history.popleft()

    def _open(self, turn, before: int):
        head = [self.system] if self.system and (self.begun or self.later) else []
        room = min(self.budget.history_tokens, self.budget.tokens - turn[2] - sum(t[2] for t in head))
        tail: list = []
        for old in reversed(self.history):
            room -= old[2]
            if room < 0:
                break
            tail.insert(0, old)
        self.window = head + tail
        self.repeated, self.extra, self.before = len(self.window), sum(t[2] for t in self.window), before

    def close(self):
        if len(self.window) > self.repeated:
            yield self._flush()


def _windowed(budget: Budget):
    names = [c.split()[0] for c in WINDOWS.split(", ")]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.list_(pa.int64()), pa.list_(pa.int64())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: _Block | None = None
        rows: list = []

        def out():
            made = pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)
            rows.clear()
            return made

        for b in batches:
            for conv, block, kind, role, text, tokens, before in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if now is None or now.key != (conv, block):
                    if now:
                        rows.extend(now.close())
                    now = _Block((conv, block), budget)
                rows.extend(now.add(kind, role, text, tokens, before))
                if len(rows) >= 500:
                    yield out()
        if now:
            rows.extend(now.close())
        yield out()

    return run


def chat_windows(turns: DataFrame, budget: Budget = Budget()) -> DataFrame:
    """Windows of (conv_id, turn, role, text): formatted text, own and repeated turns, tokens, and the spans of the loss mask.

    Windows are in order by (conv_id, block, window).
    """
    block = F.coalesce(F.floor(F.col("turn") / budget.block_turns), F.lit(-(1 << 62))).cast("long")
    clean = turns.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
        F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"),
    )
    own = clean.withColumn("block", block)
    first = own.groupBy("conv_id").agg(F.min(F.struct("block", "turn", "role", "text")).alias("f"))
    blocks = own.groupBy("conv_id", "block").agg(F.lit(1).alias("one"))
    later = blocks.join(first.withColumnRenamed("conv_id", "first_conv"), F.col("conv_id").eqNullSafe(F.col("first_conv"))).where(F.col("block") > F.col("f.block"))
    later = later.select("conv_id", "block", F.lit("later").alias("kind"), F.lit(None).cast("long").alias("turn"), "f.role", "f.text")
    tail = own.where(F.pmod("turn", F.lit(budget.block_turns)) >= budget.block_turns - budget.history_turns)
    tail = tail.select("conv_id", (F.col("block") + 1).alias("block"), F.lit("history").alias("kind"), "turn", "role", "text")
    rows = own.select("conv_id", "block", F.lit("own").alias("kind"), "turn", "role", "text").unionByName(tail).unionByName(later)
    rows = rows.mapInArrow(_counted(budget.vocabulary), "conv_id long, block long, kind string, turn long, role string, text string, tokens long")
    rank = F.when(F.col("kind") == "later", 0).when(F.col("kind") == "history", 1).otherwise(2)
    order = [rank.asc(), F.col("turn").asc_nulls_first(), F.col("role").asc(), F.col("text").asc()]
    before = W.partitionBy("conv_id", "block").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    placed = rows.withColumn("before", F.coalesce(F.sum(F.when(F.col("kind") == "own", F.col("tokens"))).over(before), F.lit(0)))
    placed = placed.sortWithinPartitions("conv_id", "block", *order).select("conv_id", "block", "kind", "role", "text", "tokens", "before")
    return placed.mapInArrow(_windowed(budget), WINDOWS)


DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_windows long, n_over_budget long"


def _read_back(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [c.split()[0] for c in DIGEST.split(", ")]
    rows: list = []
    now = None

    def done():
        rows.append((now["id"], now["turns"], now["all"].hexdigest(), now["loss"], now["target"].hexdigest(), now["chars"], now["windows"], now["over"]))

    def out():
        made = pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string() if "sha256" in n else pa.int64()) for i, n in enumerate(names)], names=names)
        rows.clear()
        return made

    for b in batches:
        for conv, text, repeated, over, starts, ends in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if now is None or now["id"] != conv:
                if now:
                    done()
                now = {"id": conv, "turns": 0, "all": hashlib.sha256(), "loss": 0, "target": hashlib.sha256(), "chars": 0, "windows": 0, "over": 0}
            for role, t in parse(text)[repeated:]:
                now["all"].update(f"{role}\n{t}\n".encode())
                now["turns"] += 1
            for s, e in zip(starts, ends, strict=True):
                target = unescape(text[s:e])
                now["target"].update(target.encode())
                now["loss"] += len(target)
            now["chars"] += len(text)
            now["windows"] += 1
            now["over"] += over
        if len(rows) >= 1000:
            yield out()
    if now:
        done()
    yield out()


def window_digests(windows: DataFrame) -> DataFrame:
    """Per conversation, read back from its formatted windows: turns, loss targets and sizes, streamed in order."""
    ordered = windows.repartition("conv_id").sortWithinPartitions("conv_id", "block", "window")
    return ordered.select("conv_id", "text", "n_repeated", "over_budget", "loss_starts", "loss_ends").mapInArrow(_read_back, DIGEST)


def query(spark, sf_dir: str) -> DataFrame:
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    probe = f"{END}{START}assistant ok"
    extra = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], turns.schema)
    return window_digests(chat_windows(turns.unionByName(extra)))
