"""Chat formatting in budgeted windows.

A conversation becomes windows of whole turns. Prefix sums of the turns' tokens choose where a
window ends; every window after the first starts with the system turn and a limited stretch of the
turns before it, whose assistant texts are left out of the loss. Each assistant text is thus under
the loss mask exactly once. Rows stream through sorted by conversation and turn: what is held is a
window's turns, never a conversation.
"""

from __future__ import annotations

import hashlib
import re
from collections import deque
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common

# The template's marks, and control strings of common chat templates.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"
CONTROL = (OPEN, CLOSE[:-1], "<|endoftext|>", "<|startoftext|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
JOINER = "\u2060"

_any = "|".join(f"{re.escape(c[0])}{JOINER}{{}}{re.escape(c[1:])}" for c in CONTROL)
ESCAPE, UNESCAPE = re.compile(_any.format(*["*"] * len(CONTROL))), re.compile(_any.format(*["+"] * len(CONTROL)))
TOKEN = re.compile(r"\w+|[^\w\s]")


def escape(text: str) -> str:
    """No control string is left: each gets a word joiner after its first character.

    Strings that already look escaped get one joiner more, so unescape() undoes it exactly.
    """
    return ESCAPE.sub(lambda m: m[0][0] + JOINER + m[0][1:], text)


def unescape(text: str) -> str:
    return UNESCAPE.sub(lambda m: m[0][0] + m[0][2:], text)


def escape_role(role: str) -> str:
    return escape(role).replace("\\", "\\\\").replace("\n", "\\n")


def unescape_role(role: str) -> str:
    return unescape(re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], role, flags=re.DOTALL))


def count_tokens(text: str) -> int:
    return sum(1 for _ in TOKEN.finditer(text)) + 4


@dataclass
class Budget:
    """Tokens of a window, and of the history that later windows repeat; count: a text's tokens."""

    window: int = 2048
    history: int = 512
    count: Callable[[str], int] = count_tokens


@dataclass
class _Conversation:
    """The open window of one conversation; texts are escaped already."""

    conv_id: int | None
    budget: Budget
    system: tuple[str, str, int] | None = None
    turns: list = field(default_factory=list)  # (role, text, tokens, repeated)
    prefix: list = field(default_factory=lambda: [0])
    no: int = 0

    def add(self, role: str, text: str, first: bool) -> Iterator[dict]:
        tokens = self.budget.count(text)
        fresh = any(not t[3] for t in self.turns)
        if fresh and self.prefix[-1] + tokens > self.budget.window:
            yield self.close()
            self.reopen(tokens)
        if first and role == "system":
            self.system = (role, text, tokens)
        self.push(role, text, tokens, False)

    def push(self, role: str, text: str, tokens: int, repeated: bool) -> None:
        self.turns.append((role, text, tokens, repeated))
        self.prefix.append(self.prefix[-1] + tokens)

    def reopen(self, coming: int) -> None:
        """Start the next window with the system turn and as much history as the budgets allow."""
        skip = bool(self.system) and self.turns[0][0] == "system"
        turns, prefix = self.turns[skip:], self.prefix[skip:]
        own = self.system[2] if self.system else 0
        room = min(self.budget.history, self.budget.window - own - coming)
        first = next((k for k in range(len(turns)) if prefix[-1] - prefix[k] <= room), len(turns))
        self.turns, self.prefix = [], [0]
        if self.system:
            self.push(*self.system, True)
        for role, text, tokens, _ in turns[first:]:
            self.push(role, text, tokens, True)

    def close(self) -> dict:
        parts, at, starts, ends = [], 0, [], []
        for role, text, _, repeated in self.turns:
            head = f"{OPEN}{escape_role(role)}\n"
            if role == "assistant" and not repeated:
                starts.append(at + len(head))
                ends.append(at + len(head) + len(text))
            parts += (head, text, CLOSE)
            at += len(head) + len(text) + len(CLOSE)
        row = {"conv_id": self.conv_id, "window": self.no, "formatted": "".join(parts), "n_repeated": sum(t[3] for t in self.turns), "n_tokens": self.prefix[-1], "loss_starts": starts, "loss_ends": ends}
        self.no += 1
        return row


SCHEMA = "conv_id long, window int, formatted string, n_repeated int, n_tokens long, loss_starts array<int>, loss_ends array<int>"
_ARROW = pa.schema([("conv_id", pa.int64()), ("window", pa.int32()), ("formatted", pa.string()), ("n_repeated", pa.int32()), ("n_tokens", pa.int64()), ("loss_starts", pa.list_(pa.int32())), ("loss_ends", pa.list_(pa.int32()))])
FLUSH_CHARS = 1 << 21


def windows(turns: DataFrame, budget: Budget | None = None) -> DataFrame:
    """One row for each window of the conversations in turns(conv_id, turn, role, text).

    Turns are taken by turn, then role, then text, so ties and repeated rows have one order; nulls
    sort first, null role and text count as empty, and rows without conv_id form one conversation.
    A turn over the budget is a window of its own (after the system turn): texts are never cut.
    loss_starts and loss_ends are offsets in ``formatted``, in code points.
    """
    budget = budget or Budget()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size, now = [], 0, None
        for b in batches:
            for conv, role, text in zip(*(b.column(k).to_pylist() for k in range(3)), strict=True):
                first = now is None or now.conv_id != conv
                if first:
                    if now is not None:
                        rows.append(now.close())
                    now = _Conversation(conv, budget)
                rows += now.add(role, escape(text), first)
                size += len(text)
                if size > FLUSH_CHARS and rows:
                    yield pa.RecordBatch.from_pylist(rows, _ARROW)
                    rows, size = [], 0
        if now is not None:
            rows.append(now.close())
        if rows:
            yield pa.RecordBatch.from_pylist(rows, _ARROW)

    empty = F.lit("")
    t = turns.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), F.coalesce("role", empty).alias("role"), F.coalesce("text", empty).alias("text"))
    dealt = t.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return common.mapped(dealt.select("conv_id", "role", "text"), run, SCHEMA)


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a window, unescaped."""
    out = []
    for part in formatted.split(OPEN)[1:]:
        role, _, text = part.partition("\n")
        if not text.endswith(CLOSE):
            raise ValueError("a turn has no end mark")
        out.append((unescape_role(role), unescape(text[: -len(CLOSE)])))
    return out


def digests(w: DataFrame) -> DataFrame:
    """What the windows hold, read back from their text, one row for each conversation."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = None

        def done() -> list:
            conv, n, turns, chars, loss, total = state
            return [conv, n, turns.hexdigest(), chars, loss.hexdigest(), total]

        for b in batches:
            out: deque = deque()
            for row in b.to_pylist():
                if state is None or state[0] != row["conv_id"] or row["window"] == 0:
                    if state is not None:
                        out.append(done())
                    state = [row["conv_id"], 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                text = row["formatted"]
                for role, said in read_back(text)[row["n_repeated"] :]:
                    state[1] += 1
                    state[2].update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
                for s, e in zip(row["loss_starts"], row["loss_ends"], strict=True):
                    target = unescape(text[s:e])
                    state[3] += len(target)
                    state[4].update(target.encode("utf-8", "surrogatepass"))
                state[5] += len(text)
            if out:
                yield _rows(list(out))
        if state is not None:
            yield _rows([done()])

    dealt = w.repartition("conv_id").sortWithinPartitions("conv_id", "window")
    return common.mapped(dealt, run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def _rows(rows: list) -> pa.RecordBatch:
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    return pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)


def op8_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = common.table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.range(1).select(F.explode(F.array(*[F.struct(F.lit(-1).cast("long").alias("conv_id"), F.lit(k).cast("long").alias("turn"), F.lit(r).alias("role"), F.lit(probe).alias("text")) for k, r in enumerate(("user", "assistant"))])).alias("x")).select("x.*")
    return digests(windows(turns.unionByName(extra)))

