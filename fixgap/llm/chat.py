"""Chat formatting in budgeted windows.

Turns are written in a marked template, control strings inside texts are escaped reversibly, and a conversation becomes
one or more windows of whole turns. A turn's tokens are those of its formatted text under a public tokenizer. Prefix sums of
them, by a window function, decide where a window ends: a window holds the leading system turn again, then as many of the latest
earlier turns as fit `history` tokens, then new turns up to the budget. Where the first new turn doesn't fit beside them, earlier
turns go, the oldest first. Every turn is new in exactly one window; a repeated assistant turn is masked, so each assistant text
is a target once.

Rows are brought together by conversation and sorted by turn (a conversation is one key: its windows follow from one another,
and its digest is of all its turns in order); a task streams over them and keeps the current window and its history only, so
the memory needed is bounded by the budget and the longest turn, not by a conversation.

Nulls: a null text is empty; a null role is written as an empty role; a null turn comes first; rows of a null
conversation form one conversation. Equal turn numbers are ordered by role, then text; repeated rows stay. A turn that, alone
or with the system turn, is above the budget gets a window of its own, beside the system turn, and is never cut. Extra columns are ignored; an empty table gives no windows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import words

# The strings of the template and other common templates' control strings, which must not appear inside a text.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
CONTROLS = ["<|im_start|>", "<|im_end|>", "<|endoftext|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>"]

_ESCAPE = re.compile(r"\\|" + "|".join(map(re.escape, CONTROLS)))
_UNESCAPE = re.compile(r"\\(.)", re.DOTALL)
WINDOW = "conv_id long, window long, text string, turns array<struct<start:long,end:long,repeated:boolean,target:boolean>>, n_tokens long"


def escape(text: str) -> str:
    """A backslash is doubled; a control string gets a backslash after its first character. No control string remains."""
    return _ESCAPE.sub(lambda m: "\\\\" if m[0] == "\\" else m[0][0] + "\\" + m[0][1:], text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"\1", text)


def escape_role(role: str) -> str:
    """Roles end at a line break in the template, so theirs are written as a backslash and n."""
    return escape(role).replace("\n", "\\n")


def unescape_role(text: str) -> str:
    return _UNESCAPE.sub(lambda m: "\n" if m[1] == "n" else m[1], text)


def formatted(role: str, text: str) -> tuple[str, str]:
    """A turn's opening line and its escaped text."""
    return f"{OPEN}{escape_role(role)}\n", escape(text)


def _counted(tokenizer: str):
    """Adds the number of tokens of each formatted turn."""
    dtype = words.width(tokenizer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = words.table_of_worker(tokenizer, dtype, 1 << 18)
        for b in batches:
            n = []
            for role, text in zip(b.column("role").to_pylist(), b.column("text").to_pylist(), strict=True):
                at = table.places(words.split(("".join(formatted(role, text)) + CLOSE).encode()))
                n.append(int(table.lens[at].sum()))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n, pa.int64())], names=[*b.schema.names, "n"])

    return run


class _Windows:
    """Builds the windows of one conversation after another from its turns in order."""

    def __init__(self, budget: int, history: int):
        self.budget, self.limit = budget, history
        self.conv: int | None = None
        self.system: tuple | None = None
        self.new: list[tuple] = []  # (role, text, tokens) of the open window
        self.past: list[tuple] = []  # the latest turns before it, within the limit
        self.first, self.number, self.upto, self.base = True, 0, 0, 0

    def begin(self, conv: int | None) -> None:
        self.conv, self.system, self.new, self.past = conv, None, [], []
        self.first, self.number, self.upto, self.base = True, 0, 0, 0

    def held(self) -> int:
        """Tokens of repeated turns."""
        return (self.system[2] if self.system else 0) + sum(x[2] for x in self.past)

    def add(self, role: str, text: str, n: int, upto: int) -> Iterator[tuple]:
        """The next turn: its tokens, and all tokens of the conversation up to it."""
        if self.new and self.held() + upto - self.base > self.budget:
            yield self.close()
        while not self.new and self.past and self.held() + upto - self.base > self.budget:
            self.past.pop(0)
        self.upto = upto
        self.new.append((role, text, n))
        if self.first and role == "system":
            self.system = None  # it is new in this window; repeated from the next one on
            self.pending = (role, text, n)
        elif self.first:
            self.pending = None
        self.first = False

    def close(self) -> tuple:
        repeated = ([self.system] if self.system else []) + self.past
        parts, turns, at = [], [], 0
        for i, (role, text, _) in enumerate([*repeated, *self.new]):
            head, body = formatted(role, text)
            parts.append(f"{head}{body}{CLOSE}\n")
            old = i < len(repeated)
            turns.append({"start": at + len(head), "end": at + len(head) + len(body), "repeated": old, "target": not old and role == "assistant"})
            at += len(parts[-1])
        row = (self.conv, self.number, "".join(parts), turns, sum(x[2] for x in repeated) + self.upto - self.base)
        self.system = self.pending
        pool = [x for x in [*self.past, *self.new] if x is not self.pending]
        kept, left = [], self.limit
        for x in reversed(pool):
            if x[2] > left or (self.system and self.system[2] + (self.limit - left) + x[2] >= self.budget):
                break
            kept.append(x)
            left -= x[2]
        self.past, self.new, self.base, self.number = kept[::-1], [], self.upto, self.number + 1
        return row


def windows(turns: DataFrame, tokenizer: str, budget: int = 1024, history: int = 256) -> DataFrame:
    """conv_id, window, text, turns (ranges in code points, repeated, target), n_tokens. tokenizer: path of a tokenizers file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, some, out = _Windows(budget, history), False, []
        names, kinds = ["conv_id", "window", "text", "turns", "n_tokens"], [pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("repeated", pa.bool_()), ("target", pa.bool_())])), pa.int64()]

        def flush():
            cols = list(zip(*out, strict=True))
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

        for b in batches:
            for conv, role, text, n, upto in zip(*(b.column(c).to_pylist() for c in ("conv_id", "role", "text", "n", "upto")), strict=True):
                if not some or conv != state.conv:
                    if some:
                        out.append(state.close())
                    state.begin(conv)
                    some = True
                out.extend(state.add(role, text, n, upto))
            if len(out) > 500:
                yield flush()
        if some:
            out.append(state.close())
        if out:
            yield flush()

    rows = turns.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    counted = rows.mapInArrow(_counted(tokenizer), "conv_id long, turn long, role string, text string, n long")
    line = Window.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, 0)
    summed = counted.repartition("conv_id").withColumn("upto", F.sum("n").over(line))
    return summed.sortWithinPartitions("conv_id", "turn", "role", "text", "upto").select("conv_id", "role", "text", "n", "upto").mapInArrow(run, WINDOW)


_TURN = re.compile(re.escape(OPEN) + r"([^\n]*)\n(.*?)" + re.escape(CLOSE) + "\n", re.DOTALL)


def digests(formatted: DataFrame) -> DataFrame:
    """Reads formatted windows back. Turns are parsed from the text alone; the mask says which are repeated or targets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        state: list = []

        def end():
            conv, n, turns, chars, loss, total = state
            rows.append((conv, n, turns.hexdigest(), chars, loss.hexdigest(), total))

        for b in batches:
            for conv, text, mask in zip(*(b.column(c).to_pylist() for c in ("conv_id", "text", "turns")), strict=True):
                if not state or state[0] != conv:
                    if state:
                        end()
                    state[:] = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                at = 0
                for m, found in zip(mask, _TURN.finditer(text), strict=True):
                    if found.start() != at or found.span(2) != (m["start"], m["end"]):
                        raise ValueError(f"window of conversation {conv} does not parse")
                    at = found.end()
                    if not m["repeated"]:
                        state[1] += 1
                        state[2].update(f"{unescape_role(found[1])}\n{unescape(found[2])}\n".encode())
                    if m["target"]:
                        target = unescape(text[m["start"] : m["end"]])
                        state[3] += len(target)
                        state[4].update(target.encode())
                if at != len(text):
                    raise ValueError(f"window of conversation {conv} has text after its last turn")
                state[5] += len(text)
        if state:
            end()
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    schema = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    return formatted.repartition("conv_id").sortWithinPartitions("conv_id", "window").select("conv_id", "text", "turns").mapInArrow(run, schema)


def with_probe(turns: DataFrame) -> DataFrame:
    """The table's turns and conversation -1, whose texts contain control strings."""
    spark: SparkSession = turns.sparkSession
    probe = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    cast = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    return cast.unionByName(probe)
