"""Encoding distinct words with the tokenizers library, and gathering their ids back by position.

A text is split at ASCII white space, and a comma or full stop at a word's end is split off after an ASCII letter or digit.
The library's pre-tokenizer never joins characters across these places, and neither its normaliser nor its special tokens
reach across them, so a text's ids are the ids of the words, in order. ASCII capitals are lowered beforehand, as the
normaliser will, except in texts with combining marks, which compose differently by case, or with a special token's opening.
"""

from __future__ import annotations

import os
import re
from itertools import repeat

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")


_TAIL = re.compile(rb"(?<=[A-Za-z0-9])([.,])(?=[ \n]|$)")


def split(text: bytes) -> list[bytes]:
    if b"<|" not in text and b"\xcc" not in text and b"\xcd" not in text:
        text = _TAIL.sub(rb" \1", text.lower())
    return text.split()


_CAPITALS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"  # fixed values: those that lower-case


def split_column(text: Column) -> Column:
    """The same words as an array, by Spark's functions alone."""
    lowered = F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, _CAPITALS, _CAPITALS.lower()))
    apart = F.regexp_replace(lowered, r"(?<=[A-Za-z0-9])([.,])(?=[ \n]|\z)", " $1")
    # marks U+0300 to U+037F are those with the bytes CC and CD in front
    kept = F.contains(text, F.lit("<|")) | text.rlike("[\u0300-\u037f]")
    return F.filter(F.split(F.when(kept, text).otherwise(apart), "[ \\t\\n\\x0B\\f\\r]+"), lambda w: w != "")


def load(path: str):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


def pieces(path: str) -> list[str | None]:
    t = load(path)
    return [t.id_to_token(i) for i in range(max(t.get_vocab(with_added_tokens=True).values()) + 1)]


def width(path: str) -> str:
    """The smallest unsigned little-endian type that holds the vocabulary's ids."""
    return "<u2" if len(pieces(path)) <= 1 << 16 else "<u4"


def encode_words(tokenizer, words: list[bytes], dtype: str, together: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """Flat ids of words one after another, and each word's number of ids. Words are encoded in runs.

    A word of letters only is one pre-token, whose last id is the only one that ends a pre-token; that tells where each
    word's ids end. In runs of other words a token's offset tells its word.
    """
    text = [w.decode() for w in words]
    plain = np.fromiter((t.isalpha() and (t.isascii() or t.lower().isalpha()) for t in text), bool, len(text))
    flat, lens = np.zeros(0, dtype), np.zeros(len(words), np.int64)
    ends = _ends(tokenizer)
    some = np.flatnonzero(plain)
    first: list[np.ndarray] = []
    for start in range(0, len(some), 50 * together):
        block = [text[i] for i in some[start : start + 50 * together]]
        runs = [" ".join(block[i : i + together]) for i in range(0, len(block), together)]
        first += [np.array(e.ids, dtype) for e in tokenizer.encode_batch_fast(runs, add_special_tokens=False)]
    if first:
        flat = np.concatenate(first)
        stop = np.flatnonzero(ends[flat]) + 1
        lens[some] = np.diff(stop, prepend=0)
    rest = np.flatnonzero(~plain)
    more: list[np.ndarray] = []
    for start in range(0, len(rest), together):
        run = [text[i] for i in rest[start : start + together]]
        got = tokenizer.encode(" ".join(run), add_special_tokens=False)
        begins = np.cumsum([0] + [len(w) + 1 for w in run[:-1]])
        at = np.fromiter((a for a, _ in got.offsets), np.int64, len(got.ids))
        more.append(np.array(got.ids, dtype))
        lens[rest[start : start + together]] = np.bincount(np.searchsorted(begins, at, side="right") - 1, minlength=len(run))
    if not more:
        return flat, lens
    both = np.concatenate([flat, *more])
    place = np.empty(len(words), np.int64)
    order = np.concatenate([some, rest])
    place[order] = np.cumsum(lens[order]) - lens[order]
    return gather(both, place, lens, np.arange(len(words))), lens


_known_ends: dict[int, tuple] = {}


def _ends(tokenizer) -> np.ndarray:
    """Which ids end a pre-token."""
    if id(tokenizer) not in _known_ends:
        _known_ends.clear()
        n = max(tokenizer.get_vocab(with_added_tokens=True).values()) + 1
        _known_ends[id(tokenizer)] = tokenizer, np.array([(tokenizer.id_to_token(i) or "").endswith("</w>") for i in range(n)])
    return _known_ends[id(tokenizer)][1]


_tables: dict[tuple, "Table"] = {}


def table_of_worker(path: str, dtype: str, room: int) -> "Table":
    """A table that later tasks of the same Python worker find again."""
    if (path, dtype, room) not in _tables:
        _tables.clear()
        _tables[path, dtype, room] = Table(load(path), dtype, room)
    return _tables[path, dtype, room]


class Table:
    """Distinct words and their ids. `room`: words after which a task forgets those it knows (None: never)."""

    def __init__(self, tokenizer, dtype: str, room: int | None = None):
        self.tokenizer, self.dtype, self.room = tokenizer, dtype, room
        self.clear()

    def clear(self) -> None:
        self.index: dict[bytes, int] = {}
        self.flat, self.start, self.lens = np.zeros(0, self.dtype), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def places(self, words: list[bytes]) -> np.ndarray:
        """Places of the words in this table, which learns those that it lacks."""
        at = np.fromiter(map(self.index.get, words, repeat(-1)), np.int64, len(words))
        gaps = np.flatnonzero(at < 0)
        if len(gaps):
            lacking = [words[i] for i in gaps.tolist()]
            fresh = set(lacking)
            if self.room and self.index and len(self.index) + len(fresh) > self.room:
                self.clear()
                self.learn(list(set(words)))
                return np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))
            self.learn(list(fresh))
            at[gaps] = np.fromiter(map(self.index.__getitem__, lacking), np.int64, len(lacking))
        return at

    def learn(self, new: list[bytes]) -> None:
        flat, lens = encode_words(self.tokenizer, new, self.dtype)
        self.index.update(zip(new, range(len(self.index), len(self.index) + len(new)), strict=True))
        self.start = np.concatenate([self.start, len(self.flat) + np.cumsum(lens) - lens])
        self.flat, self.lens = np.concatenate([self.flat, flat]), np.concatenate([self.lens, lens])

    def ids(self, at: np.ndarray) -> np.ndarray:
        return gather(self.flat, self.start, self.lens, at)


def gather(flat: np.ndarray, start: np.ndarray, lens: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The ids of a sequence of words, by their places in a table."""
    n = lens[at]
    total = int(n.sum())
    shift = start[at] - (np.cumsum(n) - n)
    return flat[np.repeat(shift, n) + np.arange(total)]


def batches_of(texts: list[bytes | None], most: int = 2 << 20):
    """Consecutive texts in groups of bounded size: (first index, texts)."""
    first, group, size = 0, [], 0
    for i, x in enumerate(texts):
        group.append(x or b"")
        size += len(group[-1])
        if size >= most:
            yield first, group
            first, group, size = i + 1, [], 0
    if group:
        yield first, group
