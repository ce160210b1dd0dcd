"""Removal of byte strings that start more than once in the corpus, by merging Burrows-Wheeler transforms.

Every window of `length` bytes has one anchor: the k-gram in it with the smallest hash (the leftmost of equals). Equal
windows have equal anchors at equal places, so windows need comparing only within the group of one anchor hash, and groups
are independent. What an anchor's windows cover is its context.
1. Each text sends a row for each anchor: hash, context hash, text key, place. Contexts that occur twice are repeated as a
   whole; contexts alone under their anchor hash are not repeated at all. Both are settled without any bytes.
2. The rest, contexts that differ under one anchor hash (edges of passages, near copies), go to buckets as bytes. A bucket
   builds transforms of bounded shards and merges them by interleave refinement; the repeated intervals of the merged order
   say which windows occur again. A large group is dealt out by window offset, and beyond that by window hash, which equal
   windows share.
3. Ranges meet their texts again, and every byte under a repeated window goes.

Anchor hashes of very many rows (a passage that a large share of the texts hold) are found first on a sample of the rows. The
sample decides only how rows are dealt out, never what is repeated: rows of such a hash go by context instead of by hash, their
contexts are all compared, and of a context that a task has already sent twice, further rows are known to be repeated and go
anywhere.

Texts are known by 79 bits of hash; equal texts have equal results, so copies in one task cost one text's rows.

Nulls: a null text is empty. Texts shorter than `length` keep all bytes. Repeated rows are copies of one another and count as
occurrences. Long texts are handled in overlapping pieces. Extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import bwt
from .base import materialise

LENGTH, GRAM, STEP = 200, 32, 50
PIECE = 4 << 20  # bytes of text handled at once
BUCKET_BYTES = 3 << 20
SAMPLE, OFTEN = 1 / 64, 256  # share of rows looked at for frequent anchor hashes, and how often these occur there
HOT = 100_000  # most hashes dealt by context; any other then has at most a share of 1 / HOT of all rows
SEEN = 200_000  # contexts of frequent hashes that a task remembers
ROWS = "fp long, ctx long, k1 long, k2 short, first int, lead short, spread short, twice byte, deal int, hint int"
SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
_PLACE = np.uint64((1 << 23) - 1)


def keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("k1"), F.pmod(F.xxhash64(F.lit(1), text), F.lit(1 << 15)).cast("short").alias("k2"), text.cast("binary").alias("raw"))


def _pieces(texts: list[bytes], length: int) -> Iterator[list[tuple[int, int, bytes]]]:
    """Groups of (text number, offset of the piece, piece); pieces of a long text overlap by all but one byte of a window."""
    group, size = [], 0
    for i, t in enumerate(texts):
        for at in range(0, max(1, len(t) - length + 1), PIECE):
            part = t[at : at + PIECE + length - 1] if len(t) > PIECE else t
            if size and size + len(part) > PIECE:
                yield group
                group, size = [], 0
            group.append((i, at, part))
            size += len(part)
    if group:
        yield group


def anchors(group: list[tuple[int, int, bytes]], length: int, gram: int) -> tuple[np.ndarray, ...]:
    """anchor hash, context hash, text number, anchor's offset in the text, first and last window start."""
    lens = np.array([len(p) for _, _, p in group], np.int64)
    ends = np.cumsum(lens)
    x = np.frombuffer(b"".join(p for _, _, p in group), np.uint8)
    n = len(x) - length + 1
    if n <= 0:
        return tuple(np.zeros(0, np.int64) for _ in range(6))
    sums = bwt.running(x)
    h = bwt.mix((sums[gram:] - sums[:-gram]) * bwt.powers(len(sums)).down[: len(x) - gram + 1])
    low = (h & ~_PLACE) | np.arange(len(h), dtype=np.uint64)
    span, w = length - gram + 1, 1
    while 2 * w <= span:
        low = np.minimum(low[:-w], low[w:])
        w *= 2
    if w < span:
        low = np.minimum(low[: n], low[span - w :])
    owner = np.repeat(np.arange(len(group)), lens)
    start = np.flatnonzero(np.arange(n) + length <= ends[owner[:n]])
    if not len(start):
        return tuple(np.zeros(0, np.int64) for _ in range(6))
    place = (low[start] & _PLACE).astype(np.int64)
    cut = np.flatnonzero((place[1:] != place[:-1]) | (start[1:] != start[:-1] + 1)) + 1
    first, last, place = start[np.concatenate([[0], cut])], start[np.concatenate([cut, [len(start)]]) - 1], place[np.concatenate([[0], cut])]
    shape = ((place - first) << 20 | (last - first)).astype(np.uint64)
    context = bwt.mix(bwt.ranges(sums, first, last + length) ^ bwt.mix(shape + np.uint64(1)))
    who = owner[first]
    shift = np.array([a for _, a, _ in group], np.int64)[who] - (ends - lens)[who]
    return h[place].view(np.int64), context.view(np.int64), np.array([i for i, _, _ in group])[who], place + shift, first + shift, last + shift


def _deal(fp: np.ndarray, ctx: np.ndarray, twice: np.ndarray, hot: tuple[np.ndarray, np.ndarray], seen: dict, task: int) -> tuple[np.ndarray, ...]:
    """deal, hint, twice of each row. Ordinary rows: 0 and 0. Rows of a frequent hash: above 0, told by their context, and the
    hash's estimated rows. Rows whose context this task has sent twice already: below 0, spread evenly, and -1."""
    deal, hint = np.zeros(len(fp), np.int32), np.zeros(len(fp), np.int32)
    known, rows = hot
    if not len(known):
        return deal, hint, twice
    at = np.minimum(np.searchsorted(known, fp), len(known) - 1)
    some = np.flatnonzero(known[at] == fp)
    deal[some] = (ctx[some] & 0x7FFFFFFF).astype(np.int32) | 1
    hint[some] = rows[at[some]]
    twice = twice.copy()
    if len(seen) > SEEN:
        seen.clear()
    for i, key in zip(some.tolist(), zip(fp[some].tolist(), ctx[some].tolist(), strict=True), strict=True):
        n = seen.get(key, 0)
        if n > 1:
            seen[key] = n + 1
            deal[i], hint[i], twice[i] = -1 - (n * 0x9E3779B1 + task * 0x85EBCA6B) % 0x7FFFFFFF, -1, 1
        else:
            seen[key] = n + 1 + int(twice[i])
    return deal, hint, twice


def _scan(length: int, gram: int, hot: tuple[np.ndarray, np.ndarray] = (np.zeros(0, np.int64), np.zeros(0, np.int32))):
    names = ["fp", "ctx", "k1", "k2", "first", "lead", "spread", "twice", "deal", "hint"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int16(), pa.int32(), pa.int16(), pa.int16(), pa.int8(), pa.int32(), pa.int32()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sent: dict[tuple[int, int], int] = {}
        task = TaskContext.get().partitionId()
        for b in batches:
            k1, k2 = b.column("k1").to_numpy(), b.column("k2").to_numpy()
            seen: dict[tuple[int, int], int] = {}
            texts, keys, times = [], [], []
            for key, t in zip(zip(k1.tolist(), k2.tolist(), strict=True), b.column("raw").to_pylist(), strict=True):
                if len(t) < length:
                    continue
                if key in seen:
                    times[seen[key]] = 1
                    continue
                seen[key] = len(texts)
                texts.append(t)
                keys.append(key)
                times.append(0)
            k1, k2, twice = np.array([k[0] for k in keys], np.int64), np.array([k[1] for k in keys], np.int64), np.array(times, np.int8)
            for group in _pieces(texts, length):
                fp, ctx, who, place, first, last = anchors(group, length, gram)
                deal, hint, more = _deal(fp, ctx, twice[who], hot, sent, task)
                cols = (fp, ctx, k1[who], k2[who], first, place - first, last - first, more, deal, hint)
                yield pa.RecordBatch.from_arrays([pa.array(c.astype(t.to_pandas_dtype())) for c, t in zip(cols, kinds, strict=True)], names=names)

    return run


def _extract(length: int):
    """Bytes of requested contexts, dealt out by part and salt."""
    names = ["fp", "part", "salt", "k1", "k2", "start", "bytes"]
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int16(), pa.int32(), pa.binary()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, done = [], set()
            for k1, k2, raw, asked in zip(*(b.column(c).to_pylist() for c in ("k1", "k2", "raw", "asked")), strict=True):
                for r in asked:
                    if (r["fp"], r["ctx"]) in done:
                        continue
                    done.add((r["fp"], r["ctx"]))
                    first, spread, parts, salts = r["first"], r["spread"], r["parts"], r["salts"]
                    if parts == 1:
                        rows.append((r["fp"], 0, 0, k1, k2, first, raw[first : first + spread + length]))
                        continue
                    lead, width = r["lead"], -(-length // parts)  # parts are told by how far the anchor is from a window's start
                    for part in range(parts):
                        lo, hi = max(0, lead - (part + 1) * width + 1), min(spread, lead - part * width)
                        if lo > hi:
                            continue
                        if salts == 1:
                            rows.append((r["fp"], part, 0, k1, k2, first + lo, raw[first + lo : first + hi + length]))
                            continue
                        for w in range(first + lo, first + hi + 1):
                            s = raw[w : w + length]
                            rows.append((r["fp"], part, int.from_bytes(hashlib.blake2b(s, digest_size=4).digest()) % salts, k1, k2, w, s))
                    if len(rows) > 20_000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)
                        rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return run


def _merge(length: int, step: int):
    def run(table: pa.Table) -> pa.Table:
        hits = bwt.repeated_windows(table.column("bytes").to_pylist(), length, step)
        k1, k2, start, lo, n = table.column("k1").to_numpy(), table.column("k2").to_numpy(), table.column("start").to_numpy(), [], []
        who = []
        for i, hit in enumerate(hits):
            edge = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
            for a, b in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
                who.append(i)
                lo.append(a)
                n.append(b - a - 1)
        at = np.array(who, np.int64)
        return pa.table({"k1": k1[at], "k2": k2[at].astype(np.int16), "first": (start[at] + np.array(lo, np.int64)).astype(np.int32), "spread": np.array(n, np.int16)})

    return run


def _apply(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for raw, marks in zip(b.column("raw").to_pylist(), b.column("ranges"), strict=True):
                kept, removed, spans = cut(raw, marks.values, length) if marks.is_valid else (raw, 0, 0)
                out.append((len(raw), removed, spans, hashlib.sha256(kept).hexdigest()))
            cols = list(zip(*out, strict=True)) if out else [[]] * 4
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string()), strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return run


def cut(raw: bytes, ranges: pa.Array, length: int) -> tuple[bytes, int, int]:
    """Text without the bytes under windows that start in the ranges; bytes removed; maximal runs of them."""
    first, spread = ranges.field("first").to_numpy().astype(np.int64), ranges.field("spread").to_numpy().astype(np.int64)
    step = np.zeros(len(raw) + 1, np.int64)
    np.add.at(step, first, 1)
    np.add.at(step, np.minimum(first + spread + length, len(raw)), -1)
    gone = np.cumsum(step[:-1]) > 0
    x = np.frombuffer(raw, np.uint8)
    return x[~gone].tobytes(), int(gone.sum()), int((gone & ~np.concatenate([[False], gone[:-1]])).sum())


def frequent(docs: DataFrame, length: int, gram: int, sample: float, often: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchor hashes found `often` times or more on a sample of the rows, sorted, and their rows estimated from it."""
    some = keyed(docs if sample >= 1 else docs.sample(sample, seed=11)).mapInArrow(_scan(length, gram), ROWS)
    counts = some.groupBy("fp").agg(F.sum(F.col("twice") + F.lit(1)).alias("n")).where(F.col("n") >= often)
    got = sorted((r["fp"], r["n"]) for r in counts.orderBy(F.desc("n"), "fp").limit(HOT).collect())
    return np.array([g[0] for g in got], np.int64), np.array([min(int(g[1] / sample), (1 << 31) - 1) for g in got], np.int32)


def repeated(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, step: int = STEP, bucket_bytes: int = BUCKET_BYTES, sample: float = SAMPLE, often: int = OFTEN) -> tuple[DataFrame, DataFrame]:
    """The keyed texts, and k1, k2, ranges: starts of repeated windows (first .. first + spread) of each text that has any."""
    texts = keyed(docs)
    found = texts.mapInArrow(_scan(length, gram, frequent(docs, length, gram, sample, often)), ROWS)
    group, same = Window.partitionBy("fp", "deal"), Window.partitionBy("fp", "deal", "ctx")
    n = F.sum(F.col("twice") + F.lit(1))
    classed = (
        found.repartition("fp", "deal").withColumn("n", n.over(same)).withColumn("rep", F.min(F.struct("k1", "k2", "first")).over(same))
        .withColumn("total", n.over(group)).withColumn("low", F.min("n").over(group)).withColumn("rows", F.when(F.col("hint") > 0, F.col("hint").cast("long")).otherwise(F.count(F.lit(1)).over(group)))
        .where("total > 1 OR hint > 0")
    )
    contested = (F.col("hint") > 0) | (F.col("hint") == 0) & (F.col("total") > F.col("n")) & (F.col("low") == 1)
    ask = contested & (F.struct("k1", "k2", "first") == F.col("rep"))
    whole = F.col("n") > 1
    marks = materialise(classed.where(ask | whole).select("k1", "k2", "first", "spread", whole.alias("whole"), ask.alias("ask"), *(F.when(ask, F.col(c)).alias(c) for c in ("fp", "ctx", "lead", "rows"))), "marks")
    ranges = marks.where("whole").select("k1", "k2", "first", "spread")
    size = marks.where("ask").agg(F.sum(F.col("spread") + F.lit(length))).first()[0]
    if size:
        most = length - gram + 1
        load = F.col("rows") * F.lit(2.0 * length / bucket_bytes)
        parts = F.greatest(F.lit(1), F.least(F.lit(most), F.ceil(load))).cast("int").alias("parts")
        salts = F.greatest(F.lit(1), F.ceil(load / most)).cast("int").alias("salts")
        asked = marks.where("ask").groupBy("k1", "k2").agg(F.collect_list(F.struct("fp", "ctx", "first", "lead", "spread", parts, salts)).alias("asked"))
        contexts = texts.join(asked, ["k1", "k2"]).select("doc_id", "k1", "k2", "raw", "asked").mapInArrow(_extract(length), "fp long, part int, salt int, k1 long, k2 short, start int, bytes binary")
        buckets = max(1, -(-size // bucket_bytes))
        dealt = contexts.withColumn("bucket", F.pmod(F.xxhash64("fp", "part", "salt"), F.lit(buckets))).repartition(min(buckets, 1 << 16), "bucket")
        ranges = ranges.unionByName(dealt.groupBy("bucket").applyInArrow(_merge(length, step), "k1 long, k2 short, first int, spread short"))
    return texts, ranges.groupBy("k1", "k2").agg(F.collect_list(F.struct("first", "spread")).alias("ranges"))


def remove(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    length = options.get("length", LENGTH)
    texts, ranges = repeated(docs, **options)
    return texts.join(ranges, ["k1", "k2"], "left").select("doc_id", "k1", "k2", "raw", "ranges").mapInArrow(_apply(length), SCHEMA)


def kept_text(docs: DataFrame, **options) -> DataFrame:
    """doc_id, kept (binary): what is left of each text."""
    length = options.get("length", LENGTH)
    texts, ranges = repeated(docs, **options)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            kept = [cut(raw, m.values, length)[0] if m.is_valid else raw for raw, m in zip(b.column("raw").to_pylist(), b.column("ranges"), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(kept, pa.binary())], names=["doc_id", "kept"])

    return texts.join(ranges, ["k1", "k2"], "left").select("doc_id", "raw", "ranges").mapInArrow(run, "doc_id long, kept binary")
