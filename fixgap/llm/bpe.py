"""BPE encoding and decoding through a distinct-word table.

Spark splits texts into words and deals the texts into chunks of bounded size. Each chunk sends its distinct words, packed by
hash bucket; each bucket encodes a word once, however many chunks have it: that is the distinct-word table. For decoding, its ids
are joined with their pieces through the vocabulary, which is of fixed size. A bucket answers every chunk in the order asked, and
back in its chunk a text's ids (and pieces) are gathered by word position. A frequent word reaches its bucket once for each
chunk, not once for each use, so no word is hot.

Nulls: a null text is empty and has no ids. Repeated rows stay, each with the same values; extra columns are ignored; an
empty table gives an empty table. A text longer than a chunk makes its chunk longer; no text is cut.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words
from .base import give_back, materialise

CHUNK_BYTES = 16 << 20
PACK_BYTES = 32 << 20  # of words that a task packs by chunk at once
MAX_BUCKETS = 50_000
MAX_PARTITIONS = 50_000
DIGESTS = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def _buckets(distinct: set[bytes] | dict, n: int) -> dict[int, list[bytes]]:
    """Sorted words of each bucket; a chunk asks and reads answers in this order."""
    out: dict[int, list[bytes]] = {}
    crc = zlib.crc32
    for w in sorted(distinct):
        out.setdefault(crc(w) % n, []).append(w)
    return out


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of one chunk put together: ids of documents, byte lengths and, compressed, their words."""
    held: dict[int, tuple[list, list[bytes]]] = {}
    size = 0

    def flush() -> pa.RecordBatch:
        cols = [pa.array(list(held), pa.int32()), pa.array([d for d, _ in held.values()], pa.list_(pa.int64())), pa.array([list(map(len, t)) for _, t in held.values()], pa.list_(pa.int32()))]
        return pa.RecordBatch.from_arrays([*cols, pa.array([zlib.compress(b"".join(t), 1) for _, t in held.values()], pa.binary())], names=["chunk", "doc_ids", "sizes", "texts"])

    for b in batches:
        for chunk, doc, text in zip(*(b.column(c).to_pylist() for c in ("chunk", "doc_id", "raw")), strict=True):
            docs, texts = held.setdefault(chunk, ([], []))
            docs.append(doc)
            texts.append(text)
            size += len(text)
            if size > PACK_BYTES:
                yield flush()
                held.clear()
                size = 0
    if held:
        yield flush()
    held.clear()
    give_back()


def _texts(sizes: list[int], blob: bytes) -> Iterator[list[bytes]]:
    """The words of each packed text, one text's at a time."""
    raw, at = zlib.decompress(blob), 0
    for n in sizes:
        yield raw[at : at + n].split(b"\n") if n else []
        at += n


def _ask(n_buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[int, set[bytes]] = {}
        for b in batches:
            for chunk, sizes, blob in zip(*(b.column(c).to_pylist() for c in ("chunk", "sizes", "texts")), strict=True):
                known = seen.setdefault(chunk, set())
                for ws in _texts(sizes, blob):
                    known.update(ws)
        for chunk in list(seen):
            found = _buckets(seen.pop(chunk), n_buckets)
            blobs = [zlib.compress(b"\n".join(ws), 1) for ws in found.values()]
            yield pa.RecordBatch.from_arrays([pa.array([chunk] * len(found), pa.int32()), pa.array(list(found), pa.int32()), pa.array(blobs, pa.binary())], names=["chunk", "bucket", "words"])
        give_back()

    return run


def _distinct(tokenizer: str, dtype: str):
    """The distinct-word table of a bucket, a row for each word: its number and ids. After it a row for each chunk that asked: the
    numbers of its words in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = words.Table(words.load(tokenizer), dtype)
        asks: list[tuple] = []
        names, none = ["no", "chunk", "bucket", "refs", "ids"], None
        for b in batches:
            for chunk, bucket, blob in zip(*(b.column(c).to_pylist() for c in ("chunk", "bucket", "words")), strict=True):
                first = len(table.index)
                at = table.places(zlib.decompress(blob).split(b"\n"))
                asks.append((-1, chunk, bucket, zlib.compress(at.astype("<u4").tobytes(), 1), none))
                some = np.arange(first, len(table.index))
                if len(some):
                    ids = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *table.lens[some].tolist()]), pa.int32()), pa.array(table.ids(some).astype(np.int32)))
                    yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), *(pa.nulls(len(some), t) for t in (pa.int32(), pa.int32(), pa.binary())), ids], names=names)
        if asks:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*asks, strict=True), (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.list_(pa.int32())), strict=True)], names=names)

    return run


def _ids_alone(tokenizer: str, dtype: str):
    """For every ask lengths and ids of its words in order, where nothing is to be decoded. Asks pass one at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = words.Table(words.load(tokenizer), dtype)
        for b in batches:
            for chunk, bucket, blob in zip(*(b.column(c).to_pylist() for c in ("chunk", "bucket", "words")), strict=True):
                at = table.places(zlib.decompress(blob).split(b"\n"))
                said = zlib.compress(table.lens[at].astype("<u4").tobytes() + table.ids(at).tobytes(), 1)
                yield pa.RecordBatch.from_arrays([pa.array([chunk], pa.int32()), pa.array([bucket], pa.int32()), pa.array([said], pa.binary())], names=["chunk", "bucket", "ids"])
        give_back()

    return run


def _answers(dtype: str):
    """Words' ids and pieces, and asks -> for every ask: lengths and ids of its words in order, then lengths and bytes of their
    decoded pieces (joined by spaces). Everything of one bucket is in one partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        no, pos, ids, pieces, asks = [], [], [], [], []
        for b in batches:
            here = b.column("no").to_numpy()
            for i in np.flatnonzero(here < 0).tolist():
                asks.append(tuple(b.column(c)[i].as_py() for c in ("chunk", "bucket", "refs")))
            on = pa.array((here >= 0) & b.column("id").is_valid().to_numpy(zero_copy_only=False))
            rows = b.filter(on)
            no.append(rows.column("no").to_numpy())
            pos.append(rows.column("pos").to_numpy(zero_copy_only=False).astype(np.int64))
            ids.append(rows.column("id").to_numpy(zero_copy_only=False).astype(dtype))
            pieces += rows.column("piece").to_pylist()
        if not asks:
            return
        no, pos, ids = np.concatenate(no), np.concatenate(pos), np.concatenate(ids)
        if len(no) > 1 and not ((no[1:] > no[:-1]) | ((no[1:] == no[:-1]) & (pos[1:] > pos[:-1]))).all():
            order = np.lexsort((pos, no))
            no, ids, pieces = no[order], ids[order], [pieces[i] for i in order.tolist()]
        numbers = [np.frombuffer(zlib.decompress(r), "<u4").astype(np.int64) for _, _, r in asks]
        n = np.bincount(no, minlength=max(int(x.max(initial=-1)) for x in numbers) + 1)
        ends = np.cumsum(n)
        said = [" ".join(pieces[a:b]).encode() for a, b in zip((ends - n).tolist(), ends.tolist(), strict=True)]
        m = np.array([len(x) for x in said], "<u4")
        for (chunk, bucket, _), at in zip(asks, numbers, strict=True):
            parts = [n[at].astype("<u4").tobytes(), words.gather(ids, ends - n, n, at).tobytes(), m[at].tobytes(), b"".join([said[i] for i in at.tolist()])]
            yield pa.RecordBatch.from_arrays([pa.array([chunk], pa.int32()), pa.array([bucket], pa.int32()), pa.array([zlib.compress(b"".join(parts), 1)], pa.binary())], names=["chunk", "bucket", "ids"])

    return run


def vocabulary(spark, tokenizer: str) -> DataFrame:
    """id, piece: a table of fixed size."""
    return spark.createDataFrame([(i, p) for i, p in enumerate(words.pieces(tokenizer)) if p is not None], "id int, piece string")


def joined_pieces(encoded: DataFrame, vocab: DataFrame, keys: list[str]) -> DataFrame:
    """keys, ids, decoded: each row's ids joined with their pieces, a space between, as the library does without a decoder.
    Rows without ids are left out; keys must tell rows apart."""
    flat = encoded.select(*keys, F.posexplode("ids").alias("pos", "id")).join(F.broadcast(vocab), "id")  # the vocabulary is of fixed size
    rows = flat.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("pos", "id", "piece"))).alias("x"))
    return rows.select(*keys, F.transform("x", lambda p: p["id"]).alias("ids"), F.array_join(F.transform("x", lambda p: p["piece"]), " ").alias("decoded"))


def _lookup(texts: Iterator[list[bytes]], answers: pa.Table, n_buckets: int, dtype: str, spelt: bool):
    """word -> place, with flat ids, starts, lengths and (spelt) decoded pieces, from the answers to this chunk."""
    distinct: set[bytes] = set()
    for ws in texts:
        distinct.update(ws)
    asked = _buckets(distinct, n_buckets)
    got = dict(zip(answers.column("bucket").to_pylist(), answers.column("ids").to_pylist(), strict=True))
    index: dict[bytes, int] = {}
    flat, lens, said = [], [], []
    for bucket, ws in asked.items():
        raw = zlib.decompress(got[bucket])
        lens.append(np.frombuffer(raw, "<u4", len(ws)).astype(np.int64))
        flat.append(np.frombuffer(raw, dtype, int(lens[-1].sum()), 4 * len(ws)))
        at = 4 * len(ws) + flat[-1].nbytes
        index.update(zip(ws, range(len(index), len(index) + len(ws)), strict=True))
        if not spelt:
            if at != len(raw):
                raise ValueError("an answer doesn't match the words asked for")
            continue
        ends = (at + 4 * len(ws) + np.cumsum(np.frombuffer(raw, "<u4", len(ws), at).astype(np.int64))).tolist()
        if ends[-1] != len(raw):
            raise ValueError("an answer doesn't match the words asked for")
        said += [raw[a:b] for a, b in zip([at + 4 * len(ws), *ends], ends, strict=False)]
    n = np.concatenate(lens) if lens else np.zeros(0, np.int64)
    return index, np.concatenate(flat) if flat else np.zeros(0, dtype), np.cumsum(n) - n, n, said


def _join(docs: DataFrame, tokenizer: str, finish, schema: str, spelt: bool = True) -> DataFrame:
    """finish(doc_ids, texts' words, index, flat, start, lens, said) -> a table, for each chunk with its words' ids and, where
    they are to be spelt, pieces."""
    dtype = words.width(tokenizer)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    n = max(1, -(-size // CHUNK_BYTES))
    buckets = min(n, MAX_BUCKETS)
    # by both, so that neither rows of one doc_id nor copies of one text meet in one chunk
    chunk = F.pmod(F.xxhash64("doc_id", "text"), F.lit(n)).cast("int").alias("chunk")
    dealt = rows.select("doc_id", F.array_join(words.split_column(F.col("text")), "\n").cast("binary").alias("raw"), chunk)
    chunks = _deal(dealt.mapInArrow(_pack, "chunk int, doc_ids array<long>, sizes array<int>, texts binary"), n)
    asked = chunks.mapInArrow(_ask(buckets), "chunk int, bucket int, words binary").repartitionById(buckets, F.col("bucket"))
    if spelt:
        table = asked.mapInArrow(_distinct(tokenizer, dtype), "no long, chunk int, bucket int, refs binary, ids array<int>")
        flat = table.select("no", "chunk", "bucket", "refs", F.posexplode_outer("ids").alias("pos", "id"))
        pieces = flat.join(F.broadcast(vocabulary(docs.sparkSession, tokenizer)), "id", "left")  # the vocabulary is of fixed size
        answered = pieces.select("no", "chunk", "bucket", "refs", "pos", "id", "piece").mapInArrow(_answers(dtype), "chunk int, bucket int, ids binary")
    else:
        answered = asked.mapInArrow(_ids_alone(tokenizer, dtype), "chunk int, bucket int, ids binary")

    def solve(left: pa.Table, right: pa.Table) -> pa.Table:
        doc_ids = pa.array([d for some in left.column("doc_ids").to_pylist() for d in some], pa.int64())

        def texts() -> Iterator[list[bytes]]:  # split twice, so that a chunk's words are never all held
            for sizes, blob in zip(left.column("sizes"), left.column("texts"), strict=True):
                yield from _texts(sizes.as_py(), blob.as_py())

        done = finish(doc_ids, texts(), *_lookup(texts(), right, buckets, dtype, spelt))
        give_back()
        return done

    return chunks.groupBy("chunk").cogroup(_deal(answered, n).groupBy("chunk")).applyInArrow(solve, schema)


def _deal(df: DataFrame, n: int) -> DataFrame:
    """A chunk is a partition; where there are very many, partitions hold several chunks."""
    return df.repartitionById(n, F.col("chunk")) if n <= MAX_PARTITIONS else df.repartition(MAX_PARTITIONS, "chunk")


def encode(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, ids: the ids of whole texts, without added special tokens."""

    def finish(doc_ids, texts, index, flat, start, lens, said):
        ids = [words.gather(flat, start, lens, np.fromiter(map(index.__getitem__, ws), np.int64, len(ws))) for ws in texts]
        edges = pa.array(np.cumsum([0, *map(len, ids)]), pa.int32())
        return pa.table({"doc_id": doc_ids, "ids": pa.ListArray.from_arrays(edges, pa.array(np.concatenate(ids).astype(np.int32)))})

    return _join(docs, tokenizer, finish, "doc_id long, ids array<int>", spelt=False)


def decode(encoded: DataFrame, tokenizer: str) -> DataFrame:
    """The columns of encoded, and decoded: its ids through the id-to-piece join. Rows are numbered in a table first, so repeated
    or null keys don't mix. Null ids decode to an empty text."""
    rows = materialise(encoded.withColumn("_row", F.monotonically_increasing_id()), "encoded")
    text = joined_pieces(rows.select("_row", "ids"), vocabulary(encoded.sparkSession, tokenizer), ["_row"]).select("_row", F.col("decoded").alias("_text"))
    return rows.join(text, "_row", "left").select(*encoded.columns, F.coalesce("_text", F.lit("")).alias("decoded"))


def round_trip(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, decoded: texts after encoding and decoding."""

    def finish(doc_ids, texts, index, flat, start, lens, said):
        return pa.table({"doc_id": doc_ids, "decoded": pa.array([_said(ws, index, said).decode() for ws in texts], pa.string())})

    return _join(docs, tokenizer, finish, "doc_id long, decoded string")


def _said(ws: list[bytes], index: dict[bytes, int], said: list[bytes]) -> bytes:
    """A text's pieces, from those of its words; words without ids say nothing."""
    return b" ".join([x for w in ws if (x := said[index[w]])])


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256."""

    def finish(doc_ids, texts, index, flat, start, lens, said):
        n, a, b = [], [], []
        for ws in texts:
            ids = words.gather(flat, start, lens, np.fromiter(map(index.__getitem__, ws), np.int64, len(ws)))
            n.append(len(ids))
            a.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
            b.append(hashlib.sha256(_said(ws, index, said)).hexdigest())
        return pa.table({"doc_id": doc_ids, "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(a, pa.string()), "decoded_sha256": pa.array(b, pa.string())})

    return _join(docs, tokenizer, finish, DIGESTS)
