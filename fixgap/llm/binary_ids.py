"""Token ids as flat unsigned integer files with 64-bit document offsets.

Documents are dealt out by ranges of doc_id and sorted, so each task writes the next stretch of the corpus: a data file of
ids and nothing else, an index file of document offsets (n + 1 unsigned 64-bit integers), and a file of doc_ids. A task's
files carry its attempt in their names, and only the manifest, which Spark commits, says which files count: a lost executor
leaves at most files that nobody reads. Global positions need no pass over the data: the base of a partition is the prefix
sum of the manifest's token counts before it. Local files are memory-mapped; files elsewhere are read by ranges.

Nulls: a null text is empty and holds the end id only. Null doc_ids come first. Rows of one doc_id stay together in order of
their text's hash, then text; extra columns are ignored; an empty table gives an empty manifest and no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words
from .base import materialise, shared_path

CACHE_WORDS = 600_000
MANIFEST = "part int, n_docs long, n_null long, n_tokens long, name string"


@dataclass
class IdFiles:
    """url: the folder; parts: (name, first document, base token, documents, null doc_ids, tokens) in order."""

    url: str
    dtype: str
    parts: list[tuple[str, int, int, int, int, int]]

    @property
    def n_tokens(self) -> int:
        return sum(p[5] for p in self.parts)


def _open(url: str) -> tuple[pafs.FileSystem, str]:
    fs, path = pafs.FileSystem.from_uri(url)
    return fs, path


def write(docs: DataFrame, tokenizer: str, end_id: int | None = 2, url: str | None = None) -> IdFiles:
    """Encode whole texts, append end_id to each, and write the files to url (the session's shared folder if none is given)."""
    spark = docs.sparkSession
    url = url or shared_path(spark, "ids")
    dtype = words.width(tokenizer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = words.table_of_worker(tokenizer, dtype, CACHE_WORDS)
        task = TaskContext.get()
        name = f"part-{task.partitionId():06d}-{task.taskAttemptId()}"
        fs, path = _open(url)
        n_null = n_tokens = 0
        ends: list[np.ndarray] = []
        ids_of: list[np.ndarray] = []
        out = None
        for b in batches:
            if not b.num_rows:
                continue
            if out is None:
                fs.create_dir(path, recursive=True)
                out = fs.open_output_stream(f"{path}/{name}.bin")
            for first, texts in words.batches_of(b.column("raw").to_pylist()):
                split = [words.split(t) for t in texts]
                at = table.places([w for ws in split for w in ws])
                n = table.lens[at]
                edges = np.concatenate([[0], np.cumsum([len(ws) for ws in split])])
                sums = np.concatenate([[0], np.cumsum(n)])
                stops = sums[edges[1:]]
                got = table.ids(at)
                if end_id is not None:
                    got = np.insert(got, stops, end_id)
                    stops = stops + np.arange(1, len(stops) + 1)
                out.write(got.astype(dtype).tobytes())
                ends.append(stops + n_tokens)
                n_tokens += len(got)
                col = b.column("doc_id").slice(first, len(texts))
                n_null += col.null_count
                ids_of.append(col.fill_null(0).to_numpy(zero_copy_only=False))
        if out is None:
            return
        out.close()
        for suffix, data in (("idx", np.concatenate([[0], *ends]).astype("<u8")), ("doc", np.concatenate(ids_of).astype("<i8"))):
            with fs.open_output_stream(f"{path}/{name}.{suffix}") as f:
                f.write(data.tobytes())
        yield pa.RecordBatch.from_arrays([pa.array([task.partitionId()], pa.int32()), *(pa.array([x], pa.int64()) for x in (sum(map(len, ids_of)), n_null, n_tokens)), pa.array([name])], names=["part", "n_docs", "n_null", "n_tokens", "name"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    keyed = rows.select("doc_id", F.xxhash64("text").alias("h"), F.col("text").cast("binary").alias("raw"))
    dealt = keyed.repartitionByRange("doc_id", "h").sortWithinPartitions("doc_id", "h", "raw").select("doc_id", "raw")
    manifest = materialise(dealt.mapInArrow(run, MANIFEST), "manifest").orderBy("part").collect()  # a row for each task
    parts, first, base = [], 0, 0
    for r in manifest:
        parts.append((r["name"], first, base, r["n_docs"], r["n_null"], r["n_tokens"]))
        first, base = first + r["n_docs"], base + r["n_tokens"]
    return IdFiles(url, dtype, parts)


class Part:
    """One partition's files, opened by a reader."""

    def __init__(self, url: str, name: str, dtype: str):
        self.dtype = np.dtype(dtype)
        fs, path = _open(url)
        base = f"{path}/{name}"
        if isinstance(fs, pafs.LocalFileSystem):
            read = lambda suffix, kind: np.memmap(f"{base}.{suffix}", kind, "r")
            self._ids = read("bin", self.dtype) if fs.get_file_info(f"{base}.bin").size else np.zeros(0, self.dtype)
            self.offsets, self.doc_ids = read("idx", "<u8"), read("doc", "<i8")
        else:
            read = lambda suffix, kind: np.frombuffer(fs.open_input_file(f"{base}.{suffix}").read(), kind)
            self._ids, self._file = None, fs.open_input_file(f"{base}.bin")
            self.offsets, self.doc_ids = read("idx", "<u8"), read("doc", "<i8")

    def ids(self, i: int) -> np.ndarray:
        a, b = int(self.offsets[i]), int(self.offsets[i + 1])
        if self._ids is not None:
            return self._ids[a:b]
        return np.frombuffer(self._file.read_at((b - a) * self.dtype.itemsize, a * self.dtype.itemsize), self.dtype)


def read(spark: SparkSession, files: IdFiles, ids: bool = False) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids_crc32 (of the ids as unsigned 32-bit), and ids if wanted."""
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * ids
    if not files.parts:
        return spark.createDataFrame([], schema)
    url, dtype = files.url, files.dtype

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, base, n_null in zip(*(b.column(c).to_pylist() for c in ("name", "base", "n_null")), strict=True):
                part = Part(url, name, dtype)
                n = len(part.doc_ids)
                for lo in range(0, n, 4096):
                    some = range(lo, min(lo + 4096, n))
                    tokens = [part.ids(i) for i in some]
                    cols = [
                        pa.array(np.array(part.doc_ids[lo : some.stop]), pa.int64(), mask=np.arange(lo, some.stop) < n_null),
                        pa.array(base + np.array(part.offsets[lo : some.stop], np.int64)),
                        pa.array([len(t) for t in tokens], pa.int64()),
                        pa.array([zlib.crc32(t.astype("<u4").tobytes()) for t in tokens], pa.int64()),
                    ]
                    yield pa.RecordBatch.from_arrays(cols + ([pa.array([t.astype(np.int32) for t in tokens], pa.list_(pa.int32()))] if ids else []), names=["doc_id", "start", "n_tokens", "ids_crc32"] + ["ids"] * ids)

    rows = spark.createDataFrame([(p[0], p[2], p[4]) for p in files.parts], "name string, base long, n_null long")
    return rows.repartition(len(files.parts)).mapInArrow(run, schema)
