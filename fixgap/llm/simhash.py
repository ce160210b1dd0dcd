"""SimHash near-duplicates with covering locality-sensitive hashing.

A text's fingerprint has bit i set if more than half of its shingles' hashes have. Two fingerprints link at `radius` or
fewer differing bits. Each bit position gets a non-zero vector of radius + 1 bits; for every non-zero vector v there is a
mask of the positions whose vector has an odd inner product with v. Any `radius` positions leave some v with even
products only, so that mask skips them all: every pair within the radius agrees on some mask, with certainty.

Fingerprints, not documents, are compared, so copies cost nothing. A bucket (mask, masked bits) of bounded size is solved
in one task, which returns a spanning forest of its links, never all pairs. A larger bucket is split by a second family of
masks over the bits that its first mask left out, and so on; every level fixes bits, so buckets shrink to the bound.

Nulls: a null or wordless text has fingerprint zero, linked like any other. Texts with one or two words use the whole
sequence as one shingle. A null doc_id takes part in links, but is never a component's id unless no other is there.
Repeated rows stay and share a component; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .base import is_empty, materialise
from .components import connected

BUCKET = 1024  # fingerprints of a bucket that one task compares with one another
BITS = 64


def fingerprint(text: bytes, words: int = 3, seed: int = 42) -> int:
    w = text.lower().split()  # of bytes: A-Z only, and white space 0x20, 0x09-0x0D
    if not w:
        return 0
    grams = map(b" ".join, zip(*(w[i:] for i in range(words)), strict=False)) if len(w) >= words else [b" ".join(w)]
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(g, seed) for g in grams], np.uint64)
    ones = np.zeros(BITS, np.int64)
    for i in range(0, len(h), 4096):
        part = h[i : i + 4096]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int32)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, words: int = 3) -> DataFrame:
    """doc_id, fp (the unsigned fingerprint's bits as a long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(x or b"", words) for x in b.column("raw").to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    raw = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("raw"))
    return raw.mapInArrow(run, "doc_id long, fp long")


def covering_masks(positions: list[int], radius: int) -> list[int]:
    """Masks over the given bit positions such that any `radius` of them are all left out by at least one mask."""
    vectors = [1 + i % ((1 << radius + 1) - 1) for i in range(len(positions))]
    return [sum(1 << p for p, x in zip(positions, vectors, strict=True) if (x & v).bit_count() & 1) for v in range(1, 1 << radius + 1)]


def _signed(n: int) -> int:
    return n - (1 << 64) if n >> 63 else n


def _forest(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links of a spanning forest of the graph on these distinct fingerprints."""
    n, out = len(fps), []
    left = np.arange(n)
    while len(left):  # breadth first from one root after another; each node is compared once with what is left
        front, left = left[:1], left[1:]
        while len(front) and len(left):
            near = np.bitwise_count(fps[front, None] ^ fps[None, left]) <= radius
            hit = near.any(0)
            if not hit.any():
                break
            out.extend(zip(fps[front[near[:, hit].argmax(0)]].tolist(), fps[left[hit]].tolist(), strict=True))
            front, left = left[hit], left[~hit]
    return out


def _solve(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        last = None

        def links(group: np.ndarray) -> list[tuple[int, int]]:
            return _forest(np.unique(group).view(np.uint64), radius)

        for b in batches:
            keys = np.stack([b.column(c).to_numpy(zero_copy_only=False) for c in ("space", "key")])
            fps = b.column("fp").to_numpy(zero_copy_only=False)
            cut = np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(0)) + 1
            pairs: list[tuple[int, int]] = []
            for start, end in zip([0, *cut], [*cut, len(fps)], strict=True):
                if start == end:
                    continue
                here = (int(keys[0, start]), int(keys[1, start]))
                if here != last and held:
                    pairs += links(np.concatenate(held))
                    held = []
                held.append(fps[start:end])
                last = here
            if pairs:
                yield _pairs(pairs)
        if held and (pairs := links(np.concatenate(held))):
            yield _pairs(pairs)

    return run


def _pairs(pairs: list[tuple[int, int]]) -> pa.RecordBatch:
    x = np.array(pairs, np.uint64).view(np.int64).reshape(-1, 2)
    return pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1])], names=["a", "b"])


def links(fps: DataFrame, radius: int = 3, bucket: int = BUCKET) -> DataFrame:
    """fp (distinct) -> a, b: links that connect all fingerprints within the radius of one another, directly or by others' links."""
    spark = fps.sparkSession
    found, level = None, 0
    # space: which mask of which parent; done: the bits fixed so far
    rows = fps.select("fp", F.lit(0).cast("long").alias("done"), F.lit(0).cast("long").alias("space"))
    spaces = [0]
    while spaces:
        # a row for each mask of each set of bits fixed so far: 15 to the level's power at most
        rules = [(_signed(d), _signed(d | m), _signed(m)) for d in spaces for m in dict.fromkeys(covering_masks([p for p in range(BITS) if not d >> p & 1], radius))]
        masks = F.broadcast(spark.createDataFrame(rules, "done long, next long, mask long"))
        keyed = rows.join(masks, "done").select("fp", F.col("next").alias("done"), F.xxhash64("space", "next", "mask").alias("space"), F.col("fp").bitwiseAND(F.col("mask")).alias("key"))
        sizes = keyed.groupBy("space", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        shared = materialise(keyed.join(sizes, ["space", "key"]), f"buckets{level}")
        here = shared.where(F.col("n") <= bucket).select("space", "key", "fp").repartition("space", "key").sortWithinPartitions("space", "key").mapInArrow(_solve(radius), "a long, b long")
        found = here if found is None else found.unionByName(here)
        large = shared.where(F.col("n") > bucket)
        spaces = [r["done"] & (1 << 64) - 1 for r in large.select("done").distinct().collect()]  # at most 15 to the level's power
        rows = large.select("fp", "done", F.xxhash64("space", "key").alias("space"))
        level += 1
    return found if found is not None else spark.createDataFrame([], "a long, b long")


def near_duplicates(docs: DataFrame, radius: int = 3, words: int = 3, bucket: int = BUCKET) -> DataFrame:
    """doc_id, fp, component_id: the smallest doc_id that links reach, itself included."""
    fps = materialise(fingerprints(docs, words), "fingerprints")
    distinct = materialise(fps.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("n")), "distinct")
    edges = links(distinct.select("fp"), radius, bucket)
    edges = materialise(edges, "links")
    if is_empty(edges):
        return fps.join(distinct.select("fp", F.col("low").alias("component_id")), "fp").select("doc_id", "fp", "component_id")
    roots = connected(edges)
    rooted = distinct.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "low", F.coalesce("root", "fp").alias("root"))
    lows = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    label = rooted.join(lows, "root").select("fp", "component_id")
    return fps.join(label, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """One document of each component, with all its columns: that with the smallest doc_id.

    Where a component's rows share that doc_id (repeated rows) or have none, one of them stays, chosen by its text's hash.
    """
    found = materialise(near_duplicates(docs, **options), "components")
    first = found.where(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("_id"))
    sizes = first.agg(F.count(F.lit(1)), F.count_distinct("_id")).first()
    if sizes[0] == sizes[1] and is_empty(found.where("component_id IS NULL")):
        return docs.join(first, F.col("doc_id") == F.col("_id"), "left_semi")
    label = found.groupBy("fp").agg(F.min("component_id").alias("_component"))
    rows = with_fingerprint(docs, "_fp", options.get("words", 3)).join(label.withColumnRenamed("fp", "_label_fp"), F.col("_fp") == F.col("_label_fp"))
    rows = rows.where(F.col("doc_id").cast("long").eqNullSafe(F.col("_component")))
    group = F.when(F.col("_component").isNull(), F.col("_fp")).otherwise(F.col("_component"))  # null ids only: one row for each fingerprint
    pick = F.min_by(F.struct(*docs.columns), F.struct(F.xxhash64("text"), F.col("text")))
    return rows.groupBy(F.col("_component").isNull(), group).agg(pick.alias("_row")).select("_row.*")


def with_fingerprint(docs: DataFrame, name: str, words: int = 3) -> DataFrame:
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint((x or "").encode(), words) for x in b.column(at).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(fps.view(np.int64))], names=[*b.schema.names, name])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(name, T.LongType())]))


def hex_digits(fp: str = "fp"):
    return F.lower(F.lpad(F.hex(F.col(fp)), 16, "0"))
