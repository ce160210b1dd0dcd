"""Near copies by SimHash fingerprints, and by word shingles beyond their reach.

Two texts are near copies if their fingerprints (of three-word shingles, as in simhash.py) differ in three bits or fewer; covering
masks find all such pairs. Three bits are about a similarity of 0.97, so texts are near copies as well if their sets of five-word
shingles have a Jaccard similarity of at least 0.8: min-wise hashing finds candidates, the sets themselves decide. Sets are kept as
32-bit hashes of shingles (two sets of n shingles share n * n / 2^32 by chance, so a similarity is off by less than n / 2^32;
keys of whole sets and of bands have 64 bits). Each set has BANDS x ROWS smallest hashes, under as many multipliers; a band's are one key, and
sets that share a key are candidates. A pair of similarity s is missed with probability (1 - s^ROWS)^BANDS: 0.0004 at 0.8.

Equal sets count once. In buckets of up to SMALL sets all pairs are compared. In a larger one, LEADERS sets in the largest buckets
are compared with all others first, which joins most of a group of near copies into one component. Buckets that are in one
component are done. In the others, the sets outside the largest component are compared with all of the bucket, inside tasks: cells
of at most about SIDE of them by SIDE of the bucket's sets, by products of 0-1 blocks of sets by shingles. A cell returns a forest of
the links between components, so no rows are made of pairs, and no pair in question is left out.

Words are of bytes, split at ASCII white space with A-Z lowered; a text of under five words is one shingle, and wordless texts
(null ones too) are equal. A null doc_id is a component's id only if no other is there.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import simhash
from .base import give_back, is_empty, materialise
from .components import connected

WORDS = 5
BANDS, ROWS = 20, 5
SMALL = 16  # sets of a bucket that are all compared with one another
LEADERS = 2  # sets of a larger bucket that are compared with the rest first
SIDE = 1024  # sets on each side of a cell
LOAD = 1 << 19  # shingles on each side of a cell
COLUMNS = 2048  # shingles that a product takes at once
SLICE = 256  # documents whose sets a task holds at once
MULTIPLIERS = np.random.default_rng(8).integers(0, 1 << 63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
SKETCH = T.StructType([T.StructField("key", T.LongType()), T.StructField("fp", T.LongType()), T.StructField("size", T.LongType()), T.StructField("bands", T.ArrayType(T.LongType())), T.StructField("shingles", T.ArrayType(T.IntegerType()))])


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: bytes) -> np.ndarray:
    """The text's distinct shingles as hashes, in order."""
    w = text.lower().split()
    if not w:
        return np.zeros(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    known = {x: digest(x) for x in set(w)}
    hashes = np.fromiter(map(known.__getitem__, w), np.uint64, len(w))
    n = min(WORDS, len(w))
    out = np.full(len(w) - n + 1, np.uint64(n))
    for i in range(n):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + hashes[i : len(w) - n + 1 + i])
    return np.unique(out)


def bands(some: np.ndarray) -> np.ndarray:
    """The band keys of a set of shingles."""
    low = np.full(BANDS * ROWS, np.uint64(0xFFFFFFFFFFFFFFFF))
    for i in range(0, len(some), 4096):
        low = np.minimum(low, (MULTIPLIERS[:, None] * some[None, i : i + 4096]).min(1))
    out = np.arange(1, BANDS + 1, dtype=np.uint64)
    for row in low.reshape(BANDS, ROWS).T:
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + row)
    return out


def short(some: np.ndarray) -> np.ndarray:
    """A set's shingles as 32-bit hashes."""
    return np.unique((some >> np.uint64(32)).astype(np.uint32)).view(np.int32)


def _key(some: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(some.tobytes())


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0] + [len(x) for x in parts])
    flat = np.concatenate(parts) if parts else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat if flat.dtype == np.int32 else flat.view(np.int64)))


def _longs(values: list[int], kind=np.uint64) -> pa.Array:
    return pa.array(np.array(values, kind).view(np.int64))


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, key of the shingle set, the text's fingerprint, the set's size, band keys and shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x.slice(i, SLICE) for x in batches for i in range(0, x.num_rows, SLICE)):
            texts = b.column("raw").to_pylist()
            sets, fps = [shingles(x or b"") for x in texts], [simhash.fingerprint(x or b"") for x in texts]
            cols = [b.column("doc_id"), _longs([_key(s) for s in sets]), _longs(fps), _longs([len(s) for s in sets]), _lists([bands(s) for s in sets]), _lists([short(s) for s in sets])]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", *SKETCH.names])
        give_back()

    raw = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("raw"))
    return raw.mapInArrow(run, T.StructType([T.StructField("doc_id", T.LongType()), *SKETCH.fields]))


def _apart(pairs: DataFrame) -> DataFrame:
    """Pairs x, y with sizes m, n -> distinct a, b whose sizes allow the similarity."""
    return pairs.where(F.least("m", "n") * 5 >= F.greatest("m", "n") * 4).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def _similar(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs a, b whose sets have a Jaccard similarity of at least 0.8."""
    left, right = (sets.select(F.col("key").alias(c), F.col("shingles").alias("s" + c)) for c in "ab")
    both = F.size(F.array_intersect("sa", "sb"))  # of two sets with m and n elements: 5 both >= 4 (m + n - both)
    return pairs.join(left, "a").join(right, "b").where(both * 9 >= (F.size("sa") + F.size("sb")) * 4).select("a", "b")


def fingerprint_links(rows: DataFrame) -> DataFrame:
    """Sketches -> a, b (keys of sets): a star for each component of texts that fingerprints link."""
    kinds = materialise(rows.select("key", "fp").distinct(), "kinds")
    roots = connected(simhash.links(kinds.select("fp").distinct()))
    rooted = kinds.join(roots, F.col("fp") == F.col("node"), "left").select("key", F.coalesce("root", "fp").alias("root"))
    hubs = rooted.groupBy("root").agg(F.min("key").alias("b"))
    return rooted.join(hubs, "root").where("key != b").select(F.col("key").alias("a"), "b")


def _cell(group: pa.Table) -> pa.Table:
    """Links a, b of a forest that joins what the similar pairs of a cell's left and other sets join."""
    left = group.column("outside").to_numpy()
    key, root = group.column("key").to_numpy(), group.column("root").to_numpy()
    lists = group.column("shingles").combine_chunks()
    size = np.diff(lists.offsets.to_numpy())
    _, col, n = np.unique(lists.flatten().to_numpy(), return_inverse=True, return_counts=True)
    row, often = np.repeat(np.arange(len(key)), size), n > 1  # a shingle of one set is in no pair
    row, col = row[often[col]], (np.cumsum(often) - 1)[col[often[col]]]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    both = np.zeros((left.sum(), (~left).sum()), np.float32)  # whole numbers stay exact in single precision
    for a in range(0, int(often.sum()), COLUMNS):
        i, j = np.searchsorted(col, (a, a + COLUMNS))
        x = np.zeros((len(key), COLUMNS), np.float32)
        x[row[i:j], col[i:j] - a] = 1
        both += x[left] @ x[~left].T
    near = (both * 9 >= (size[left][:, None] + size[~left][None]) * 4) & (root[left][:, None] != root[~left][None])
    one, other, of_one, of_other = key[left], key[~left], root[left], root[~left]
    out = [np.zeros((0, 2), np.int64)]
    for i in np.flatnonzero(near.any(1)):
        hit = np.flatnonzero(near[i])
        roots, first = np.unique(of_other[hit], return_index=True)
        new = roots != of_one[i]
        out.append(np.stack([np.full(new.sum(), one[i]), other[hit[first[new]]]], 1))
        of_one, of_other = (np.where(np.isin(x, roots), of_one[i], x) for x in (of_one, of_other))
    out = np.concatenate(out)
    return pa.table([pa.array(out[:, 0]), pa.array(out[:, 1])], names=["a", "b"])


def _cells(rooted: DataFrame, sets: DataFrame, side: int) -> DataFrame:
    """bucket, key, size, root -> a, b: links between the components of each bucket."""
    parts = rooted.groupBy("bucket", "root").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("load"))
    whole = parts.groupBy("bucket").agg(F.sum("n").alias("n"), F.sum("load").alias("load"), F.max(F.struct("n", "root", "load")).alias("top")).where("n > top.n")

    def blocks(n, load):
        return F.greatest(F.lit(1), F.ceil(n / side), F.ceil(load / LOAD)).cast("int")

    whole = whole.select("bucket", F.col("top.root").alias("main"), blocks(F.col("n"), F.col("load")).alias("others"), blocks(F.col("n") - F.col("top.n"), F.col("load") - F.col("top.load")).alias("outs"))
    open_ = materialise(rooted.join(whole, "bucket"), "open")

    def part(n: str, salt: int):
        return F.pmod(F.xxhash64("key", F.lit(salt)), F.col(n)).cast("int")

    def every(n: str):
        return F.explode(F.sequence(F.lit(0), F.col(n) - 1))

    all_ = open_.select("bucket", "key", "root", every("outs").alias("i"), part("others", 1).alias("j"), F.lit(False).alias("outside"))
    outs = open_.where("root != main").select("bucket", "key", "root", part("outs", 2).alias("i"), every("others").alias("j"), F.lit(True).alias("outside"))
    return all_.unionByName(outs).join(sets, "key").groupBy("bucket", "i", "j").applyInArrow(_cell, "a long, b long")


def links(rows: DataFrame, small: int = SMALL, leaders: int = LEADERS, known: DataFrame | None = None, side: int = SIDE) -> DataFrame:
    """Sketches with a row number -> a, b (keys of sets): links that connect all candidates of enough similarity, directly or by
    others' links. known: further links, which come out too."""
    distinct = rows.groupBy("key").agg(F.first("size").alias("size"), F.first("bands").alias("bands"))
    entries = distinct.select("key", "size", F.explode("bands").alias("bucket"))
    sizes = entries.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = materialise(entries.join(sizes, "bucket"), "buckets")
    # one row for each set in question, chosen by row number, so that the shingles move once at most
    chosen_rows = rows.select("key", "row").join(shared.select("key").distinct(), "key", "left_semi").groupBy("key").agg(F.min("row").alias("row"))
    sets = materialise(rows.select("row", "shingles").join(chosen_rows, "row").select("key", "shingles"), "sets")
    few = shared.where(F.col("n") <= small)
    one, other = (few.select("bucket", F.col("key").alias(k), F.col("size").alias(s)) for k, s in ("xm", "yn"))
    pairs = one.join(other, "bucket").where("x < y").drop("bucket")
    active = shared.where(F.col("n") > small)
    large = not is_empty(active)
    if large:
        # a set in many large buckets is close to many others
        weight = active.groupBy("key").agg(F.sum("n").alias("weight"))
        active = materialise(active.join(weight, "key").select("bucket", "key", "size", "weight"), "active")
        pick = F.max_by(F.struct("key", "size"), F.struct("weight", "key")).alias("c")
        chosen = active.groupBy("bucket", F.pmod(F.xxhash64("key"), F.lit(leaders))).agg(pick).select("bucket", F.col("c.key").alias("x"), F.col("c.size").alias("m"))
        pairs = pairs.unionByName(active.select("bucket", F.col("key").alias("y"), F.col("size").alias("n")).join(chosen, "bucket").where("x != y").select("x", "m", "y", "n"))
    found = _similar(_apart(pairs), sets)
    found = materialise(found if known is None else found.unionByName(known), "links")
    if not large:
        return found
    rooted = active.join(connected(found), F.col("key") == F.col("node"), "left").select("bucket", "key", "size", F.coalesce("root", "key").alias("root"))
    return found.unionByName(materialise(_cells(materialise(rooted, "rooted"), sets, side), "links"))


def near_duplicates(docs: DataFrame, small: int = SMALL, leaders: int = LEADERS, by_fingerprint: bool = False, side: int = SIDE) -> DataFrame:
    """doc_id, key, root, component_id: the least key and the smallest doc_id that links reach, itself included.

    by_fingerprint: links of fingerprints count beside those of shingle sets.
    """
    rows = materialise(sketches(docs).withColumn("row", F.monotonically_increasing_id()), "shingles")  # numbers stay as written
    roots = connected(links(rows, small, leaders, fingerprint_links(rows) if by_fingerprint else None, side))
    lows = rows.groupBy("key").agg(F.min("doc_id").alias("low"))
    rooted = materialise(lows.join(roots, F.col("key") == F.col("node"), "left").select("key", "low", F.coalesce("root", "key").alias("root")), "rooted")
    label = rooted.join(rooted.groupBy("root").agg(F.min("low").alias("component_id")), "root").select("key", "root", "component_id")
    return rows.select("doc_id", "key").join(label, "key").select("doc_id", "key", "root", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component of both kinds of links, with all its columns: that with the smallest doc_id.

    Where a component's rows share that doc_id (repeated rows) or have none, one of them stays, chosen by its text's hash.
    """
    found = materialise(near_duplicates(docs, by_fingerprint=True), "components")
    first = found.where(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("_id"))
    sizes = first.agg(F.count(F.lit(1)), F.count_distinct("_id")).first()
    if sizes[0] == sizes[1] and is_empty(found.where("component_id IS NULL")):
        return docs.join(first, F.col("doc_id") == F.col("_id"), "left_semi")
    label = found.select(F.col("key").alias("_of"), F.col("root").alias("_root"), F.col("component_id").alias("_component")).distinct()
    rows = _with_key(docs, "_key").join(label, F.col("_key") == F.col("_of")).where(F.col("doc_id").cast("long").eqNullSafe(F.col("_component")))
    pick = F.min_by(F.struct(*docs.columns), F.struct(F.xxhash64("text"), F.col("text")))
    return rows.groupBy("_root").agg(pick.alias("_row")).select("_row.*")


def _with_key(docs: DataFrame, name: str) -> DataFrame:
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = _longs([_key(shingles((x or "").encode())) for x in b.column(at).to_pylist()])
            yield pa.RecordBatch.from_arrays([*b.columns, keys], names=[*b.schema.names, name])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(name, T.LongType())]))
