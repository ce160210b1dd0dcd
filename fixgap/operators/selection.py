"""The two selectors: encoded tables of a sequence, or of many groups of sequences at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import ENCODED
from ..params import Params
from ..sources.shared import Scratch
from . import encoding, kernel, table

ROWS = "cls string, row_no int, round int, rank int, score long, size int, types array<int>, gaps array<int>, n_occ long, starts array<long>"


def _table(cls: str | None, picks: list[kernel.Pick], left: kernel.Events) -> pa.Table:
    rows = [(cls, p.rank, p.round, p.rank, p.score, p.episode.size, list(p.episode.types), list(p.episode.gaps), len(p.episode.starts), np.sort(p.episode.starts)) for p in picks]
    for e in np.unique(left.e).tolist():
        starts = left.t[left.e == e]
        rows.append((cls, len(rows) + 1, None, None, None, 1, [e], [], len(starts), starts))
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 10
    kinds = [pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.int64(), pa.list_(pa.int64())]
    return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["cls", "row_no", "round", "rank", "score", "size", "types", "gaps", "n_occ", "starts"])


def select_groups(events: DataFrame, p: Params, selector: str = "path_greedy", by: str | None = None) -> DataFrame:
    """Rows of ENCODED with cls, round, rank and score, for every group of `by` (cast to string); no `by`: one group.

    A group is one line of time. Groups of at most p.kernel_events events are solved at once, each in one task; larger ones go
    through the table engine one after another. Results are equal.
    """

    def run(group: pa.Table) -> pa.Table:
        if group.num_rows > p.kernel_events:
            raise ValueError(f"a group of {group.num_rows} events is above kernel_events; use engine='table'")
        picks, left, _ = kernel.select(group.column("t").to_numpy(), group.column("etype").to_numpy(), p, selector)
        return _table(group.column("cls")[0].as_py(), picks, left)

    cls = F.col(by).cast("string") if by else F.lit("all")
    rows = events.select(cls.alias("cls"), "etype", "t")
    large = [r["cls"] for r in rows.groupBy("cls").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > p.kernel_events).collect()] if by else []  # a row for each class
    few = rows
    for c in large:
        few = few.where(~F.col("cls").eqNullSafe(F.lit(c)))
    out = few.groupBy("cls").applyInArrow(run, ROWS)
    for c in large:
        out = out.unionByName(select(rows.where(F.col("cls").eqNullSafe(F.lit(c))).select("etype", "t"), p.but(engine="table"), selector).withColumn("cls", F.lit(c)))
    return out


def _frame(spark: SparkSession, picks: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(r, rnd, r, s, e.key, e.size, list(e.types), list(e.gaps)) for rnd, r, s, e in picks], "row_no int, round int, rank int, score long, ep_id string, size int, types array<int>, gaps array<int>")


def _after(p: Params, n_picks: int) -> Params:
    return p if p.k is None else p.but(k=p.k - n_picks)


def _rest(events: DataFrame, p: Params, selector: str, done: tuple[int, int], n_picks: int) -> DataFrame:
    """The rows of the rounds after those done, by the kernel in one task."""

    def run(group: pa.Table) -> pa.Table:
        picks, left, _ = kernel.select(group.column("t").to_numpy(), group.column("etype").to_numpy(), _after(p, n_picks), selector, done)
        return _table(None, picks, left)

    rows = events.select("etype", "t", F.lit("all").alias("cls")).groupBy("cls").applyInArrow(run, ROWS).drop("cls")
    return rows.withColumn("row_no", F.col("row_no") + n_picks).withColumn("rank", F.col("rank") + n_picks)


def alone(p: Params, selector: str) -> int:
    """Events of a line that the kernel takes under engine="auto". Frequent episodes of any size occur hundreds of times as often
    as there are events, so of those it takes a 32nd."""
    return p.kernel_events if selector == "path_greedy" or (p.max_size or 4) <= 3 else p.kernel_events // 32


def select(events: DataFrame, p: Params = Params(), selector: str = "path_greedy") -> DataFrame:
    """ENCODED of one line of events (etype, t) with round, rank and score of chosen episodes; 1-node rows cover the rest."""
    engine = p.engine
    if engine != "kernel":
        events = Scratch(events.sparkSession).write(events.select("etype", "t"))  # read more than once
    if engine == "auto":
        engine = "kernel" if events.count() <= alone(p, selector) else "table"
    if engine == "kernel":
        return select_groups(events, p, selector).drop("cls")
    spark = events.sparkSession
    picks, occs, left, _, more = table.rounds(events, p, selector, until=alone(p, selector) if p.engine == "auto" else 0)
    if more:  # the later rounds' rows, 1-node rows among them
        ones = _rest(left, p, selector, more, len(picks))
        frame = _frame(spark, picks)
        return encoding.encode(frame, occs).join(frame.select("row_no", "round", "rank", "score"), "row_no").select(*ones.columns).unionByName(ones)
    ones = encoding.trivial(left).drop("row_no").withColumn("_e", F.col("types")[0])
    ones = ones.withColumn("row_no", F.row_number().over(Window.orderBy("_e")) + len(picks)).drop("_e")  # a row for each type
    empty = [F.lit(None).cast(k).alias(c) for c, k in (("round", "int"), ("rank", "int"), ("score", "long"))]
    ones = ones.select("row_no", *empty, "size", "types", "gaps", "n_occ", "starts")
    if not picks:
        return ones
    frame = _frame(spark, picks)
    multi = encoding.encode(frame, occs).join(frame.select("row_no", "round", "rank", "score"), "row_no")
    return multi.select(*ones.columns).unionByName(ones)


def trace(events: DataFrame, p: Params = Params(), selector: str = "path_greedy") -> DataFrame:
    """round, n_found, n_useful, n_picked, events_left; by the engine that `select` would take."""
    schema = "round long, n_found long, n_useful long, n_picked long, events_left long"
    before, done, n_picks = None, None, 0
    if p.engine != "kernel":
        events = Scratch(events.sparkSession).write(events.select("etype", "t"))
    if p.engine == "table" or (p.engine == "auto" and events.count() > alone(p, selector)):
        picks, _, events, rows, done = table.rounds(events, p, selector, until=alone(p, selector) if p.engine == "auto" else 0)
        before, n_picks = events.sparkSession.createDataFrame(rows, schema), len(picks)
        if not done:
            return before

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, e = [], []
        for b in batches:
            t.append(b.column("t").to_numpy())
            e.append(b.column("etype").to_numpy())
        rows = kernel.select(np.concatenate(t), np.concatenate(e), _after(p, n_picks), selector, done)[2] if t else []
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["round", "n_found", "n_useful", "n_picked", "events_left"])

    here = events.select("t", "etype").coalesce(1).mapInArrow(run, schema)
    return here if before is None else before.unionByName(here)


def plain(encoded: DataFrame) -> DataFrame:
    return encoded.select(*[c.split()[0] for c in ENCODED.split(", ")])
