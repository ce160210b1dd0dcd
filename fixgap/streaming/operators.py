"""The sequence methods on streams: windowed counts, lateness, de-duplication, pairs, frozen-episode matching, monitoring."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Episode
from ..operators import encoding, occ
from ..params import Params

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, schema: str = EVENT_SCHEMA, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(path)


def with_lateness(stream: DataFrame, delay: str, time: str = "ts") -> DataFrame:
    """Event time as a timestamp with a watermark."""
    return stream.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, delay)


def counts(stream: DataFrame, kind: str, size: str, slide: str | None = None, time: str = "ts", key: str = "event_type") -> DataFrame:
    """Counts by key in tumbling, sliding or session windows of a watermarked stream."""
    w = F.session_window(time, size) if kind == "session" else F.window(time, size, slide) if kind == "sliding" else F.window(time, size)
    return stream.groupBy(w.alias("w"), key).agg(F.count(F.lit(1)).alias("n")).select("w.start", "w.end", key, "n")


def dedup(stream: DataFrame, key: str = "event_type", time: str = "ts") -> DataFrame:
    """One event for each key and time within the watermark."""
    return stream.dropDuplicatesWithinWatermark([key, time])


def encode_symbols(stream: DataFrame, alphabet: DataFrame, key: str = "event_type") -> DataFrame:
    """Types coded by a static alphabet; unknown symbols go."""
    return stream.join(F.broadcast(alphabet.select("etype", F.col("symbol").alias(key))), key)  # alphabet: a row for each type


def pair_join(stream: DataFrame, tg_seconds: int, first: str, second: str, key: str = "user_id", time: str = "ts", how: str = "inner") -> DataFrame:
    """Two-node episodes: events of `second` at most tg after events of `first` of the same key; a stream-stream join."""
    a = stream.where(F.col("event_type") == first).select(F.col(key).alias("ka"), F.col(time).alias("ta"))
    b = stream.where(F.col("event_type") == second).select(F.col(key).alias("kb"), F.col(time).alias("tb"))
    return a.join(b, F.expr(f"ka = kb AND tb > ta AND tb <= ta + INTERVAL {tg_seconds} SECONDS"), how)


def match(stream: DataFrame, episodes: list[Episode], slack: int = 0, time: str | None = None, tick_ms: int = 1000) -> DataFrame:
    """key, ep_id, start_t of each occurrence of frozen episodes, once, when its last event arrives. stream: key, etype, t.

    State holds the events of the last span (plus `slack` ticks for late ones), so its size follows the span, not the stream.
    With `time`, a watermarked timestamp column, a key's state leaves once the watermark is a span (and slack) of `tick_ms`
    ticks past its newest event, so idle keys hold nothing, and rows behind the watermark are dropped (see `late_rows`).
    """
    plans = [(e.key, list(zip(e.types, e.offsets, strict=True))) for e in episodes]
    span = max((e.offsets[-1] for e in episodes), default=0)
    hold = (span + slack + 1) * tick_ms

    def run(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        etypes, times, until = state.get if state.exists else ([], [], 0)
        old, new = set(zip(etypes, times, strict=True)), set()
        for b in batches:
            new |= {(int(e), int(t)) for e, t in zip(b["etype"], b["t"], strict=True)}
            until = max(until, int(b["ms"].max()) + hold) if time else 0
        new -= old
        seen, out = old | new, set()
        for e, t in new:
            for name, nodes in plans:
                for etype, off in nodes:
                    if etype == e and all((x, t - off + o) in seen for x, o in nodes):
                        out.add((name, t - off))
        last = max((t for _, t in seen), default=0)
        kept = sorted(x for x in seen if x[1] >= last - span - slack)
        state.update(([x[0] for x in kept], [x[1] for x in kept], until))
        if time:
            state.setTimeoutTimestamp(max(until, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame([(key[0], n, s) for n, s in sorted(out)], columns=["key", "ep_id", "start_t"])

    rows = stream.select("key", "etype", "t", time, F.unix_millis(time).alias("ms")) if time else stream
    schema, state = "key string, ep_id string, start_t long", "etypes array<int>, times array<long>, until long"
    return rows.groupBy("key").applyInPandasWithState(run, schema, state, "append", "EventTimeTimeout" if time else "NoTimeout")


def late_rows(query) -> int:
    """Rows that a query's stateful operators dropped behind the watermark, over the progress it still reports (an aggregate's
    rows are counted after its partial aggregation)."""
    return sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])


def monitor(model_episodes: DataFrame, on_result: Callable[[int, dict], None], floor: float = 1.0) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: length of each batch under a frozen model, and an alarm when its ratio falls below `floor`."""

    def run(batch: DataFrame, epoch: int) -> None:
        events = batch.select(F.lit(0).cast("long").alias("seq_id"), "etype", "t").dropDuplicates()
        found = occ.fixed(events, model_episodes)
        gone = occ.covered(found, model_episodes).select("etype", "t").distinct()
        rest = events.select("etype", "t").join(gone, ["etype", "t"], "left_anti")
        multi = found.groupBy("ep_id").agg(F.count(F.lit(1)).alias("f")).join(model_episodes.select("ep_id", "size"), "ep_id").agg(F.coalesce(F.sum(2 * F.col("size") + F.col("f") + 1), F.lit(0)).alias("u")).first()["u"]
        left = encoding.trivial_units(rest).first()["trivial_units"]
        base = encoding.trivial_units(events).first()
        total = multi + left
        ratio = base["trivial_units"] / total if total else 1.0
        on_result(epoch, {"events": base["n_events"], "total_units": total, "ratio": ratio, "alarm": ratio < floor})

    return run


def refresh(params: Params, on_model: Callable[[int, list], None], keep_ticks: int, store: str | None = None) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function that chooses episodes anew from the last `keep_ticks`; models are numbered by epoch.

    The window is that of the batch, or with `store`, a shared folder, that of all batches: each is a table of its own there
    (a repeated epoch replaces it), and tables that the window has passed are deleted.
    """
    from ..operators import selection

    def run(batch: DataFrame, epoch: int) -> None:
        events = batch.select("etype", "t")
        if store:
            events.write.mode("overwrite").parquet(f"{store}/epoch={epoch}")
            events = batch.sparkSession.read.schema("etype int, t long, epoch long").parquet(store)
        last = events.agg(F.max("t")).first()[0]
        if last is not None:
            rows = selection.select(events.where(F.col("t") > last - keep_ticks).select("etype", "t"), params)
            on_model(epoch, rows.where("rank IS NOT NULL").orderBy("rank").collect())
            if store:  # a row for each stored batch
                for r in events.groupBy("epoch").agg(F.max("t").alias("t")).where(F.col("t") <= last - keep_ticks).collect():
                    _drop(batch.sparkSession, f"{store}/epoch={r['epoch']}")

    return run


def _drop(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
