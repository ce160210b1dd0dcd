"""Encoded tables, integer streams, decoding, and lengths in units and bits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.expr import elias_bits, offsets, type_bits


def encode(episodes: DataFrame, occ: DataFrame) -> DataFrame:
    """row_no, size, types, gaps, n_occ, starts. episodes: row_no, ep_id, size, types, gaps; occ: ep_id, start_t."""
    starts = occ.groupBy("ep_id").agg(F.sort_array(F.collect_list("start_t")).alias("starts"))
    return episodes.join(starts, "ep_id").select("row_no", "size", "types", "gaps", F.size("starts").cast("long").alias("n_occ"), "starts")


def trivial(events: DataFrame) -> DataFrame:
    """Every event through 1-node episodes."""
    rows = events.groupBy("etype").agg(F.sort_array(F.collect_list("t")).alias("starts"))
    return rows.select(F.col("etype").alias("row_no"), F.lit(1).alias("size"), F.array("etype").alias("types"), F.array().cast("array<int>").alias("gaps"), F.size("starts").cast("long").alias("n_occ"), "starts")


def to_stream(encoded: DataFrame) -> DataFrame:
    """row_no, ints: size, types, gaps, count, starts of each row strung together."""
    longs = lambda c: F.col(c).cast("array<long>")
    return encoded.select("row_no", F.concat(F.array(F.col("size").cast("long")), longs("types"), longs("gaps"), F.array("n_occ"), longs("starts")).alias("ints"))


def from_stream(stream: DataFrame) -> DataFrame:
    """Rows from integers; each row tells its own length."""
    size = F.element_at("ints", 1).cast("int")
    n = F.element_at("ints", 2 * size + 1)
    return stream.select(
        "row_no", size.alias("size"), F.slice("ints", F.lit(2), size).cast("array<int>").alias("types"), F.slice("ints", size + 2, size - 1).cast("array<int>").alias("gaps"),
        n.alias("n_occ"), F.slice("ints", 2 * size + 2, n.cast("int")).alias("starts"),
    )


def decode(encoded: DataFrame) -> DataFrame:
    """etype, t: occurrences rolled out; an event that several episodes cover comes once."""
    nodes = encoded.select("starts", F.arrays_zip(F.col("types").alias("e"), offsets(F.col("gaps")).alias("off")).alias("nodes"))
    flat = nodes.select(F.explode("starts").alias("s"), "nodes").select("s", F.explode("nodes").alias("x"))
    return flat.select(F.col("x.e").alias("etype"), (F.col("s") + F.col("x.off")).cast("long").alias("t")).distinct()


def lost_or_added(events: DataFrame, encoded: DataFrame) -> DataFrame:
    """Events that differ between the data and its decoded encoding; none if it is lossless."""
    a, b = events.select("etype", "t"), decode(encoded)
    return a.exceptAll(b).withColumn("side", F.lit("lost")).unionByName(b.exceptAll(a).withColumn("side", F.lit("added")))


def units(encoded: DataFrame) -> DataFrame:
    """model_units, data_units, total_units, n_patterns (rows of two or more nodes)."""
    return encoded.agg(
        F.sum(2 * F.col("size")).cast("long").alias("model_units"), F.sum(F.col("n_occ") + 1).cast("long").alias("data_units"),
        F.sum(2 * F.col("size") + F.col("n_occ") + 1).cast("long").alias("total_units"), F.sum((F.col("size") > 1).cast("long")).alias("n_patterns"),
    )


def trivial_units(events: DataFrame) -> DataFrame:
    """events, types and trivial_units: three integers a type and one an event."""
    return events.agg(F.count(F.lit(1)).alias("n_events"), F.count_distinct("etype").alias("n_types")).withColumn("trivial_units", 3 * F.col("n_types") + F.col("n_events"))


def raw_units(events: DataFrame) -> DataFrame:
    return events.agg((2 * F.count(F.lit(1))).alias("raw_units"))


def row_bits(m: Column, starts: str = "absolute") -> Column:
    """Bits of one row: gamma codes for size, gaps, count and starts; a fixed-width code for types."""
    total = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda a, x: a + elias_bits(x))
    s = F.col("starts")
    if starts == "delta":
        s = F.transform(s, lambda x, i: F.when(i == 0, x).otherwise(x - F.element_at("starts", F.greatest(i, F.lit(1)))))
    return elias_bits(F.col("size").cast("long")) + F.col("size") * type_bits(m) + total(F.col("gaps").cast("array<long>")) + elias_bits(F.col("n_occ")) + total(s)


def bits(encoded: DataFrame, m: int, starts: str = "absolute") -> DataFrame:
    """total_bits: all rows and the alphabet's size."""
    return encoded.agg((F.sum(row_bits(F.lit(m).cast("long"), starts)) + elias_bits(F.lit(m).cast("long"))).cast("long").alias("total_bits"))


def per_event_time_units(encoded: DataFrame) -> DataFrame:
    """Units if every event of an occurrence had a time of its own written; may exceed the raw data."""
    return encoded.agg(F.sum(2 * F.col("size") + 1 + F.col("n_occ") * F.col("size")).cast("long").alias("per_event_units"))


# ---- the long form: rows without starts, and one start a row; no array grows with the data


def encode_long(episodes: DataFrame, occ: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(row_no, size, types, gaps, n_occ) and (row_no, start_t). Counts are partial sums; starts are never brought together."""
    starts = occ.join(episodes.select("row_no", "ep_id"), "ep_id").select("row_no", "start_t")
    n = starts.groupBy("row_no").agg(F.count(F.lit(1)).alias("n_occ"))
    return episodes.join(n, "row_no").select("row_no", "size", "types", "gaps", "n_occ"), starts


def trivial_long(events: DataFrame) -> tuple[DataFrame, DataFrame]:
    rows = events.groupBy("etype").agg(F.count(F.lit(1)).alias("n_occ"))
    rows = rows.select(F.col("etype").alias("row_no"), F.lit(1).alias("size"), F.array("etype").alias("types"), F.array().cast("array<int>").alias("gaps"), "n_occ")
    return rows, events.select(F.col("etype").alias("row_no"), F.col("t").alias("start_t"))


def decode_long(rows: DataFrame, starts: DataFrame) -> DataFrame:
    """etype, t. rows: one for each episode and type of a model."""
    nodes = rows.select("row_no", F.explode(F.arrays_zip(F.col("types").alias("e"), offsets(F.col("gaps")).alias("off"))).alias("x"))
    return starts.join(nodes, "row_no").select(F.col("x.e").alias("etype"), (F.col("start_t") + F.col("x.off")).cast("long").alias("t")).distinct()


def blocks(rows: DataFrame, starts: DataFrame, block_ticks: int = 1 << 20) -> DataFrame:
    """ENCODED with block_no: a row's starts in arrays of one block of time each, as a stream is written."""
    parts = starts.groupBy("row_no", F.floor(F.col("start_t") / block_ticks).alias("block_no")).agg(F.sort_array(F.collect_list("start_t")).alias("starts"))
    return rows.drop("n_occ").join(parts, "row_no").select("row_no", "block_no", "size", "types", "gaps", F.size("starts").cast("long").alias("n_occ"), "starts")


def units_for(events: DataFrame, episodes: DataFrame, occ: DataFrame) -> DataFrame:
    """Lengths of the data under a given multi-node set: its occurrences, and 1-node rows for what they leave.

    episodes: ep_id, size, types, gaps, offsets; occ: ep_id, start_t.
    """
    nodes = episodes.select("ep_id", F.explode(F.arrays_zip("types", "offsets")).alias("x"))
    gone = occ.join(nodes, "ep_id").select(F.col("x.types").alias("etype"), (F.col("start_t") + F.col("x.offsets")).alias("t"))
    rest = events.select("etype", "t").join(gone, ["etype", "t"], "left_anti")
    multi = occ.groupBy("ep_id").agg(F.count(F.lit(1)).alias("n_occ")).join(episodes.select("ep_id", "size"), "ep_id").select("size", "n_occ")
    ones = rest.groupBy("etype").agg(F.count(F.lit(1)).alias("n_occ")).select(F.lit(1).alias("size"), "n_occ")
    return units(multi.unionByName(ones))
