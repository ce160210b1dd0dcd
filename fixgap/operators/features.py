"""Classification features from selected episodes, and their assembly."""

from __future__ import annotations

from pyspark.ml.linalg import VectorUDT
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.expr import episode_key, offsets
from ..params import Params
from . import occ, selection

_VECTORS = T.StructType([T.StructField("v", VectorUDT())])


def select_per_class(events: DataFrame, labels: DataFrame, p: Params, tg_gap: int | None = None) -> DataFrame:
    """Episodes chosen for each class, all classes in one job: cls, ep_id, size, types, gaps, offsets. 1-node rows are dropped.

    Sequences of a class are put on one line of time, tg idle ticks apart. events: seq_id, etype, t; labels: seq_id, label.
    """
    from pyspark.sql import Window

    tg = tg_gap or p.tg
    rows = events.join(labels.select("seq_id", F.col("label").cast("string").alias("cls")), "seq_id")
    spans = rows.groupBy("cls", "seq_id").agg((F.max("t") + 1 + tg).alias("len"))
    shift = spans.withColumn("shift", F.sum("len").over(Window.partitionBy("cls").orderBy("seq_id")) - F.col("len"))  # rows are sequences, not events
    line = rows.join(shift.select("cls", "seq_id", "shift"), ["cls", "seq_id"]).select("cls", "etype", (F.col("t") + F.col("shift")).alias("t"))
    got = selection.select_groups(line, p, by="cls").where("size > 1")
    return got.select("cls", episode_key(F.col("types"), F.col("gaps")).alias("ep_id"), "size", "types", "gaps", offsets(F.col("gaps")).alias("offsets"))


def fixed_gap(events: DataFrame, episodes: DataFrame) -> DataFrame:
    """seq_id, feature, n: occurrences of each episode with its gaps."""
    distinct = episodes.select("ep_id", "size", "types", "offsets").dropDuplicates(["ep_id"])
    return occ.fixed(events, distinct).groupBy("seq_id", F.col("ep_id").alias("feature")).agg(F.count(F.lit(1)).alias("n"))


def order_only(events: DataFrame, episodes: DataFrame) -> DataFrame:
    """seq_id, feature, n: event-disjoint occurrences of each episode's types in order, whatever the gaps."""
    distinct = episodes.select(F.array_join(F.transform("types", lambda x: x.cast("string")), ">").alias("ep_id"), "size", "types").dropDuplicates(["ep_id"])
    return occ.serial_distinct(events, distinct).select("seq_id", F.col("ep_id").alias("feature"), "n").where("n > 0")


def singletons(events: DataFrame) -> DataFrame:
    return events.groupBy("seq_id", F.concat(F.lit("e"), F.col("etype").cast("string")).alias("feature")).agg(F.count(F.lit(1)).alias("n"))


def assemble(features: DataFrame, labels: DataFrame) -> DataFrame:
    """seq_id, label, features: long counts as sparse vectors. Sequences without any feature get an empty vector."""
    from ..sources.sequence import numbered

    vocabulary = numbered(features.select("feature").distinct(), "feature", "i", F.substring("feature", 1, 2)).persist()
    width = vocabulary.count()
    rows = features.join(vocabulary, "feature").groupBy("seq_id").agg(F.sort_array(F.collect_list(F.struct((F.col("i") - 1).alias("i"), F.col("n").cast("double").alias("n")))).alias("x"))
    both = labels.join(rows, "seq_id", "left")
    x = F.coalesce("x", F.array().cast("array<struct<i:int,n:double>>"))
    parts = F.struct(F.lit(0).cast("tinyint").alias("type"), F.lit(max(width, 1)).alias("size"), F.transform(x, lambda s: s["i"]).alias("indices"), F.transform(x, lambda s: s["n"]).alias("values"))
    # a vector's stored form, turned into one by the reader of JSON; no Python sees a row
    return both.select("seq_id", "label", F.from_json(F.to_json(F.struct(parts.alias("v"))), _VECTORS)["v"].alias("features"))
