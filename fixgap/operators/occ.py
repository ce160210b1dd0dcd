"""Occurrences of given episodes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import EPISODES, Episode


def episodes_frame(spark: SparkSession, episodes: list[Episode]) -> DataFrame:
    return spark.createDataFrame([e.row() for e in episodes], EPISODES)


def fixed(events: DataFrame, episodes: DataFrame) -> DataFrame:
    """ep_id, seq_id, start_t of every occurrence: each event votes for the starts it would belong to, and full votes count.

    One equi-join on the type and one aggregation; no join for each node. episodes is a model, so of bounded size.
    """
    nodes = episodes.select("ep_id", "size", F.explode(F.arrays_zip("types", "offsets")).alias("x")).select("ep_id", "size", F.col("x.types").alias("etype"), F.col("x.offsets").alias("off"))
    votes = events.join(nodes, "etype").select("ep_id", "size", "seq_id", (F.col("t") - F.col("off")).alias("start_t"))
    return votes.groupBy("ep_id", "seq_id", "start_t").agg(F.count(F.lit(1)).alias("n"), F.first("size").alias("size")).where("n = size").select("ep_id", "seq_id", "start_t")


def covered(occ: DataFrame, episodes: DataFrame) -> DataFrame:
    """ep_id, seq_id, etype, t of the events in occurrences."""
    nodes = episodes.select("ep_id", F.explode(F.arrays_zip("types", "offsets")).alias("x"))
    return occ.join(nodes, "ep_id").select("ep_id", "seq_id", F.col("x.types").alias("etype"), (F.col("start_t") + F.col("x.offsets")).alias("t"))


def frequency(occ: DataFrame) -> DataFrame:
    """Occurrences of an injective episode share no event, so their number is the distinct-occurrence frequency."""
    return occ.groupBy("ep_id").agg(F.count(F.lit(1)).alias("freq"))


def serial_all(events: DataFrame, types: list[int]) -> DataFrame:
    """All occurrences of a serial episode as times t1..tn (exponential in the worst case; for small data)."""
    out = None
    for i, e in enumerate(types, 1):
        here = events.where(F.col("etype") == e).select("seq_id", F.col("t").alias(f"t{i}"))
        out = here if out is None else out.join(here, "seq_id").where(F.col(f"t{i}") > F.col(f"t{i - 1}"))
    return out


def serial_distinct(events: DataFrame, episodes: DataFrame) -> DataFrame:
    """ep_id, seq_id, n: the most event-disjoint occurrences of each order-only episode (types array) in each sequence.

    First-come matching, stage by stage: completions up to t are the stage's events so far plus the lowest that prefixes
    completed strictly before an event have fallen behind its number. Running sums and minima say all of that.
    """
    longest = episodes.agg(F.max("size")).first()[0] or 0
    member = episodes.select("ep_id", "size", F.posexplode("types").alias("i", "etype"))
    rows = events.join(member, "etype").select("ep_id", "size", "seq_id", "t", "i")
    # done: matched so far at stage i - 1, by time
    stage = rows.where("i = 0").select("ep_id", "size", "seq_id", "t", F.lit(1).cast("long").alias("hit"))
    out = None
    for i in range(1, longest + 1):
        ended = stage.where(F.col("size") == i).groupBy("ep_id", "seq_id").agg(F.sum("hit").alias("n"))
        out = ended if out is None else out.unionByName(ended)
        if i == longest:
            break
        prev = stage.where(F.col("size") > i).select("ep_id", "size", "seq_id", "t", F.col("hit"), F.lit(0).cast("long").alias("here"))
        this = rows.where((F.col("i") == i) & (F.col("size") > i)).select("ep_id", "size", "seq_id", "t", F.lit(0).cast("long").alias("hit"), F.lit(1).cast("long").alias("here"))
        both = prev.unionByName(this)
        line = Window.partitionBy("ep_id", "seq_id").orderBy("t")
        before = line.rangeBetween(Window.unboundedPreceding, -1)
        upto = line.rangeBetween(Window.unboundedPreceding, 0)
        a = F.coalesce(F.sum("hit").over(before), F.lit(0))
        both = both.withColumn("a", a).withColumn("n", F.sum("here").over(upto))
        low = F.least(F.lit(0), F.coalesce(F.min(F.when(F.col("here") == 1, F.col("a") - F.col("n"))).over(upto), F.lit(0)))
        both = both.withColumn("d", F.col("n") + low).where("here = 1")
        stage = both.withColumn("hit", F.col("d") - F.coalesce(F.lag("d").over(line), F.lit(0))).select("ep_id", "size", "seq_id", "t", "hit")
    return out if out is not None else rows.select("ep_id", "seq_id", F.lit(0).cast("long").alias("n")).limit(0)


def serial_non_overlapped(events: DataFrame, episodes: DataFrame) -> DataFrame:
    """ep_id, seq_id, n: occurrences counted left to right, one open at a time. Folds each sequence's sorted events."""
    member = episodes.select("ep_id", "types", F.explode("types").alias("etype"))
    lines = events.join(member, "etype").groupBy("ep_id", "types", "seq_id").agg(F.array_sort(F.collect_list(F.struct("t", "etype"))).alias("line"))
    start = F.struct(F.lit(0).alias("at"), F.lit(0).cast("long").alias("n"), F.lit(-(1 << 60)).cast("long").alias("last"))

    def step(s, x):
        hit = (F.element_at("types", s["at"] + 1) == x["etype"]) & (x["t"] > s["last"])
        full = hit & (s["at"] + 1 == F.size("types"))
        return F.struct(F.when(full, 0).when(hit, s["at"] + 1).otherwise(s["at"]).alias("at"), (s["n"] + full.cast("long")).alias("n"), F.when(hit, x["t"]).otherwise(s["last"]).alias("last"))

    return lines.select("ep_id", "seq_id", F.aggregate("line", start, step, lambda s: s["n"]).alias("n")).where("n > 0")
