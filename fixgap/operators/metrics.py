"""Redundancy of chosen episodes, and their relevance where the truth is known."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.expr import episode_key, offsets
from ..sources.sequence import routes
from . import table


def redundancy(encoded: DataFrame) -> DataFrame:
    """mean_shared: mean number of events that two chosen episodes share; pairs without any count as 0."""
    multi = encoded.where("size > 1").select(episode_key(F.col("types"), F.col("gaps")).alias("ep_id"), "size", "types", "gaps", offsets(F.col("gaps")).alias("offsets"), "starts")
    occs = multi.select("ep_id", F.explode("starts").alias("start_t"))
    shared = table.overlap_matrix(occs, multi).agg(F.coalesce(F.sum("shared"), F.lit(0)).alias("s"))
    n = multi.agg(F.count(F.lit(1)).alias("n"))
    return shared.join(n).select(F.when(F.col("n") > 1, F.col("s") / (F.col("n") * (F.col("n") - 1) / 2)).otherwise(0.0).alias("mean_shared"))


def route_match(encoded: DataFrame, alphabet: DataFrame, topology: str) -> DataFrame:
    """subpath_precision: share of chosen episodes that are contiguous pieces of a route, with its transfer times; route_recall: share of routes chosen whole."""
    spark: SparkSession = encoded.sparkSession
    symbols = encoded.where("size > 1").select("row_no", F.posexplode("types").alias("i", "etype"), "gaps").join(alphabet, "etype")
    eps = symbols.groupBy("row_no", "gaps").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "symbol"))), lambda x: x["symbol"]).alias("units"))
    lines: dict[int, list[str]] = {}
    for r, _, unit, _ in routes(topology):
        lines.setdefault(r, []).append(unit)
    known = spark.createDataFrame([(r, "|" + "|".join(u) + "|") for r, u in lines.items()], "route int, line string")
    text = F.concat(F.lit("|"), F.array_join("units", "|"), F.lit("|"))
    hit = eps.join(F.broadcast(known), F.instr(F.col("line"), text) > 0, "left").groupBy("row_no").agg(F.max(F.col("route").isNotNull().cast("int")).alias("hit"), F.max(F.when(F.col("line") == text, F.col("route"))).alias("whole"))  # known: a row for each route
    return hit.agg(F.avg("hit").cast("double").alias("subpath_precision"), (F.count_distinct("whole") / F.lit(len(lines))).alias("route_recall"))
