"""Connected components of an edge list by alternating star contraction, all in DataFrames.

Null ends and edges of a node to itself are left out; repeated edges count once; without edges there are no rows. A hub's edges
are dealt out by their other end (SALTS ways): its smallest neighbour is found in two steps and sent to each part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import materialise

SALTS = 64


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _large_star(edges: DataFrame) -> DataFrame:
    """Every node links its larger neighbours to the smallest node around it."""
    sym = _both(edges).withColumn("salt", F.pmod(F.xxhash64("b"), F.lit(SALTS)))
    parts = sym.groupBy("a", "salt").agg(F.min("b").alias("m"))
    low = parts.groupBy("a").agg(F.least(F.min("m"), F.col("a")).alias("m"), F.collect_list("salt").alias("salts"))  # SALTS at most
    return sym.where("b > a").join(low.select("a", "m", F.explode("salts").alias("salt")), ["a", "salt"]).select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Every node links itself and its smaller neighbours to the smallest of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b")
    low = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(low, "a").where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(low.select("a", F.col("m").alias("b")))


def connected(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges a, b (longs) -> node, root: the smallest node of each component; nodes without an edge are left out.

    Rounds follow the logarithm of the longest chain. Each round is written to the shared folder, so no lineage builds up
    and a lost executor costs one round at most.
    """
    edges = materialise(edges.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    seen = None
    for _ in range(max_rounds):
        edges = materialise(_small_star(_large_star(edges)).distinct(), "edges")
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components have not settled in {max_rounds} rounds")
    star = edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return star.unionByName(star.select(F.col("root").alias("node"), "root").distinct())
