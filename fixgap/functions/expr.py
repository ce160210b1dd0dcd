"""Column expressions of scores and code lengths, and the same as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def episode_score(size: Column, freq: Column) -> Column:
    return freq * size - (2 * size + freq + 1)


def is_useful(size: Column, freq: Column) -> Column:
    return episode_score(size, freq) > 0


def min_useful_freq(size: Column) -> Column:
    """The smallest frequency with a positive score: above (2N + 1) / (N - 1)."""
    return (F.floor((2 * size + 1) / (size - 1)) + 1).cast("long")


def floor_log2(n: Column) -> Column:
    """Exact for positive integers, powers of two included."""
    return F.length(F.bin(n)) - 1


def elias_bits(n: Column) -> Column:
    """Bits of a positive integer in the gamma code."""
    return 2 * floor_log2(n) + 1


def type_bits(m: Column) -> Column:
    return floor_log2(m) + 1


def offsets(gaps: Column) -> Column:
    """Running sums of gaps, from 0."""
    return F.transform(F.sequence(F.lit(0), F.size(gaps)), lambda i: F.aggregate(F.slice(gaps, F.lit(1), i), F.lit(0), lambda a, g: a + g))


def episode_key(types: Column, gaps: Column) -> Column:
    """Types with their gaps between: 1+2>4+1>3."""
    steps = F.transform(F.arrays_zip(F.slice(types, F.lit(2), F.greatest(F.size(types) - 1, F.lit(0))).alias("e"), gaps.alias("g")), lambda x: F.concat(F.lit("+"), x["g"].cast("string"), F.lit(">"), x["e"].cast("string")))
    return F.concat(types[0].cast("string"), F.array_join(steps, ""))


# Bodies of the functions for SQL users.
SQL_FUNCTIONS = {
    "episode_score(n BIGINT, f BIGINT)": ("BIGINT", "f * n - (2 * n + f + 1)"),
    "min_useful_freq(n BIGINT)": ("BIGINT", "CAST(floor((2 * n + 1) / (n - 1)) AS BIGINT) + 1"),
    "elias_bits(n BIGINT)": ("INT", "2 * (length(bin(n)) - 1) + 1"),
    "type_bits(m BIGINT)": ("INT", "length(bin(m))"),
}


def register(spark: SparkSession) -> None:
    for head, (kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
