"""Python functions for users; the library's own paths use column expressions."""

from __future__ import annotations

# Types are objects, not text: text needs a running session, and this module is imported before there is one.
import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udf(T.StringType())
def episode_label(types, gaps):
    return str(types[0]) + "".join(f"+{g}>{e}" for e, g in zip(types[1:], gaps, strict=True))


@F.pandas_udf(T.IntegerType())
def elias_bits_vec(n: pd.Series) -> pd.Series:
    return pd.Series(2 * np.floor(np.log2(n.to_numpy(np.float64))) + 1).astype("int32")


@F.udtf(returnType=T.StructType([T.StructField("etype", T.IntegerType()), T.StructField("t", T.LongType())]))
class RollOut:
    """Events of an episode's occurrences: roll_out_events(types, gaps, starts)."""

    def eval(self, types: list, gaps: list, starts: list):
        for s in starts:
            at = s
            yield types[0], at
            for e, g in zip(types[1:], gaps, strict=True):
                at += g
                yield e, at


@F.udtf(returnType=T.StructType([T.StructField("size", T.IntegerType()), *(T.StructField(c, T.ArrayType(k)) for c, k in (("types", T.IntegerType()), ("gaps", T.IntegerType()), ("starts", T.LongType())))]))
class ParseIntegers:
    """Rows of one integer stream strung together: parse_integer_stream(ints)."""

    def eval(self, ints: list):
        at = 0
        while at < len(ints):
            k = ints[at]
            n = ints[at + 2 * k]
            yield k, ints[at + 1 : at + 1 + k], ints[at + 1 + k : at + 2 * k], ints[at + 2 * k + 1 : at + 2 * k + 1 + n]
            at += 2 * k + 1 + n
