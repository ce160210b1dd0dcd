"""Entry points: fit a selector, get a model with its encoding, lengths and features, and compare methods."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.expr import episode_key, offsets
from .operators import baselines, encoding, features, occ, selection
from .params import Params
from .sources import sequence
from .sources.shared import Scratch, ship


class CompressionModel:
    """events: etype, t on one line; encoded: ENCODED with round, rank and score."""

    def __init__(self, events: DataFrame, encoded: DataFrame, params: Params):
        self.events, self.encoded, self.params = events, encoded, params

    @property
    def episodes(self) -> DataFrame:
        multi = self.encoded.where("size > 1")
        return multi.select(episode_key(F.col("types"), F.col("gaps")).alias("ep_id"), "size", "types", "gaps", offsets(F.col("gaps")).alias("offsets"), "round", "rank", "score", "row_no")

    @property
    def occurrences(self) -> DataFrame:
        return self.encoded.where("size > 1").select(episode_key(F.col("types"), F.col("gaps")).alias("ep_id"), F.explode("starts").alias("start_t"))

    def lengths(self) -> DataFrame:
        """n_events, n_types, trivial_units, model_units, data_units, total_units, n_patterns, ratio."""
        both = encoding.trivial_units(self.events).join(encoding.units(self.encoded))
        return both.withColumn("ratio", F.col("trivial_units") / F.col("total_units"))

    def ratio(self, unit: str = "units", starts: str = "absolute") -> float:
        if unit == "units":
            return self.lengths().first()["ratio"]
        m = self.events.select("etype").distinct().count()
        a = encoding.bits(encoding.trivial(self.events), m, starts).first()[0]
        return a / encoding.bits(self.encoded, m, starts).first()[0]

    def encode(self, events: DataFrame) -> DataFrame:
        """Other events by the frozen episodes in order of choice: an episode takes the occurrences whose events are all left; 1-node rows cover the rest."""
        rest, rows = events.select("etype", "t"), None
        for r in self.episodes.orderBy("rank").collect():  # the model's episodes
            frame = events.sparkSession.createDataFrame([(r["row_no"], r["ep_id"], r["size"], r["types"], r["gaps"], r["offsets"])], "row_no int, ep_id string, size int, types array<int>, gaps array<int>, offsets array<int>")
            got = occ.fixed(rest.withColumn("seq_id", F.lit(0).cast("long")), frame)
            here = encoding.encode(frame, got)
            rows = here if rows is None else rows.unionByName(here)
            rest = rest.join(occ.covered(got, frame).select("etype", "t"), ["etype", "t"], "left_anti")
        ones = encoding.trivial(rest).withColumn("row_no", F.col("row_no") + 1_000_000)
        return ones if rows is None else rows.unionByName(ones)

    def decode(self) -> DataFrame:
        return encoding.decode(self.encoded)

    def features(self, events: DataFrame, kind: str = "fixed_gap") -> DataFrame:
        """seq_id, feature, n of other events: `fixed_gap`, `order_only` or `singletons`."""
        if kind == "singletons":
            return features.singletons(events)
        return {"fixed_gap": features.fixed_gap, "order_only": features.order_only}[kind](events, self.episodes)


class EpisodeCompressor:
    def __init__(self, params: Params = Params(), selector: str = "path_greedy"):
        self.params, self.selector = params, selector

    def fit(self, events: DataFrame) -> CompressionModel:
        ship(events.sparkSession)
        scratch = Scratch(events.sparkSession)
        events = scratch.write(events.select("etype", "t"))
        return CompressionModel(events, scratch.write(selection.select(events, self.params, self.selector)), self.params)


def select(events: DataFrame, selector: str = "path_greedy", params: Params = Params()) -> CompressionModel:
    return EpisodeCompressor(params, selector).fit(events)


def compare(events: DataFrame, methods: list[str], params: Params = Params(), chop: int = 50) -> DataFrame:
    """method, ratio_units, ratio_bits, n_patterns, seconds. Order-only baselines get chopped events without times."""
    spark = events.sparkSession
    out = []
    m = events.select("etype").distinct().count()
    for method in methods:
        began = time.time()
        if method in ("gap_coding", "dependency_test"):
            rows = sequence.order_only(sequence.chop(events.select("etype", "t").withColumn("seq_id", F.lit(0).cast("long")), chop))
            patterns, bits, base = getattr(baselines, method)(rows, m)
            out.append((method, None, base / bits, len(patterns), time.time() - began))
        else:
            model = select(events, method, params)
            r = model.lengths().first()
            seconds = time.time() - began
            out.append((method, r["ratio"], model.ratio("bits"), r["n_patterns"], seconds))
    return spark.createDataFrame(out, "method string, ratio_units double, ratio_bits double, n_patterns long, seconds double")
