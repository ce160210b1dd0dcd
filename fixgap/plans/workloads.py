"""Experiment workloads on the given tables."""

from __future__ import annotations

import time
from functools import cache, partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..api import CompressionModel, select
from ..functions.expr import episode_key, offsets
from ..operators import baselines, classify, encoding, features, metrics, selection
from ..params import Params
from ..sources import sequence as seq
from ..sources.shared import Scratch, ship


def conveyor_events(spark: SparkSession, d: str, topology: str) -> tuple[DataFrame, DataFrame]:
    ship(spark)
    scratch = Scratch(spark)
    ev, names = seq.coded_conveyor(seq.table(spark, d, "orders"), topology)
    ev = scratch.write(ev.select("etype", "t"))
    return ev, ev.groupBy("etype").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(names), "etype").select("etype", "symbol", "n")  # names: a row for each unit


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """row_no, size, episode, n_occ, score of chosen episodes on the three-route conveyor, with units and ratio of the whole."""
    ev, _ = conveyor_events(spark, d, "three")
    enc = Scratch(spark).write(selection.select(ev))
    total = encoding.trivial_units(ev).join(encoding.units(enc)).select(F.col("total_units").alias("units"), (F.col("trivial_units") / F.col("total_units")).alias("ratio"))
    return enc.where("size > 1").select("row_no", "size", episode_key(F.col("types"), F.col("gaps")).alias("episode"), "n_occ", "score").join(F.broadcast(total))


def order_only_events(ev: DataFrame, size: int | None) -> DataFrame:
    """A line without times, for the order-only baselines; in pieces of `size` events."""
    rows = ev.select("etype", "t").withColumn("seq_id", F.lit(0).cast("long"))
    return seq.order_only(seq.chop(rows, size) if size else rows)


BASELINES = ("gap_coding", "dependency_test")


def _baseline(name: str, rows: DataFrame, m: int, patience: int | None):
    return baselines.gap_coding(rows, m, patience=patience) if name == "gap_coding" else baselines.dependency_test(rows, m)


def conveyor_table(spark: SparkSession, d: str, topology: str, chops: tuple[int, ...] = (25, 50, 100), patience: int | None = None, seconds: bool = False) -> DataFrame:
    """data, method, chop, ratio_units, ratio_bits, n_patterns (and seconds): the selector, and both baselines on chopped lines without times."""
    ev, _ = conveyor_events(spark, d, topology)
    m, out = ev.select("etype").distinct().count(), []
    began = time.time()
    model = select(ev)
    r = model.lengths().first()
    took = time.time() - began
    out.append((topology, "path_greedy", None, r["ratio"], model.ratio("bits"), r["n_patterns"], took))
    for size in chops:
        rows = Scratch(spark).write(order_only_events(ev, size))
        for name in BASELINES:
            began = time.time()
            patterns, bits, base = _baseline(name, rows, m, patience)
            out.append((topology, name, size, None, base / bits, len(patterns), time.time() - began))
    table = spark.createDataFrame(out, "data string, method string, chop int, ratio_units double, ratio_bits double, n_patterns long, seconds double")
    return table if seconds else table.drop("seconds")


def conveyor_units(spark: SparkSession, d: str) -> DataFrame:
    """data, events, trivial and total units, patterns and ratio of the path-greedy selector on the three lines."""
    out = None
    for top in seq.TOPOLOGY:
        ev, _ = conveyor_events(spark, d, top)
        here = select(ev).lengths().select(F.lit(top).alias("data"), "n_events", "trivial_units", "total_units", "n_patterns", "ratio")
        out = here if out is None else out.unionByName(here)
    return out


REAL = ("text", "tags", "roles", "intervals", "embeddings", "convlab")


def real_line(spark: SparkSession, d: str, name: str) -> DataFrame:
    """A data set's sequences on one line: etype, t."""
    t = lambda x: seq.table(spark, d, x)
    if name == "text":
        return text_events(spark, d)[0]
    rows = {"tags": lambda: seq.page_tags(t("pages")), "roles": lambda: seq.roles(t("conversations")), "intervals": lambda: seq.customer_intervals(t("orders"), t("lineitem")), "embeddings": lambda: seq.embedding_series(t("embeddings")), "convlab": lambda: seq.conveyor_windows(t("orders"))[0]}[name]()
    return seq.encode_alphabet(seq.concat(rows, Params().tg + 1))[0]


def real_table(spark: SparkSession, d: str, names: tuple[str, ...] = REAL, k: int | None = None, seconds: bool = False) -> DataFrame:
    """data, n_events, n_types, trivial_units, total_units, n_patterns, ratio, ratio_bits, lossless (and seconds), cap off by default."""
    ship(spark)
    scratch, out = Scratch(spark), []
    for name in names:
        ev = scratch.write(real_line(spark, d, name).select("etype", "t"))
        began = time.time()
        model = select(ev, params=Params(k=k))
        r = model.lengths().first()
        took = time.time() - began
        lossless = not encoding.lost_or_added(ev, model.encoded).take(1)
        out.append((name, r["n_events"], r["n_types"], r["trivial_units"], r["total_units"], r["n_patterns"], r["ratio"], model.ratio("bits"), lossless, took))
    table = spark.createDataFrame(out, "data string, n_events long, n_types long, trivial_units long, total_units long, n_patterns long, ratio double, ratio_bits double, lossless boolean, seconds double")
    return table if seconds else table.drop("seconds")


def cost_vs_candidates(spark: SparkSession, d: str, topology: str = "two") -> DataFrame:
    """parameter, value, first-round candidates, useful ones, patterns and units: falling fth, then a cut of the best few."""
    ev, _ = conveyor_events(spark, d, topology)
    out = []
    for name, selector, settings in (("fth", "two_phase", [Params(fth=f, max_size=4, max_rounds=1) for f in (0.08, 0.04, 0.02)]), ("max_candidates", "path_greedy", [Params(max_candidates=n) for n in (2, 8, 32)])):
        for p in settings:
            # what the first round finds doesn't depend on its choice, nor on later rounds
            first = selection.trace(ev, p.but(max_rounds=1, k=1, overlap_mode="ignore"), selector).orderBy("round").first()
            u = encoding.units(selection.select(ev, p, selector)).first()
            out.append((name, float(getattr(p, name)), first["n_found"], first["n_useful"], u["n_patterns"], u["total_units"]))
    return spark.createDataFrame(out, "parameter string, value double, n_found long, n_useful long, n_patterns long, total_units long")


def explain_cost(ev: DataFrame, p: Params) -> DataFrame:
    """level, kinds: frequent kinds of one and two events, which tell how mining will grow before it is run."""
    least = p.fth * ev.count()
    ones = ev.groupBy("etype").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
    p2 = p.but(max_size=2)
    pairs = baselines.frequent_all(ev, p2)
    return ones.agg(F.lit(1).alias("level"), F.count(F.lit(1)).alias("kinds")).unionByName(pairs.agg(F.lit(2).alias("level"), F.count(F.lit(1)).alias("kinds")))


def conveyor_top_patterns(spark: SparkSession, d: str, topology: str, k: int = 10) -> DataFrame:
    """rank, score, n_occ, pattern (units joined by >): the best episodes."""
    ev, alphabet = conveyor_events(spark, d, topology)
    return spelt(Scratch(spark).write(selection.select(ev, Params(k=k))), alphabet, ">")


def conveyor_relevance(spark: SparkSession, d: str, topology: str) -> DataFrame:
    """Share of chosen episodes that are pieces of routes, and of routes found whole."""
    ev, alphabet = conveyor_events(spark, d, topology)
    return metrics.route_match(selection.select(ev), alphabet, topology)


def spelt(encoded: DataFrame, alphabet: DataFrame, between: str) -> DataFrame:
    """Chosen episodes with their symbols: rank, score, n_occ, pattern."""
    units = encoded.where("rank IS NOT NULL").select("rank", "score", "n_occ", F.posexplode("types").alias("i", "etype")).join(alphabet, "etype")
    return units.groupBy("rank", "score", "n_occ").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("i", "symbol"))), lambda x: x["symbol"]), between).alias("pattern"))


def noise_control(spark: SparkSession, d: str, classes: int = 50) -> DataFrame:
    """Ratio on the stream table and on the same types dealt over the same times at random: noise must not compress better."""
    ship(spark)
    scratch = Scratch(spark)
    ev = scratch.write(seq.encode_alphabet(seq.events_table(seq.table(spark, d, "events"), classes))[0])
    a = select(ev).lengths().first()
    b = select(scratch.write(seq.shuffled(ev))).lengths().first()
    return spark.createDataFrame([(classes, a["ratio"], b["ratio"], a["ratio"] / b["ratio"])], "classes int, ratio double, shuffled_ratio double, relative double")


def text_events(spark: SparkSession, d: str, min_letters: int = 1, min_count: int = 6) -> tuple[DataFrame, DataFrame]:
    """English documents as one line of stemmed words without function words. Words seen under `min_count` times can't be in a
    useful episode of two (which needs six occurrences); they keep their places."""
    docs = seq.table(spark, d, "documents").where("lang = 'en'")
    words = seq.from_text(docs, stop_words=seq.STOP_WORDS, min_letters=min_letters, stemmer=seq.stem)
    often = words.groupBy("sym").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_count).select("sym")
    line = seq.concat(words.join(often, "sym"), Params().tg + 1)
    return seq.encode_alphabet(line)


def text_top20(spark: SparkSession, d: str) -> DataFrame:
    """The twenty best phrases with their units saved."""
    ship(spark)
    ev, alphabet = text_events(spark, d)
    scratch = Scratch(spark)
    ev, alphabet = scratch.write(ev), scratch.write(alphabet)
    return spelt(scratch.write(selection.select(ev, Params(k=20))), alphabet, " ").withColumnRenamed("pattern", "phrase")


def labelled(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Events (seq_id, etype, t) and labels (seq_id, label) of a labelled workload."""
    t = lambda x: seq.table(spark, d, x)
    if name == "convlab":
        rows, labels = seq.conveyor_windows(t("orders"))
    elif name == "embeddings":
        rows, labels = seq.embedding_series(t("embeddings")), t("embeddings").select(F.col("vec_id").alias("seq_id"), F.col("label").cast("string").alias("label"))
    elif name == "intervals":
        rows, labels = seq.customer_intervals(t("orders"), t("lineitem")), t("customer").select(F.col("c_custkey").alias("seq_id"), F.col("c_mktsegment").alias("label"))
    elif name == "language":
        words = seq.from_text(t("documents"))
        often = words.groupBy("sym").agg(F.count_distinct("seq_id").alias("n")).where("n >= 20").select("sym")
        rows, labels = words.join(often, "sym"), t("documents").select(F.col("doc_id").alias("seq_id"), F.col("lang").alias("label"))
    else:
        words = seq.from_text(t("documents"))
        often = words.groupBy("sym").agg(F.count_distinct("seq_id").alias("n")).where("n >= 20").select("sym")
        rows, labels = words.join(often, "sym"), t("labels").select(F.col("doc_id").alias("seq_id"), F.col(name).cast("string").alias("label"))
    ev, _ = seq.encode_alphabet(rows)
    return ev, labels


def accuracy(spark: SparkSession, d: str, name: str, folds: int = 10, reps: int = 20, k: int | None = None, sources: tuple[str, ...] = ("fixed_gap", "order_only", "singletons", *BASELINES), patience: int | None = None) -> DataFrame:
    """source, accuracy, n_features: fixed-gap, order-only and singleton features, and order-only ones of both baselines' patterns;
    patterns are chosen on training folds only."""
    ship(spark)
    ev, labels = labelled(spark, d, name)
    scratch = Scratch(spark)
    ev, labels = scratch.write(ev), scratch.write(labels.join(ev.select("seq_id").distinct(), "seq_id"))
    ones = scratch.write(features.singletons(ev))
    m = ev.select("etype").distinct().count()
    sizes: dict[str, list[int]] = {source: [] for source in sources}

    def make(train: DataFrame) -> dict:
        chosen = cache(lambda: scratch.write(features.select_per_class(ev, train, Params(k=k))))  # of two sources

        def of(source: str) -> DataFrame:
            if source == "singletons":
                return features.assemble(ones, labels)
            if source in BASELINES:
                patterns = _baseline(source, seq.order_only(ev.join(train.select("seq_id"), "seq_id")), m, patience)[0]
                eps = spark.createDataFrame([(">".join(map(str, c)), len(c), list(c)) for c in patterns], "ep_id string, size int, types array<int>")
            else:
                eps = chosen()
            found = (features.fixed_gap if source == "fixed_gap" else features.order_only)(ev, eps)
            sizes[source].append(eps.select("ep_id").distinct().count())
            return features.assemble(scratch.write(found.unionByName(ones)), labels)

        return {source: partial(of, source) for source in sources}

    out = []
    for source, got in classify.repeated_cv_of(make, labels, folds, reps).items():
        n = sizes[source]
        out.append((name, source, sum(a for _, a in got) / len(got), float(sum(n) / len(n)) if n else 0.0))
    return spark.createDataFrame(out, "data string, source string, accuracy double, n_features double")


def sweep(spark: SparkSession, d: str, topology: str = "two") -> DataFrame:
    """How units and patterns move with tg and k. Picks with a limit are the first ones without, so one model serves all of k."""
    ev, _ = conveyor_events(spark, d, topology)
    out, whole = [], None
    for v in (1, 2, 5, 10):
        model = select(ev, params=Params(tg=v))
        r = model.lengths().first()
        out.append(("tg", v, r["total_units"], r["n_patterns"], r["ratio"]))
        if v == Params().tg:
            whole = model
    out += [("k", *row) for row in first_picks(whole, (1, 5, 20, None))]
    return spark.createDataFrame(out, "parameter string, value int, total_units long, n_patterns long, ratio double")


def first_picks(model: CompressionModel, limits: tuple[int | None, ...]) -> list[tuple]:
    """limit, total units, patterns and ratio of the model that keeps its first picks only."""
    picks = model.encoded.where("rank IS NOT NULL")
    nodes = picks.select("rank", "starts", F.explode(F.arrays_zip(F.col("types").alias("e"), offsets(F.col("gaps")).alias("off"))).alias("x"))
    events = nodes.select("rank", F.col("x.e").alias("etype"), F.explode(F.transform("starts", lambda t: t + F.col("x.off"))).alias("t"))
    gone = events.groupBy("etype", "t").agg(F.min("rank").alias("rank")).groupBy("etype", "rank").agg(F.count(F.lit(1)).alias("n")).collect()  # a row for each type of a pick
    sizes = picks.select("rank", "size", "n_occ").collect()  # a row for each pick
    counts = {r["etype"]: r["n"] for r in model.events.groupBy("etype").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each type
    out = []
    for k in limits:
        kept, left = [r for r in sizes if k is None or r["rank"] <= k], dict(counts)
        for r in gone:
            if k is None or r["rank"] <= k:
                left[r["etype"]] -= r["n"]
        units = sum(2 * r["size"] + r["n_occ"] + 1 for r in kept) + sum(n + 3 for n in left.values() if n)
        out.append((k, units, len(kept), (3 * len(counts) + sum(counts.values())) / units))
    return out


def two_vs_greedy(spark: SparkSession, d: str, topology: str = "two", fth: float = 0.02) -> DataFrame:
    """Episodes that both selectors choose over those that either chooses, candidates, and seconds of each."""
    ev, _ = conveyor_events(spark, d, topology)
    sets, secs, cands = [], [], []
    for s in ("two_phase", "path_greedy"):
        began = time.time()
        rows = selection.select(ev, Params(fth=fth), s).where("rank IS NOT NULL").select(episode_key(F.col("types"), F.col("gaps"))).collect()
        secs.append(time.time() - began)
        sets.append({r[0] for r in rows})
        cands.append(selection.trace(ev, Params(fth=fth), s).agg(F.sum("n_found")).first()[0])
    both = len(sets[0] & sets[1]) / max(1, len(sets[0] | sets[1]))
    return spark.createDataFrame([(fth, both, len(sets[0]), len(sets[1]), cands[0], cands[1], secs[0], secs[1])], "fth double, jaccard double, n_two_phase long, n_path_greedy long, candidates_two_phase long, candidates_path_greedy long, s_two_phase double, s_path_greedy double")
