"""Mining, overlap and choice over DataFrames, and the loop of selection rounds, for sequences of any length.

For mining by joins, events are laid out in blocks of time; a block also holds copies of the first `halo` ticks after it, and an
occurrence belongs to the block of its start for its whole life. A level of growth is one equi-join of the frontier, exploded by
gap, with the events on (block, t), one small aggregation, and one join with the winners. Rounds go over packed blocks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expr import episode_score
from ..model import Episode, score
from ..params import Params
from ..sources.shared import Scratch
from . import kernel, occ, packed

SMALL_ROWS = 50_000  # rows of paths, winners or names that are broadcast
POOL = 2000  # candidates that a choice starts with


class Layout:
    """Events with a block each, and the same with halo copies."""

    def __init__(self, events: DataFrame, p: Params, nodes: int = 16):
        self.p = p
        self._lay(events, nodes)

    def _lay(self, events: DataFrame, nodes: int) -> None:
        p = self.p
        self.nodes, self.ticks = nodes, max(p.block_ticks, (nodes - 1) * p.tg + 1)
        self.home = events.select("etype", "t", F.floor(F.col("t") / self.ticks).alias("block"))
        halo = (nodes - 1) * p.tg
        copies = F.when(F.col("t") % self.ticks < halo, F.array("block", F.col("block") - 1)).otherwise(F.array("block"))
        self.wide = self.home.select("etype", "t", F.explode(copies).alias("block")).repartition("block").persist()

    def drop(self) -> None:
        self.wide.unpersist()

    def room_for(self, size: int, frontier: DataFrame) -> DataFrame:
        """The frontier, in a layout whose halo holds episodes of `size` nodes: blocks are laid anew with twice the nodes if not."""
        if size <= self.nodes:
            return frontier
        old = self.wide
        self._lay(self.home.select("etype", "t"), max(size, 2 * self.nodes))
        old.unpersist()
        return frontier.withColumn("block", F.floor(F.col("start_t") / self.ticks))


def small(df: DataFrame, rows: int) -> DataFrame:
    """A hint to broadcast a frame of so many rows, if they are few."""
    return F.broadcast(df) if rows <= SMALL_ROWS else df


def step(lay: Layout, frontier: DataFrame, paths: DataFrame) -> DataFrame:
    """All one-event extensions of the frontier by a type that the path doesn't have: path, block, start_t, t, etype, gap."""
    reach = frontier.select("path", "block", "start_t", F.explode(F.sequence(F.lit(1), F.lit(lay.p.tg))).alias("gap"), "end_t").withColumn("t", F.col("end_t") + F.col("gap"))
    met = reach.join(lay.wide, ["block", "t"])
    return met.join(paths.select("path", "types"), "path").where(~F.array_contains("types", F.col("etype"))).select("path", "block", "start_t", "t", "etype", "gap")


def frequent(lay: Layout, least: float, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """All frequent multi-node episodes (ep_id, size, types, gaps, freq) and their occurrences, level by level.

    Nothing is collected: a level's survivors stay a DataFrame. Going level by level visits what going depth-first would,
    since an extension is never more frequent than what it extends.
    """
    spark, p = lay.home.sparkSession, lay.p
    ones = lay.home.groupBy("etype").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
    eps = ones.select(F.col("etype").cast("string").alias("path"), F.array("etype").alias("types"), F.array().cast("array<int>").alias("gaps"))
    frontier = lay.home.join(ones.select("etype"), "etype").select(F.col("etype").cast("string").alias("path"), "block", F.col("t").alias("start_t"), F.col("t").alias("end_t"))
    all_eps, all_occ, size = None, None, 1
    while not (p.max_size and size >= p.max_size):
        frontier = lay.room_for(size + 1, frontier)
        reach = frontier.select("path", "block", "start_t", F.explode(F.sequence(F.lit(1), F.lit(p.tg))).alias("gap"), "end_t").withColumn("t", F.col("end_t") + F.col("gap"))
        met = reach.join(lay.wide, ["block", "t"]).join(eps.select("path", "types"), "path").where(~F.array_contains("types", F.col("etype")))
        met = scratch.write(met.select("path", "block", "start_t", "t", "etype", "gap"))
        n = met.groupBy("path", "etype", "gap").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= least)
        new = F.concat("path", F.lit("+"), F.col("gap").cast("string"), F.lit(">"), F.col("etype").cast("string"))
        kept = n.join(eps, "path").select(F.col("path").alias("old"), "etype", "gap", new.alias("path"), F.concat("types", F.array("etype")).alias("types"), F.concat("gaps", F.array("gap")).alias("gaps"), "freq")
        kept = scratch.write(kept)
        if not kept.take(1):
            break
        frontier = met.join(kept.select(F.col("old").alias("path"), "etype", "gap", F.col("path").alias("new")), ["path", "etype", "gap"]).select(F.col("new").alias("path"), "block", "start_t", F.col("t").alias("end_t"))
        eps, size = kept.select("path", "types", "gaps"), size + 1
        here = kept.select(F.col("path").alias("ep_id"), F.lit(size).alias("size"), "types", "gaps", "freq")
        at = frontier.select(F.col("path").alias("ep_id"), "start_t")
        all_eps, all_occ = (here, at) if all_eps is None else (all_eps.unionByName(here), all_occ.unionByName(at))
    if all_eps is None:
        return spark.createDataFrame([], "ep_id string, size int, types array<int>, gaps array<int>, freq long"), spark.createDataFrame([], "ep_id string, start_t long")
    return all_eps, all_occ


def overlap_matrix(occurrences: DataFrame, episodes: DataFrame) -> DataFrame:
    """ep_a, ep_b, shared with ep_a < ep_b: events that occurrences of both cover. Pairs that share none have no row."""
    own = occ.covered(occurrences.withColumn("seq_id", F.lit(0).cast("long")), episodes).select("ep_id", "etype", "t")
    a, b = own.withColumnRenamed("ep_id", "ep_a"), own.withColumnRenamed("ep_id", "ep_b")
    return a.join(b, ["etype", "t"]).where("ep_a < ep_b").groupBy("ep_a", "ep_b").agg(F.count(F.lit(1)).alias("shared"))


class _Choice:
    def __init__(self, episode: Episode, freq: int):
        self.types, self.gaps, self.value = episode.types, episode.gaps, score(episode.size, freq)
        self.episode, self.freq = episode, freq


def greedy(cands: list[_Choice], om_rows: list, left: int | None, p: Params) -> list[tuple[int, int]]:
    at = {c.episode.key: i for i, c in enumerate(cands)}
    om: dict[int, dict[int, int]] = {}
    for r in om_rows if p.overlap_mode == "penalise" else ():
        a, b = at[r["ep_a"]], at[r["ep_b"]]
        om.setdefault(a, {})[b] = om.setdefault(b, {})[a] = r["shared"]
    return kernel.greedy(cands, om, left)


def choose(useful: DataFrame, occs: DataFrame, left: int | None, p: Params, pool: int = POOL) -> tuple[list[tuple[Episode, int]], DataFrame | None]:
    """The greedy picks (episode, overlap score) from useful candidates, and the picked episodes as a frame.

    Only a pool of the best candidates by initial score reaches the driver, with the overlaps among them. An overlap score never
    exceeds the initial score, so picks above the best initial score outside the pool are final. If more may follow, the pool
    is widened and the choice made again; its beginning stays the same.
    """
    spark = useful.sparkSession
    order = [F.desc("score"), F.desc("size"), "span", "types", "gaps"]  # the tie rule
    rows = useful.withColumn("score", episode_score(F.col("size").cast("long"), F.col("freq"))).withColumn("span", F.aggregate("gaps", F.lit(0), lambda a, g: a + g))
    ranked = rows.orderBy(*order)
    while True:
        most = pool if p.max_candidates is None else min(pool, p.max_candidates)
        got = ranked.limit(most + 1).collect()
        bound = got[most]["score"] if len(got) > most and most != p.max_candidates else 0
        got = got[:most]
        if not got:
            return [], None
        cands = [_Choice(Episode(tuple(r["types"]), tuple(r["gaps"])), r["freq"]) for r in got]
        frame = occ.episodes_frame(spark, [c.episode for c in cands])
        om = overlap_matrix(occs.join(small(frame.select("ep_id"), len(cands)), "ep_id"), frame).collect() if p.overlap_mode == "penalise" else []
        picks = greedy(cands, om, left, p)
        final = next((i for i, (_, s) in enumerate(picks) if s <= bound), len(picks))
        if final == len(picks) and (bound == 0 or len(picks) == left):
            return [(cands[i].episode, s) for i, s in picks], frame
        pool *= 2


def select(events: DataFrame, p: Params, selector: str = "path_greedy", nodes: int = 32) -> tuple[list[tuple], DataFrame | None, DataFrame, list[tuple]]:
    """Picks (round, rank, score, episode), their occurrences (ep_id, start_t), the events left over, and a trace."""
    return rounds(events, p, selector, nodes)[:4]


def rounds(events: DataFrame, p: Params, selector: str, nodes: int = 32, until: int = 0) -> tuple[list[tuple], DataFrame | None, DataFrame, list[tuple], tuple[int, int] | None]:
    """What `select` returns, and whether rounds are left.

    Where a round leaves at most `until` events and more rounds follow, they are left to the kernel: the last value is then (rounds
    done, events at first), else None.
    """
    spark = events.sparkSession
    scratch = Scratch(spark)
    line = packed.Line(events.select("etype", "t"), p, scratch, nodes)
    total = line.n_events
    picks: list[tuple] = []
    kept: DataFrame | None = None
    trace, rnd = [], 0
    while (p.k is None or len(picks) < p.k) and (p.max_rounds is None or rnd < p.max_rounds) and line.n_events:
        if rnd and line.n_events <= until:
            return picks, kept, line.events(), trace, (rnd, total)
        rnd += 1
        if selector == "path_greedy":
            found = packed.best_paths(line)
        else:
            found = packed.frequent(line, p.fth * (total if p.min_freq_base == "original" else line.n_events))
        useful = [(e, n) for e, n in found if score(e.size, n) > 0]
        n_useful = len(useful) if p.max_candidates is None else min(len(useful), p.max_candidates)
        if not n_useful:
            trace.append((rnd, len(found), 0, 0, line.n_events))
            break
        chosen = packed.choose(line, useful, None if p.k is None else p.k - len(picks))
        mine = scratch.write(line.occurrences([e for e, _ in chosen]))
        for e, s in chosen:
            picks.append((rnd, len(picks) + 1, s, e))
        line.delete([e for e, _ in chosen])
        kept = mine if kept is None else kept.unionByName(mine)
        trace.append((rnd, len(found), n_useful, len(chosen), line.n_events))
        if sum(s for _, s in chosen) <= p.min_gain:
            break
    return picks, kept, line.events(), trace, None
