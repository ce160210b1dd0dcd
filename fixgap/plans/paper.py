"""Registered queries for the sequence methods, each with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.expr import elias_bits, episode_key, episode_score, is_useful, offsets, type_bits
from ..model import Episode
from ..operators import baselines, encoding, features, occ, selection, table
from ..params import Params
from ..sources import sequence as seq
from ..sources.shared import Scratch, ship
from . import oracle

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}
TG = 5


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        Q[name or f.__name__] = f
        if sql:
            O[name or f.__name__] = sql
        return f

    return put


# ---- sequences, in both forms

EVENT_ORIGIN = "TIMESTAMP '2024-01-01 00:00:00'"


def conveyor(spark: SparkSession, d: str, topology: str) -> DataFrame:
    ship(spark)
    return seq.conveyor_from_orders(seq.table(spark, d, "orders"), topology)


def conveyor_sql(topology: str) -> str:
    rows = ", ".join(f"({r}, {p}, '{u}', {o})" for r, p, u, o in seq.routes(topology))
    return f"""r(route, pos, sym, off) AS (VALUES {rows}), k AS (SELECT 16 * greatest(1, round(count(*) / 1500.0))::BIGINT AS d FROM orders),
    c AS (SELECT DISTINCT sym, (date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) * d + (o_orderkey * 7919) % d + 1 + off + CASE WHEN o_custkey % 10 = 0 AND pos > 5 THEN 1 ELSE 0 END)::BIGINT AS t
          FROM orders CROSS JOIN k JOIN r ON CAST(substr(o_orderpriority, 1, 1) AS INT) = route),
    ev AS (SELECT CAST(dense_rank() OVER (ORDER BY sym) AS INT) AS etype, sym, t FROM c)"""


def coded(spark: SparkSession, d: str, topology: str) -> DataFrame:
    ship(spark)
    return seq.coded_conveyor(seq.table(spark, d, "orders"), topology)[0].select("etype", "t")


for _top in seq.TOPOLOGY:
    query(f"WITH {conveyor_sql(_top)} SELECT sym, t FROM c", f"seq_conveyor_{_top}")(lambda s, d, top=_top: conveyor(s, d, top).select("sym", "t"))
    query(f"WITH {conveyor_sql(_top)} SELECT etype, any_value(sym) AS symbol, count(*) AS n FROM ev GROUP BY etype", f"alphabet_{_top}")(lambda s, d, top=_top: seq.encode_alphabet(conveyor(s, d, top))[1])
    query(f"WITH {conveyor_sql(_top)} SELECT count(*) AS n_events, count(DISTINCT etype) AS n_types, 3 * count(DISTINCT etype) + count(*) AS trivial_units FROM ev", f"trivial_length_{_top}")(lambda s, d, top=_top: encoding.trivial_units(coded(s, d, top)))
    query(f"WITH {conveyor_sql(_top)} SELECT 2 * count(*) AS raw_units FROM ev", f"raw_length_{_top}")(lambda s, d, top=_top: encoding.raw_units(coded(s, d, top)))

_TICKS = "CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / 60000000) AS BIGINT) + 1"
query(f"SELECT DISTINCT event_type AS sym, {_TICKS} AS t FROM events", "seq_events_5")(lambda s, d: seq.events_table(seq.table(s, d, "events"), 5).select("sym", "t"))
query(f"SELECT DISTINCT concat(event_type, '|', user_id % 10) AS sym, {_TICKS} AS t FROM events", "seq_events_50")(lambda s, d: seq.events_table(seq.table(s, d, "events"), 50).select("sym", "t"))
_WORDS = """w AS (SELECT doc_id AS seq_id, list_filter(string_split(regexp_replace(lower(text), '[^a-z]+', ' ', 'g'), ' '), lambda x: x <> '') AS ws FROM documents)"""
query(f"WITH {_WORDS} SELECT seq_id, unnest(ws) AS sym, CAST(generate_subscripts(ws, 1) AS BIGINT) AS t FROM w", "seq_text")(lambda s, d: seq.from_text(seq.table(s, d, "documents")))
query("SELECT conv_id AS seq_id, role AS sym, turn + 1 AS t FROM conversations GROUP BY 1, 2, 3", "seq_roles")(lambda s, d: seq.roles(seq.table(s, d, "conversations")))
query("WITH g AS (SELECT page_id AS seq_id, regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1) AS ws FROM pages) SELECT seq_id, unnest(ws) AS sym, CAST(generate_subscripts(ws, 1) AS BIGINT) AS t FROM g", "seq_pages")(lambda s, d: seq.page_tags(seq.table(s, d, "pages")))
_EMB = """m AS (SELECT vec_id AS seq_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings),
    e AS (SELECT seq_id, concat(i // 8, '|', CAST(least(3, greatest(0, floor(CAST(x AS DOUBLE) / 0.125) + 2)) AS INT)) AS sym, CAST(i + 1 AS BIGINT) AS t FROM m)"""
query(f"WITH {_EMB} SELECT * FROM e", "seq_embeddings")(lambda s, d: seq.embedding_series(seq.table(s, d, "embeddings")))
_INTV = """j AS (SELECT o_custkey AS seq_id, concat(l_returnflag, l_linestatus) AS s, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) + 1 AS t1, date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) + 1 AS t2
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate > o_orderdate),
    i AS (SELECT seq_id, concat(s, '/start') AS sym, t1 AS t FROM j UNION SELECT seq_id, concat(s, '/end'), t2 FROM j)"""
query(f"WITH {_INTV} SELECT * FROM i", "seq_intervals")(lambda s, d: seq.customer_intervals(seq.table(s, d, "orders"), seq.table(s, d, "lineitem")))


@query(f"""WITH {_INTV}, s AS (SELECT seq_id, min(t) AS lo, max(t) AS hi FROM i GROUP BY seq_id), b AS (SELECT seq_id, lo, sum(hi - lo + 6) OVER (ORDER BY seq_id) - (hi - lo + 6) AS base FROM s)
    SELECT CAST(0 AS BIGINT) AS seq_id, sym, CAST(t + base - lo + 1 AS BIGINT) AS t FROM i JOIN b USING (seq_id)""")
def seq_concat(spark, d):
    return seq.concat(Q["seq_intervals"](spark, d), TG)


_CHOP = "WITH {e}, z AS (SELECT etype, t, row_number() OVER (ORDER BY t, etype) - 1 AS n FROM ev)"


@query(_CHOP.format(e=conveyor_sql("two")) + " SELECT CAST(n // 50 AS BIGINT) AS seq_id, etype, t FROM z")
def seq_chop_50(spark, d):
    return seq.chop(coded(spark, d, "two").withColumn("seq_id", F.lit(0).cast("long")), 50).select("seq_id", "etype", "t")


@query(_CHOP.format(e=conveyor_sql("two")) + " SELECT CAST(0 AS BIGINT) AS seq_id, etype, CAST(n + 1 AS BIGINT) AS t FROM z")
def seq_order_only(spark, d):
    return seq.order_only(coded(spark, d, "two").withColumn("seq_id", F.lit(0).cast("long"))).select("seq_id", "etype", "t")


# ---- mining

_LEAST = "0.01"
_PAIRS = f"""p AS (SELECT a.etype AS e1, b.etype AS e2, b.t - a.t AS g, count(*) AS n FROM ev a JOIN ev b ON b.t > a.t AND b.t <= a.t + {TG} AND a.etype <> b.etype GROUP BY 1, 2, 3)"""


@query(f"WITH {conveyor_sql('three')} SELECT etype, count(*) AS n FROM ev GROUP BY etype HAVING count(*) >= {_LEAST} * (SELECT count(*) FROM ev)")
def singletons_frequent(spark, d):
    ev = coded(spark, d, "three")
    total = ev.count()
    return ev.groupBy("etype").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= float(_LEAST) * total)


def _mined(spark, d, topology, fth, size=None):
    p = Params(fth=fth, engine="table", max_size=size)
    return baselines.frequent_all(coded(spark, d, topology), p)


@query(f"WITH {conveyor_sql('three')}, {_PAIRS} SELECT CAST(e1 AS INT) AS e1, CAST(e2 AS INT) AS e2, CAST(g AS INT) AS gap, n AS freq FROM p WHERE n >= {_LEAST} * (SELECT count(*) FROM ev)")
def pairs_frequent(spark, d):
    rows = _mined(spark, d, "three", float(_LEAST), 2)
    return rows.where("size = 2").select(F.col("types")[0].alias("e1"), F.col("types")[1].alias("e2"), F.col("gaps")[0].alias("gap"), "freq")


@query(f"""WITH {conveyor_sql('two')}, x AS (SELECT a.etype AS e1, b.etype AS e2, c.etype AS e3, b.t - a.t AS g1, c.t - b.t AS g2, count(*) AS n FROM ev a JOIN ev b ON b.t > a.t AND b.t <= a.t + {TG} AND a.etype <> b.etype
    JOIN ev c ON c.t > b.t AND c.t <= b.t + {TG} AND c.etype <> a.etype AND c.etype <> b.etype GROUP BY 1, 2, 3, 4, 5)
    SELECT CAST(e1 AS INT) AS e1, CAST(e2 AS INT) AS e2, CAST(e3 AS INT) AS e3, CAST(g1 AS INT) AS g1, CAST(g2 AS INT) AS g2, n AS freq FROM x WHERE n >= 0.02 * (SELECT count(*) FROM ev)""")
def triples_frequent(spark, d):
    t = _mined(spark, d, "two", 0.02, 3).where("size = 3")
    return t.select(*(F.col("types")[i].alias(f"e{i + 1}") for i in range(3)), *(F.col("gaps")[i].alias(f"g{i + 1}") for i in range(2)), "freq")


def _level(ev: DataFrame, p: Params) -> tuple[table.Layout, DataFrame]:
    lay = table.Layout(ev, p)
    return lay, lay.home.select(F.col("etype").alias("path"), "block", F.col("t").alias("start_t"), F.col("t").alias("end_t"))


def _best(cand: DataFrame) -> DataFrame:
    n = cand.groupBy("path", "etype", "gap").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("r", F.row_number().over(Window.partitionBy("path").orderBy(F.desc("n"), "gap", "etype"))).where("r = 1").drop("r")


_B1 = f"b1 AS (SELECT e1, e2, g, n FROM (SELECT *, row_number() OVER (PARTITION BY e1 ORDER BY n DESC, g, e2) AS r FROM p) WHERE r = 1)"
_FLOOR1 = f"(n > 5 OR (n = 5 AND g < {TG}))"


@query(f"WITH {conveyor_sql('three')}, {_PAIRS}, {_B1} SELECT CAST(e1 AS INT) AS path, CAST(e2 AS INT) AS etype, CAST(g AS INT) AS gap, n, {_FLOOR1} AS admitted FROM b1")
def best_ext_level1(spark, d):
    ev = coded(spark, d, "three")
    lay, front = _level(ev, Params())
    paths = lay.home.select("etype").distinct().select(F.col("etype").alias("path"), F.array("etype").alias("types"))
    best = _best(table.step(lay, front, paths))
    return best.select("path", "etype", "gap", "n", (F.col("n") > 5) | ((F.col("n") == 5) & (F.col("gap") < TG))).toDF("path", "etype", "gap", "n", "admitted")


@query(f"""WITH {conveyor_sql('three')}, {_PAIRS}, {_B1}, o AS (SELECT b1.e1, b1.e2, b.t FROM b1 JOIN ev a ON a.etype = b1.e1 JOIN ev b ON b.etype = b1.e2 AND b.t = a.t + b1.g WHERE {_FLOOR1}),
    q AS (SELECT o.e1, c.etype AS e3, c.t - o.t AS g, count(*) AS n FROM o JOIN ev c ON c.t > o.t AND c.t <= o.t + {TG} AND c.etype <> o.e1 AND c.etype <> o.e2 GROUP BY 1, 2, 3)
    SELECT CAST(e1 AS INT) AS path, CAST(e3 AS INT) AS etype, CAST(g AS INT) AS gap, n FROM (SELECT *, row_number() OVER (PARTITION BY e1 ORDER BY n DESC, g, e3) AS r FROM q) WHERE r = 1""")
def best_ext_level2(spark, d):
    ev = coded(spark, d, "three")
    lay, front = _level(ev, Params())
    paths = lay.home.select("etype").distinct().select(F.col("etype").alias("path"), F.array("etype").alias("types"))
    cand = table.step(lay, front, paths)
    best = _best(cand).where(f"n > 5 OR (n = 5 AND gap < {TG})")
    grown = cand.join(best, ["path", "etype", "gap"])
    longer = best.join(paths, "path").select("path", F.concat("types", F.array("etype")).alias("types"))
    return _best(table.step(lay, grown.select("path", "block", "start_t", F.col("t").alias("end_t")), longer))


_GROW = "WITH RECURSIVE " + conveyor_sql("three") + ", " + oracle.greedy_paths("", "ev", TG, "frequency_floor")


@query(_GROW + " SELECT DISTINCT CAST(path AS INT) AS path, types, gaps, CAST(size AS INT) AS size, n FROM grow WHERE size IN (3, 4)")
def best_ext_level3(spark, d):
    """The paths after two and three extensions, grown until the frequency floor."""
    scratch = Scratch(spark)
    ev = scratch.write(coded(spark, d, "three"))
    lay, front = _level(ev, Params())
    grown = lay.home.select("etype").distinct().select(F.col("etype").alias("path"), F.array("etype").alias("types"), F.array().cast("array<int>").alias("gaps"))
    out = None
    for size in (1, 2, 3):
        cand = scratch.write(table.step(lay, front, grown))
        best = _best(cand).where((F.col("n") * size > 2 * size + 3) | ((F.col("n") * size == 2 * size + 3) & (F.col("gap") < TG)))
        front = cand.join(best, ["path", "etype", "gap"]).select("path", "block", "start_t", F.col("t").alias("end_t"))
        grown = scratch.write(best.join(grown.select("path", "types", "gaps"), "path").select("path", F.concat("types", F.array("etype")).alias("types"), F.concat("gaps", F.array("gap")).alias("gaps"), "n"))
        if size > 1:
            here = grown.select("path", "types", "gaps", F.lit(size + 1).alias("size"), "n")
            out = here if out is None else out.unionByName(here)
    lay.drop()
    return out


# ---- scores, overlap, choice


def _pair_episodes(spark, d, topology, fth=0.02) -> tuple[DataFrame, DataFrame]:
    ev = coded(spark, d, topology)
    scratch = Scratch(spark)
    ev = scratch.write(ev)
    rows, occs = table.frequent(table.Layout(ev, Params(max_size=2)), fth * ev.count(), scratch)
    return rows.withColumn("offsets", offsets(F.col("gaps"))), occs, ev


_SCORE = f"WITH {conveyor_sql('two')}, {_PAIRS}, s AS (SELECT concat(e1, '+', g, '>', e2) AS ep_id, e1, e2, g, n, n * 2 - (4 + n + 1) AS score FROM p WHERE n >= 0.02 * (SELECT count(*) FROM ev))"


@query(_SCORE + " SELECT ep_id, n AS freq, score, score > 0 AS useful FROM s")
def score_table(spark, d):
    rows, _, _ = _pair_episodes(spark, d, "two")
    size = F.col("size").cast("long")
    return rows.select("ep_id", "freq", episode_score(size, F.col("freq")).alias("score"), is_useful(size, F.col("freq")).alias("useful"))


_OM = """, v AS (SELECT s.ep_id, a.etype, a.t FROM s JOIN ev a ON a.etype = s.e1 JOIN ev b ON b.etype = s.e2 AND b.t = a.t + s.g UNION ALL SELECT s.ep_id, b.etype, b.t FROM s JOIN ev a ON a.etype = s.e1 JOIN ev b ON b.etype = s.e2 AND b.t = a.t + s.g)"""


@query(_SCORE + _OM + " SELECT x.ep_id AS ep_a, y.ep_id AS ep_b, count(*) AS shared FROM v x JOIN v y ON x.etype = y.etype AND x.t = y.t AND x.ep_id < y.ep_id GROUP BY 1, 2")
def overlap_matrix_pairs(spark, d):
    rows, occs, _ = _pair_episodes(spark, d, "two")
    return table.overlap_matrix(occs, rows)


_ORDER = "ORDER BY score DESC, g, e1, e2"


@query(_SCORE + f" SELECT ep_id, score FROM s {_ORDER} LIMIT 1")
def greedy_first_pick(spark, d):
    return _pick(spark, d, 1).select("ep_id", "score")


@query(_SCORE + _OM + f""", f AS (SELECT * FROM s {_ORDER} LIMIT 1), u AS (SELECT s.*, s.score - coalesce((SELECT count(*) FROM v x JOIN v y ON x.etype = y.etype AND x.t = y.t WHERE x.ep_id = s.ep_id AND y.ep_id = (SELECT ep_id FROM f)), 0) AS left_score
    FROM s WHERE s.ep_id <> (SELECT ep_id FROM f))
    SELECT 1 AS rank, ep_id, score FROM f UNION ALL SELECT 2, ep_id, left_score FROM (SELECT * FROM u ORDER BY left_score DESC, g, e1, e2 LIMIT 1)""")
def greedy_two_picks(spark, d):
    return _pick(spark, d, 2)


def _pick(spark, d, k):
    ship(spark)
    rows = selection.select(coded(spark, d, "two"), Params(fth=0.02, k=k, max_size=2, max_rounds=1), "two_phase").where("rank IS NOT NULL")
    return rows.select("rank", episode_key(F.col("types"), F.col("gaps")).alias("ep_id"), "score")


@query(_SCORE + f", f AS (SELECT * FROM s {_ORDER} LIMIT 1), g AS (SELECT a.etype, a.t, b.etype AS e, b.t AS u FROM f JOIN ev a ON a.etype = f.e1 JOIN ev b ON b.etype = f.e2 AND b.t = a.t + f.g) SELECT etype, t FROM ev EXCEPT (SELECT etype, t FROM g UNION SELECT e, u FROM g)")
def delete_covered(spark, d):
    ev = coded(spark, d, "two")
    first = _pick(spark, d, 1).first()
    rows, occs, _ = _pair_episodes(spark, d, "two")
    mine = occs.where(F.col("ep_id") == first["ep_id"]).withColumn("seq_id", F.lit(0).cast("long"))
    return ev.join(occ.covered(mine, rows).select("etype", "t"), ["etype", "t"], "left_anti")


# ---- a fixed model: the first three units of each of two routes

_A, _B = (x[:3] for x in seq.TOPOLOGY["two"])
_KINDS = [[seq.TRANSFER[u.rstrip("0123456789")] for u in x[:2]] for x in (_A, _B)]
FIXED = [(_A, _KINDS[0]), (_B, _KINDS[1])]


def _fixed_parts(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Events, the two episodes with row_no, and their occurrences."""
    ship(spark)
    ev, alphabet = seq.encode_alphabet(conveyor(spark, d, "two"))
    code = {r["symbol"]: r["etype"] for r in alphabet.collect()}  # a row for each unit
    eps = [Episode(tuple(code[s] for s in syms), tuple(gaps)) for syms, gaps in FIXED]
    frame = occ.episodes_frame(spark, eps).join(spark.createDataFrame([(e.key, i) for i, e in enumerate(eps, 1)], "ep_id string, row_no int"), "ep_id")
    return ev.select("etype", "t"), frame, occ.fixed(ev, frame)


def _rest(ev: DataFrame, frame: DataFrame, occs: DataFrame) -> DataFrame:
    return ev.join(occ.covered(occs, frame).select("etype", "t"), ["etype", "t"], "left_anti")


def _fixed(spark, d) -> tuple[DataFrame, DataFrame]:
    ev, frame, occs = _fixed_parts(spark, d)
    return ev, encoding.encode(frame, occs).unionByName(encoding.trivial(_rest(ev, frame, occs)).withColumn("row_no", F.col("row_no") + 100))


def _fixed_long(spark, d):
    ev, frame, occs = _fixed_parts(spark, d)
    rows, starts = encoding.trivial_long(_rest(ev, frame, occs))
    return ev, encoding.encode_long(frame, occs), (rows.withColumn("row_no", F.col("row_no") + 100), starts.withColumn("row_no", F.col("row_no") + 100))


def _three(units: list[str], gaps: list[int]) -> str:
    return f"SELECT a.t FROM ev a JOIN ev b ON b.sym = '{units[1]}' AND b.t = a.t + {gaps[0]} JOIN ev c ON c.sym = '{units[2]}' AND c.t = a.t + {sum(gaps)} WHERE a.sym = '{units[0]}'"


_COV = " UNION ".join(f"SELECT '{u}' AS sym, t + {off} AS t FROM o{i}" for i, (units, gaps) in enumerate(FIXED, 1) for u, off in zip(units, (0, gaps[0], sum(gaps)), strict=True))
_GAP_BITS = [sum(2 * (g.bit_length() - 1) + 1 for g in gaps) for _, gaps in FIXED]
_FIX = f"""WITH {conveyor_sql('two')}, o1 AS ({_three(*FIXED[0])}), o2 AS ({_three(*FIXED[1])}), cov AS ({_COV}),
    rest AS (SELECT etype, t FROM ev WHERE NOT EXISTS (SELECT 1 FROM cov WHERE cov.sym = ev.sym AND cov.t = ev.t)),
    enc AS (SELECT 1 AS row_no, 3 AS size, list(t) AS starts, count(*) AS n FROM o1 UNION ALL SELECT 2, 3, list(t), count(*) FROM o2 UNION ALL SELECT etype + 100, 1, list(t), count(*) FROM rest GROUP BY etype)"""
_BITS = "(2 * (length(bin(n)) - 1) + 1)"


@query(_FIX + " SELECT CAST(row_no AS INT) AS row_no, size, n AS n_occ, list_sum(starts)::BIGINT AS start_sum, list_min(starts) AS first_start FROM enc WHERE n > 0")
def encode_fixed_model(spark, d):
    e = _fixed(spark, d)[1]
    return e.select("row_no", "size", "n_occ", F.aggregate("starts", F.lit(0).cast("long"), lambda a, x: a + x).alias("start_sum"), F.array_min("starts").alias("first_start"))


@query(_FIX + " SELECT CAST(row_no AS INT) AS row_no, size, n AS n_occ, unnest(starts) AS start_t FROM enc WHERE n > 0")
def encode_long_fixed_model(spark, d):
    ev, multi, ones = _fixed_long(spark, d)
    return (multi[0].unionByName(ones[0])).join(multi[1].unionByName(ones[1]), "row_no").select("row_no", "size", "n_occ", "start_t")


@query(f"WITH {conveyor_sql('two')} SELECT etype, t FROM ev")
def decode_long_fixed_model(spark, d):
    ev, multi, ones = _fixed_long(spark, d)
    return encoding.decode_long(multi[0].unionByName(ones[0]), multi[1].unionByName(ones[1]))


@query(_FIX + " SELECT sum(2 * size)::BIGINT AS model_units, sum(n + 1)::BIGINT AS data_units, sum(2 * size + n + 1)::BIGINT AS total_units, count(*) FILTER (size > 1) AS n_patterns FROM enc WHERE n > 0")
def length_for_set(spark, d):
    ev, frame, occs = _fixed_parts(spark, d)
    return encoding.units_for(ev, frame, occs)


@query(_FIX + " SELECT sum(2 * size)::BIGINT AS model_units, sum(n + 1)::BIGINT AS data_units, sum(2 * size + n + 1)::BIGINT AS total_units, count(*) FILTER (size > 1) AS n_patterns FROM enc WHERE n > 0")
def length_fixed_model(spark, d):
    return encoding.units(_fixed(spark, d)[1])


@query(_FIX + f""", m AS (SELECT count(DISTINCT etype) AS m FROM ev), u AS (SELECT row_no, size, n, unnest(starts) AS x FROM enc WHERE n > 0),
    s AS (SELECT row_no, sum(2 * (length(bin(x)) - 1) + 1) AS b FROM u GROUP BY 1), rows_ AS (SELECT (2 * (length(bin(size)) - 1) + 1) + size * (SELECT length(bin(m)) FROM m) + CASE row_no WHEN 1 THEN {_GAP_BITS[0]} WHEN 2 THEN {_GAP_BITS[1]} ELSE 0 END + {_BITS} + b AS bits FROM enc JOIN s USING (row_no) WHERE n > 0)
    SELECT (sum(bits) + (SELECT 2 * (length(bin(m)) - 1) + 1 FROM m))::BIGINT AS total_bits FROM rows_""")
def bits_fixed_model(spark, d):
    ev, e = _fixed(spark, d)
    return encoding.bits(e, ev.select("etype").distinct().count())


@query(_FIX + " SELECT etype, t FROM rest")
def uncovered_fixed_model(spark, d):
    return encoding.decode(_fixed(spark, d)[1].where("size = 1"))


@query(f"WITH {conveyor_sql('two')} SELECT etype, t FROM ev")
def stream_round_trip(spark, d):
    return encoding.decode(encoding.from_stream(encoding.to_stream(_fixed(spark, d)[1])))


@query(f"WITH {conveyor_sql('two')}, m AS (SELECT count(DISTINCT etype) AS m FROM ev), q AS (SELECT etype, count(*) AS n, sum(2 * (length(bin(t)) - 1) + 1) AS b FROM ev GROUP BY etype) SELECT (sum(1 + (SELECT length(bin(m)) FROM m) + {_BITS} + b) + (SELECT 2 * (length(bin(m)) - 1) + 1 FROM m))::BIGINT AS total_bits FROM q")
def trivial_bits(spark, d):
    ev = coded(spark, d, "two")
    return encoding.bits(encoding.trivial(ev), ev.select("etype").distinct().count())


@query(_FIX + " SELECT sum(2 * size + 1 + n * size)::BIGINT AS per_event_units FROM enc WHERE n > 0")
def per_event_time_units(spark, d):
    return encoding.per_event_time_units(_fixed(spark, d)[1])


# ---- selectors: chosen episodes, traces and units against SQL that makes the whole choice itself; decoded encodings against the data

ROUNDS = 5  # written out in SQL; the conveyors take fewer
_MODEL = " SELECT * FROM chosen"
_COST = f" SELECT (SELECT count(*) FROM ev) AS n_events, (SELECT 3 * count(DISTINCT etype) + count(*) FROM ev) AS trivial_units, CAST({oracle.UNITS} AS BIGINT) AS total_units, (SELECT count(*) FROM chosen) AS n_patterns, true AS lossless"


def _model(spark, d, top, p=Params(), selector="path_greedy"):
    rows = selection.select(coded(spark, d, top), p, selector).where("rank IS NOT NULL")
    return rows.select("round", "rank", "score", "size", "n_occ", episode_key(F.col("types"), F.col("gaps")).alias("episode"))


def _cost_check(spark, d, top, p=Params(), selector="path_greedy"):
    scratch = Scratch(spark)
    ev = scratch.write(coded(spark, d, top))
    enc = scratch.write(selection.select(ev, p, selector))
    bad = encoding.lost_or_added(ev, enc).agg((F.count(F.lit(1)) == 0).alias("lossless"))
    return encoding.trivial_units(ev).join(encoding.units(enc)).join(bad).select("n_events", "trivial_units", "total_units", "n_patterns", "lossless")


def _pair(name: str, top: str, p: Params, selector: str = "path_greedy", rounds: int = ROUNDS, trace: bool = False, by_table: bool = False) -> None:
    """model_<name>, cost and trace by the kernel, select_<name>_table by the table engine, all against one SQL choice."""
    sql = oracle.selection(conveyor_sql(top), p.max_rounds or rounds, p.stop_rule, p.fth if selector == "two_phase" else None, p.k, p.max_candidates, p.overlap_mode == "penalise", p.tg, p.max_size)
    query(sql + _MODEL, f"model_{name}")(lambda s, d: _model(s, d, top, p, selector))
    if by_table:
        query(sql + _MODEL, f"select_{name}_table")(lambda s, d: _model(s, d, top, p.but(engine="table"), selector))
    query(sql + _COST, f"select_{name}_cost_check")(lambda s, d: _cost_check(s, d, top, p, selector))
    if trace:
        # rounds after the last are not run
        query(sql + " SELECT CAST(round AS BIGINT) AS round, n_found, n_useful, n_picked, events_left FROM steps WHERE round <= 1 + (SELECT count(*) FROM steps WHERE n_picked > 0) AND round <= 1 + (SELECT count(*) FROM steps WHERE events_left > 0)", f"trace_{name}")(lambda s, d: selection.trace(coded(s, d, top), p, selector))


for _top in seq.TOPOLOGY:
    _pair(_top, _top, Params(), trace=True, by_table=_top != "five")
    for _rule in ("score_improves", "frequency_floor"):
        _sql = f"WITH {conveyor_sql(_top)} SELECT etype, t FROM ev"
        query(_sql, f"select_{_top}_{_rule}_decoded")(lambda s, d, top=_top, rule=_rule: encoding.decode(selection.select(coded(s, d, top), Params(stop_rule=rule))))
_pair("two_phase", "two", Params(fth=0.02, max_size=3), "two_phase", 8, trace=True, by_table=True)
_pair("two_phase_long", "two", Params(fth=0.04, max_rounds=1), "two_phase")
_pair("best_k", "three", Params(k=4))
_pair("best_few", "three", Params(max_candidates=4), rounds=9)
_pair("one_round", "three", Params(max_rounds=1), by_table=True)
_pair("no_penalty", "three", Params(overlap_mode="ignore", max_rounds=1))
_pair("floor_two_rounds", "three", Params(stop_rule="frequency_floor", max_rounds=2))
query(f"WITH {conveyor_sql('two')} SELECT etype, t FROM ev", "select_two_phase_decoded")(lambda s, d: encoding.decode(selection.select(coded(s, d, "two"), Params(fth=0.02), "two_phase")))


# ---- reductions of all frequent episodes

_ALL = f"WITH RECURSIVE {conveyor_sql('two')}, {oracle.all_frequent('', 'ev', 0.04)}, {oracle.closed('', 'found')}"
_EPS = " SELECT key AS ep_id, CAST(size AS INT) AS size, n AS freq FROM eps"
query(_ALL + _EPS, "frequent_all")(lambda s, d: _mined(s, d, "two", 0.04).select("ep_id", "size", "freq"))
query(_ALL + _EPS + " WHERE key IN (SELECT key FROM closed)", "frequent_closed")(lambda s, d: baselines.closed(_mined(s, d, "two", 0.04)).select("ep_id", "size", "freq"))
query(_ALL + _EPS + " WHERE key IN (SELECT key FROM maximal)", "frequent_maximal")(lambda s, d: baselines.maximal(_mined(s, d, "two", 0.04)).select("ep_id", "size", "freq"))
query(_ALL + ", kept AS MATERIALIZED (SELECT * FROM found WHERE key IN (SELECT key FROM closed)), " + oracle.picks("", "kept") + " SELECT CAST(place + 1 AS INT) AS rank, value AS score, key AS episode, n AS freq FROM pick", "closed_then_greedy")(
    lambda s, d: baselines.closed_then_greedy(coded(s, d, "two"), Params(fth=0.04)).select("rank", "score", episode_key(F.col("types"), F.col("gaps")).alias("episode"), "freq")
)
query(None, "random_subset")(lambda s, d: baselines.random_subset(_mined(s, d, "two", 0.04), 10))


# ---- features

_TWO_STEP = "f AS (SELECT a.seq_id, concat(a.sym, '>', b.sym) AS feature, count(*) AS n FROM {src} a JOIN {src} b ON a.seq_id = b.seq_id AND b.t = a.t + 1 WHERE a.sym = 'user' AND b.sym = 'assistant' GROUP BY 1, 2)"


@query("WITH e AS (SELECT DISTINCT conv_id AS seq_id, role AS sym, turn + 1 AS t FROM conversations), " + _TWO_STEP.format(src="e") + " SELECT seq_id, n FROM f")
def count_fixed_gap_features(spark, d):
    ev, alphabet = seq.encode_alphabet(seq.roles(seq.table(spark, d, "conversations")))
    code = {r["symbol"]: r["etype"] for r in alphabet.collect()}
    eps = occ.episodes_frame(spark, [Episode((code["user"], code["assistant"]), (1,))])
    return features.fixed_gap(ev, eps).select("seq_id", "n")


@query("WITH e AS (SELECT DISTINCT conv_id AS seq_id, role AS sym, turn + 1 AS t FROM conversations), r AS (SELECT seq_id, sym, CAST(dense_rank() OVER (ORDER BY sym) AS INT) AS c FROM e) SELECT seq_id, concat('e', c) AS feature, count(*) AS n FROM r GROUP BY 1, 2")
def count_singleton_features(spark, d):
    return features.singletons(seq.encode_alphabet(seq.roles(seq.table(spark, d, "conversations")))[0])


@query()
def count_order_only_features(spark, d):
    ev, alphabet = seq.encode_alphabet(seq.roles(seq.table(spark, d, "conversations")))
    code = {r["symbol"]: r["etype"] for r in alphabet.collect()}
    return features.order_only(ev, occ.episodes_frame(spark, [Episode((code["user"], code["assistant"]), (1,))])).select("seq_id", "n")


@query()
def class_models_embeddings(spark, d):
    ship(spark)
    emb = seq.table(spark, d, "embeddings")
    ev, _ = seq.encode_alphabet(seq.embedding_series(emb))
    labels = emb.select(F.col("vec_id").alias("seq_id"), F.col("label").cast("string").alias("label"))
    return features.select_per_class(ev, labels, Params(k=20)).select("cls", "ep_id", "size")


# ---- code lengths on plain numbers

query("SELECT DISTINCT CAST(l_quantity AS BIGINT) AS n, 2 * (length(bin(CAST(l_quantity AS BIGINT))) - 1) + 1 AS bits, length(bin(CAST(l_quantity AS BIGINT))) AS type_bits FROM lineitem WHERE l_quantity >= 1", "code_lengths")(
    lambda s, d: seq.table(s, d, "lineitem").where("l_quantity >= 1").select(F.col("l_quantity").cast("long").alias("n")).distinct().select("n", elias_bits(F.col("n")).alias("bits"), type_bits(F.col("n")).alias("type_bits"))
)


# ---- workloads; their seconds vary, so those columns are left out here and kept in bench.py


def _workloads() -> None:
    from . import workloads as w

    ratio = f"(SELECT 3 * count(DISTINCT etype) + count(*) FROM ev) / ({oracle.UNITS})"
    whole = {top: oracle.selection(conveyor_sql(top), ROUNDS) for top in seq.TOPOLOGY}
    query(whole["three"] + f" SELECT rank AS row_no, size, episode, n_occ, score, CAST({oracle.UNITS} AS BIGINT) AS units, {ratio} AS ratio FROM chosen", "entry_flagship")(w.flagship)
    lines = [f"SELECT * FROM ({sql} SELECT '{top}' AS data, (SELECT count(*) FROM ev) AS n_events, (SELECT 3 * count(DISTINCT etype) + count(*) FROM ev) AS trivial_units, CAST({oracle.UNITS} AS BIGINT) AS total_units, (SELECT count(*) FROM chosen) AS n_patterns, {ratio} AS ratio)" for top, sql in whole.items()]
    query(" UNION ALL ".join(lines), "tab_conv_units")(w.conveyor_units)
    for top in seq.TOPOLOGY:
        names = f", names AS (SELECT DISTINCT etype, sym FROM ev), spelt AS (SELECT rank, score, n_occ, unnest(list_transform(regexp_extract_all(episode, '(^|>)([0-9]+)', 2), lambda x: CAST(x AS INT))) AS etype, unnest(range(1, size + 1)) AS i FROM chosen)"
        sql = oracle.selection(conveyor_sql(top), ROUNDS, k=10) + names + " SELECT rank, score, n_occ, string_agg(sym, '>' ORDER BY i) AS pattern FROM spelt JOIN names USING (etype) GROUP BY ALL"
        query(sql, f"conv_{top}_top_patterns")(lambda s, d, top=top: w.conveyor_top_patterns(s, d, top))
        Q[f"conv_{top}_relevance"] = lambda s, d, top=top: w.conveyor_relevance(s, d, top)
        if top != "five":  # its baselines take minutes; call the function
            Q[f"tab_conv_{top}"] = lambda s, d, top=top: w.conveyor_table(s, d, top, chops=(25, 50, 100) if top == "two" else (50,))
    Q["tab_conv_time"] = lambda s, d: w.conveyor_table(s, d, "two", chops=(100,), seconds=True)
    for name in w.REAL:
        Q[f"tab_real_{name}"] = lambda s, d, name=name: w.real_table(s, d, (name,))
    Q["tab_real_time"] = lambda s, d: w.real_table(s, d, ("roles", "tags", "intervals"), seconds=True)
    Q["cost_vs_candidates"] = w.cost_vs_candidates
    pairs = f"WITH {conveyor_sql('two')}, {_PAIRS} SELECT 1 AS level, count(*) AS kinds FROM (SELECT etype FROM ev GROUP BY etype HAVING count(*) >= 0.02 * (SELECT count(*) FROM ev)) UNION ALL SELECT 2, count(*) FROM p WHERE n >= 0.02 * (SELECT count(*) FROM ev)"
    query(pairs, "explain_cost")(lambda s, d: w.explain_cost(coded(s, d, "two"), Params(fth=0.02)))
    Q["noise_control_5"] = lambda s, d: w.noise_control(s, d, 5)
    Q["noise_control_50"] = lambda s, d: w.noise_control(s, d, 50)
    Q["text_top20"] = w.text_top20
    Q["sweep_parameters"] = w.sweep
    Q["two_vs_greedy"] = lambda s, d: w.two_vs_greedy(s, d).drop("s_two_phase", "s_path_greedy")
    for name in ("embeddings", "convlab"):  # twenty repetitions of ten folds, features of all five sources
        Q[f"tab_accuracy_{name}"] = lambda s, d, name=name: w.accuracy(s, d, name)


_workloads()
