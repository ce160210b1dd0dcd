"""The relational surface around the sequence methods: scans, sinks, filters, joins, aggregates, windows, functions.

Each entry is a Spark query and DuckDB SQL for the same rows. Where both engines read one text, it is written once.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import expr, udfs
from ..sources.shared import Scratch, ship

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}
TABLES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"]


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def both(name: str, sql: str, duck: str | None = None) -> None:
    """A query in SQL text: Spark runs it over views of the tables that it names."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        ship(spark)
        expr.register(spark)
        views = {x: t(spark, d, x) for x in TABLES if x in sql}
        return spark.sql(_braced(sql, views), **views)

    Q[name], O[name] = run, duck or sql


def _braced(sql: str, views: dict) -> str:
    import re

    return re.sub(r"(?<=\b(?:FROM|JOIN)\s)(" + "|".join(views) + r")\b", r"{\1}", sql) if views else sql


def entry(name: str, duck: str | None = None):
    def put(f):
        Q[name] = f
        if duck:
            O[name] = duck
        return f

    return put


# ---- scans and sinks

for _t, _cols in {"region": "*", "nation": "*", "customer": "*", "supplier": "*", "part": "*", "labels": "*", "benchmark": "*", "pages": "page_id, url", "conversations": "conv_id, turn, role", "documents": "doc_id, lang, source, n_chars", "embeddings": "vec_id, label", "events": "event_id, user_id, event_type, value", "orders": "o_orderkey, o_custkey, o_totalprice", "lineitem": "l_orderkey, l_partkey, l_quantity"}.items():
    both(f"scan_parquet_{_t}", f"SELECT {_cols} FROM {_t}")


def _round_trip(fmt: str, **options):
    def run(spark, d):
        at = f"{Scratch(spark).path}/{fmt}"
        t(spark, d, "nation").write.format(fmt).options(**options).save(at)
        return spark.read.schema("n_nationkey int, n_name string, n_regionkey int").format(fmt).options(**options).load(at)

    return run


for _fmt, _opt in {"csv": {"header": "true"}, "json": {}, "orc": {}}.items():
    entry(f"scan_{_fmt}", "SELECT * FROM nation")(_round_trip(_fmt, **_opt))


@entry("scan_text", "SELECT n_name AS value FROM nation")
def _(spark, d):
    at = f"{Scratch(spark).path}/text"
    t(spark, d, "nation").select("n_name").write.text(at)
    return spark.read.text(at)


@entry("scan_partitioned", "SELECT event_id, event_type FROM events WHERE event_type = 'click'")
def _(spark, d):
    at = f"{Scratch(spark).path}/part"
    t(spark, d, "events").select("event_id", "event_type").write.partitionBy("event_type").parquet(at)
    return spark.read.parquet(at).where("event_type = 'click'").select("event_id", "event_type")


# ---- projection and filter

both("project_columns", "SELECT o_orderkey, o_totalprice FROM orders")
both("project_expr", "SELECT l_orderkey, l_extendedprice * (1 - l_discount) AS net FROM lineitem")
both("project_star_except", "SELECT * EXCEPT (n_regionkey) FROM nation", "SELECT * EXCLUDE (n_regionkey) FROM nation")
both("project_case_when", "SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS kind FROM documents")
both("project_cast_ticks", "SELECT event_id, CAST(floor(unix_micros(CAST(ts AS TIMESTAMP)) / 60000000) AS BIGINT) AS tick FROM events", "SELECT event_id, CAST(floor(epoch_us(ts) / 60000000) AS BIGINT) AS tick FROM events")
both("filter_eq_range", "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F' AND o_totalprice BETWEEN 1000 AND 50000")
both("filter_in", "SELECT p_partkey FROM part WHERE p_size IN (1, 5, 9)")
both("filter_like_rlike", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND text RLIKE '[0-9]'", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND regexp_matches(text, '[0-9]')")
both("filter_null_safe", "SELECT doc_id FROM labels WHERE NOT (toxic <=> 1)", "SELECT doc_id FROM labels WHERE toxic IS DISTINCT FROM 1")
both("filter_between_time", "SELECT event_id FROM events WHERE ts >= TIMESTAMP_NTZ '2024-01-05 00:00:00' AND ts < TIMESTAMP_NTZ '2024-01-06 00:00:00'", "SELECT event_id FROM events WHERE ts >= TIMESTAMP '2024-01-05 00:00:00' AND ts < TIMESTAMP '2024-01-06 00:00:00'")
both("filter_useful", "SELECT p_size, count(*) AS f FROM part GROUP BY p_size HAVING episode_score(3, count(*)) > 0", "SELECT p_size, count(*) AS f FROM part GROUP BY p_size HAVING count(*) * 3 - (6 + count(*) + 1) > 0")
both("filter_array_exists", "SELECT vec_id FROM embeddings WHERE exists(embedding, x -> x > 0.3)", "SELECT vec_id FROM embeddings WHERE len(list_filter(embedding, lambda x: x > CAST(0.3 AS FLOAT))) > 0")

# ---- equi-joins

both("join_broadcast", "SELECT /*+ BROADCAST(n) */ c_custkey, n_name FROM customer JOIN nation n ON c_nationkey = n_nationkey")
both("join_sort_merge", "SELECT /*+ MERGE(o) */ l_linenumber, o_custkey FROM lineitem JOIN orders o ON l_orderkey = o_orderkey")
both("join_shuffle_hash", "SELECT /*+ SHUFFLE_HASH(c) */ o_orderkey, c_mktsegment FROM orders JOIN customer c ON o_custkey = c_custkey")
both("join_left", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
both("join_right", "SELECT d.lang, l.doc_id FROM documents d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
both("join_full", "SELECT c_custkey, o_orderkey FROM customer FULL JOIN orders ON c_custkey = o_custkey AND o_totalprice > 300000")
both("join_semi", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer SEMI JOIN orders ON c_custkey = o_custkey")
both("join_anti", "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer ANTI JOIN orders ON c_custkey = o_custkey")
both("join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
both("join_multiway_star", "SELECT r_name, count(*) AS n, sum(o_totalprice) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
both("join_null_safe", "SELECT a.doc_id FROM labels a JOIN labels b ON a.doc_id = b.doc_id AND a.toxic <=> b.quality", "SELECT a.doc_id FROM labels a JOIN labels b ON a.doc_id = b.doc_id AND a.toxic IS NOT DISTINCT FROM b.quality")

# ---- theta joins: a block or an exploded gap makes them equi-joins

_DAYS = "SELECT a.o_orderkey AS a, b.o_orderkey AS b FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate AND b.o_orderdate <= a.o_orderdate + INTERVAL 5 DAY"


def _orders_by_day(spark, d):
    return t(spark, d, "orders").select("o_orderkey", "o_custkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("day"))


@entry("join_gap_range", _DAYS)
def _(spark, d):
    o = _orders_by_day(spark, d).withColumn("cell", F.floor(F.col("day") / 5))
    a = o.select(F.col("o_orderkey").alias("a"), "o_custkey", F.col("day").alias("da"), F.explode(F.array("cell", F.col("cell") + 1)).alias("cell"))
    b = o.select(F.col("o_orderkey").alias("b"), "o_custkey", F.col("day").alias("db"), "cell")
    return a.join(b, ["o_custkey", "cell"]).where("db > da AND db <= da + 5").select("a", "b")


@entry("join_gap_exploded", _DAYS)
def _(spark, d):
    o = _orders_by_day(spark, d)
    a = o.select(F.col("o_orderkey").alias("a"), "o_custkey", F.explode(F.sequence(F.col("day") + 1, F.col("day") + 5)).alias("day"))
    return a.join(o.select(F.col("o_orderkey").alias("b"), "o_custkey", "day"), ["o_custkey", "day"]).select("a", "b")


@entry("join_interval_overlap", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND a.p_size <= b.p_size + 1 AND b.p_size <= a.p_size + 1")
def _(spark, d):
    """Sizes that differ by one at most: one side is dealt to its size and the next, so (brand, size) is the key and each pair meets once."""
    p = t(spark, d, "part").select("p_partkey", "p_brand", F.col("p_size").cast("long").alias("size"))
    x = p.select(F.col("p_partkey").alias("x"), "p_brand", F.posexplode(F.array("size", F.col("size") + 1)).alias("up", "size"))
    met = x.join(p.select(F.col("p_partkey").alias("y"), "p_brand", "size"), ["p_brand", "size"]).where("x < y OR (up = 1 AND x != y)")
    return met.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))


both("join_interval_contains", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_type = b.p_type AND a.p_brand = b.p_brand AND a.p_size < b.p_size AND a.p_retailprice > b.p_retailprice")


def _asof(forward: bool):
    def run(spark, d):
        e = t(spark, d, "events")
        clicks = e.where("event_type = 'click'").select("event_id", "user_id", "ts", F.lit(1).alias("mine"), F.lit(None).cast("timestamp_ntz").alias("other"))
        views = e.where("event_type = 'view'").select("event_id", "user_id", "ts", F.lit(0).alias("mine"), F.col("ts").alias("other"))
        w = Window.partitionBy("user_id").orderBy("ts")
        w = w.rangeBetween(0, Window.unboundedFollowing) if forward else w.rangeBetween(Window.unboundedPreceding, 0)
        found = F.min("other").over(w) if forward else F.max("other").over(w)
        return clicks.unionByName(views).withColumn("found", found).where("mine = 1").select("event_id", "found")

    return run


for _way, _agg, _op in (("backward", "max", "<="), ("forward", "min", ">=")):
    entry(f"join_asof_{_way}", f"SELECT event_id, (SELECT {_agg}(ts) FROM events v WHERE v.event_type = 'view' AND v.user_id = c.user_id AND v.ts {_op} c.ts) AS found FROM events c WHERE event_type = 'click'")(_asof(_way == "forward"))
both("join_nested_loop_small", "SELECT r_name, n_name FROM region JOIN nation ON r_regionkey < n_regionkey")
both("join_cross_small", "SELECT r_name, n_name FROM region CROSS JOIN nation")
both("join_lateral", "SELECT r_name, x.n FROM region, LATERAL (SELECT count(*) AS n FROM nation WHERE n_regionkey = r_regionkey) x")

# ---- aggregates

both("agg_hash", "SELECT o_orderpriority, count(*) AS n, sum(o_totalprice) AS total FROM orders GROUP BY o_orderpriority")
both("agg_sort", "SELECT n_regionkey, max(n_name) AS last_name FROM nation GROUP BY n_regionkey")
both("agg_two_phase", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, avg(l_extendedprice) AS p, count(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("agg_count_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS n FROM orders GROUP BY o_orderstatus")
both("agg_multi_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
both("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
both("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
both("agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
both("agg_filter_clause", "SELECT lang, count(*) FILTER (WHERE n_chars > 1000) AS n FROM documents GROUP BY lang")
both("agg_having_frequency", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type HAVING count(*) >= 0.1 * (SELECT count(*) FROM events)")
both("agg_pivot", "SELECT lang, coalesce(bad, 0L) AS bad, coalesce(good, 0L) AS good FROM (SELECT lang, quality, l.doc_id AS id FROM documents d JOIN labels l ON d.doc_id = l.doc_id) PIVOT (count(id) FOR quality IN (0 AS bad, 1 AS good))", "SELECT lang, count(l.doc_id) FILTER (WHERE quality = 0) AS bad, count(l.doc_id) FILTER (WHERE quality = 1) AS good FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY lang")
both("agg_collect_sorted", "SELECT n_regionkey, array_join(sort_array(collect_list(n_name)), ',') AS names FROM nation GROUP BY n_regionkey", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
both("agg_max_by", "SELECT n_regionkey, max_by(n_name, n_nationkey) AS last, min_by(n_name, n_nationkey) AS first FROM nation GROUP BY n_regionkey")
both("agg_stddev_corr", "SELECT round(stddev_samp(l_quantity), 6) AS s, round(corr(l_quantity, l_extendedprice), 6) AS c FROM lineitem")
both("agg_percentile", "SELECT o_orderpriority, percentile(o_totalprice, 0.5) AS m FROM orders GROUP BY o_orderpriority", "SELECT o_orderpriority, quantile_cont(o_totalprice, 0.5) AS m FROM orders GROUP BY o_orderpriority")
both("agg_bool", "SELECT lang, bool_and(n_chars > 10) AS a, bool_or(n_chars > 10000) AS o FROM documents GROUP BY lang")
both("agg_histogram_gap", "SELECT g, count(*) AS n FROM (SELECT datediff(CAST(l_shipdate AS DATE), CAST(o_orderdate AS DATE)) AS g FROM lineitem JOIN orders ON l_orderkey = o_orderkey) GROUP BY g", "SELECT g, count(*) AS n FROM (SELECT date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS g FROM lineitem JOIN orders ON l_orderkey = o_orderkey) GROUP BY g")
entry("agg_approx_distinct")(lambda s, d: t(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("n")))
entry("agg_approx_percentile")(lambda s, d: t(s, d, "lineitem").agg(F.percentile_approx("l_quantity", 0.5).alias("m")))

# ---- windows

for _name, _call in {"row_number": "row_number()", "rank": "rank()", "dense_rank": "dense_rank()", "ntile": "ntile(4)", "percent_rank": "percent_rank()", "cume_dist": "cume_dist()"}.items():
    both(f"win_{_name}", f"SELECT c_custkey, {_call} OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS w FROM customer")
both("win_lag_lead", "SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts) AS before, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts) AS after FROM events")
both("win_first_last_nth", "SELECT c_custkey, first_value(c_custkey) OVER w AS f, last_value(c_custkey) OVER w AS l, nth_value(c_custkey, 2) OVER w AS s FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("win_running_sum", "SELECT o_orderkey, CAST(sum(1) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS n FROM orders")
both("win_rows_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS n FROM events")
both("win_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS n FROM part")
both("win_running_min", "SELECT c_custkey, min(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS UNBOUNDED PRECEDING) AS m FROM customer")
both("win_best_extension", "SELECT p_brand, p_type, n FROM (SELECT p_brand, p_type, count(*) AS n, row_number() OVER (PARTITION BY p_brand ORDER BY count(*) DESC, p_type) AS r FROM part GROUP BY p_brand, p_type) WHERE r = 1")
both("win_sessionise", "SELECT event_id, CAST(sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS BIGINT) AS session FROM (SELECT event_id, user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL OR ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS s FROM events)")

# ---- sort, limit, set operations, subqueries

both("sort_multi_nulls", "SELECT doc_id, toxic FROM labels ORDER BY toxic DESC NULLS LAST, doc_id")
both("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 20")
both("topk_score", "SELECT p_brand, count(*) * 2 - (4 + count(*) + 1) AS score FROM part GROUP BY p_brand ORDER BY score DESC, p_brand LIMIT 5")
both("topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
both("set_union_all", "SELECT n_nationkey AS k FROM nation UNION ALL SELECT r_regionkey FROM region")
both("set_union_distinct", "SELECT n_regionkey AS k FROM nation UNION SELECT r_regionkey FROM region")
both("set_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer")
both("set_intersect_all", "SELECT n_regionkey AS k FROM nation INTERSECT ALL SELECT r_regionkey FROM region")
both("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
both("set_except_all", "SELECT n_regionkey AS k FROM nation EXCEPT ALL SELECT r_regionkey FROM region")
entry("set_union_by_name", "SELECT n_nationkey AS k, n_name AS s FROM nation UNION ALL SELECT r_regionkey, r_name FROM region")(lambda s, d: t(s, d, "nation").selectExpr("n_nationkey k", "n_name s").unionByName(t(s, d, "region").selectExpr("r_name s", "r_regionkey k")))
both("scalar_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
both("exists_subquery", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 200000)")
both("not_exists_subquery", "SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
both("in_subquery", "SELECT n_name FROM nation WHERE n_regionkey IN (SELECT r_regionkey FROM region WHERE r_name LIKE 'A%')")
both("correlated_agg", "SELECT o_orderkey FROM orders o WHERE o_totalprice >= (SELECT max(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
both("cte_chain", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT n, count(*) AS m FROM a GROUP BY n) SELECT n, m FROM b")
both("recursive_cte", "WITH RECURSIVE r(n) AS (SELECT 1 UNION ALL SELECT n + 1 FROM r WHERE n < 20) SELECT n FROM r")

# ---- functions

both("fn_string", "SELECT n_name, lower(n_name) AS l, upper(n_name) AS u, substring(n_name, 2, 3) AS s, concat_ws('-', n_name, n_name) AS c, trim(n_name) AS t, lpad(n_name, 20, '*') AS p, levenshtein(n_name, 'ALGERIA') AS d, translate(n_name, 'AE', 'ae') AS x, instr(n_name, 'A') AS i FROM nation")
both("fn_regexp", "SELECT page_id, regexp_extract(url, '([a-z]+)', 1) AS e, regexp_replace(url, '[0-9]+', '#') AS r, regexp_count(url, '/') AS n FROM pages", "SELECT page_id, regexp_extract(url, '([a-z]+)', 1) AS e, regexp_replace(url, '[0-9]+', '#', 'g') AS r, CAST(len(regexp_extract_all(url, '/')) AS INT) AS n FROM pages")
both("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofmonth(o_orderdate) AS d, CAST(last_day(CAST(o_orderdate AS DATE)) AS STRING) AS l, CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS STRING) AS t FROM orders")
both("fn_math", "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS f, CAST(ceil(p_retailprice) AS BIGINT) AS c, round(sqrt(p_size), 6) AS s, greatest(p_size, 10) AS g, least(p_size, 10) AS l, p_size & 3 AS b FROM part")
both("fn_floor_log2", "SELECT p_partkey, length(bin(p_partkey)) - 1 AS l FROM part WHERE p_partkey > 0")
both("fn_array", "SELECT vec_id, size(embedding) AS n, slice(embedding, 1, 2)[0] AS first, size(array_distinct(embedding)) AS kinds FROM embeddings", "SELECT vec_id, CAST(len(embedding) AS INT) AS n, embedding[1] AS first, CAST(len(list_distinct(embedding)) AS INT) AS kinds FROM embeddings")
both("fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
both("fn_map", "SELECT n_regionkey, map_from_entries(sort_array(collect_list(struct(n_nationkey, n_name))))[min(n_nationkey)] AS first FROM nation GROUP BY n_regionkey", "SELECT n_regionkey, min_by(n_name, n_nationkey) AS first FROM nation GROUP BY n_regionkey")
both("fn_struct", "SELECT n_nationkey, named_struct('k', n_regionkey, 's', n_name).s AS s FROM nation", "SELECT n_nationkey, n_name AS s FROM nation")
both("fn_higher_order", "SELECT vec_id, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * x), CAST(0 AS DOUBLE), (a, x) -> a + x), 4) AS norm FROM embeddings", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm FROM embeddings")
both("fn_posexplode", "SELECT vec_id, p, x FROM (SELECT vec_id, posexplode(embedding) AS (p, x) FROM embeddings)", "SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS INT) AS p, unnest(embedding) AS x FROM embeddings")
both("fn_sql_functions", "SELECT p_partkey, episode_score(3, p_size) AS s, min_useful_freq(p_size + 1) AS f, elias_bits(p_partkey + 1) AS e, type_bits(p_partkey + 1) AS t FROM part", "SELECT p_partkey, p_size * 3 - (6 + p_size + 1) AS s, CAST(floor((2 * (p_size + 1) + 1) / p_size) AS BIGINT) + 1 AS f, 2 * (length(bin(p_partkey + 1)) - 1) + 1 AS e, length(bin(p_partkey + 1)) AS t FROM part WHERE p_size > 0")


@entry("udf_episode_label", "SELECT n_nationkey, concat(n_nationkey, '+', 2, '>', n_regionkey) AS label FROM nation")
def _(spark, d):
    ship(spark)
    return t(spark, d, "nation").select("n_nationkey", udfs.episode_label(F.array("n_nationkey", "n_regionkey"), F.array(F.lit(2))).alias("label"))


@entry("udf_elias_arrow", "SELECT p_partkey, CAST(2 * (length(bin(p_partkey + 1)) - 1) + 1 AS INT) AS bits FROM part")
def _(spark, d):
    ship(spark)
    return t(spark, d, "part").select("p_partkey", udfs.elias_bits_vec(F.col("p_partkey") + 1).alias("bits"))


@entry("udtf_roll_out", "SELECT CAST(10 AS INT) AS etype, CAST(s AS BIGINT) AS t FROM (VALUES (1), (5)) v(s) UNION ALL SELECT 20, CAST(s + 3 AS BIGINT) FROM (VALUES (1), (5)) v(s)")
def _(spark, d):
    ship(spark)
    spark.udtf.register("roll_out_events", udfs.RollOut)
    return spark.sql("SELECT * FROM roll_out_events(array(10, 20), array(3), array(1L, 5L))")


@entry("scan_encoded_stream", "SELECT CAST(n_nationkey + 1 AS INT) AS etype, CAST(n_nationkey + 1 AS BIGINT) AS t FROM nation")
def _(spark, d):
    """Integers written as text lines, read by a Python data source, decoded."""
    from ..operators import encoding
    from ..sources.integer_stream import register, write

    ship(spark)
    register(spark)
    ev = t(spark, d, "nation").select((F.col("n_nationkey") + 1).alias("etype"), (F.col("n_nationkey") + 1).cast("long").alias("t"))
    at = f"{Scratch(spark).path}/stream"
    write(encoding.trivial(ev), at)
    return encoding.decode(encoding.from_stream(spark.read.format("integer_stream").load(at)))
