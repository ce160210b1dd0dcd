"""Stream operators against batch results, plan shapes, and registered queries against DuckDB."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from fixgap.model import Episode
from fixgap.operators import occ, table
from fixgap.params import Params
from fixgap.sources import sequence
from fixgap.streaming import operators as st

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    q.stop()
    return df.sparkSession.table(name)


@pytest.fixture(scope="module")
def stream_dir(spark, small, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("stream") / "events")
    spark.read.parquet(f"{small}/events.parquet").repartitionByRange(4, "ts").write.parquet(at)
    return at


def test_windowed_counts(spark, stream_dir):
    got = _run(st.counts(st.with_lateness(st.read_events(spark, stream_dir), "1 day"), "tumbling", "1 day"), "tumbling", "complete")
    batch = spark.read.parquet(stream_dir).groupBy(F.to_date("ts"), "event_type").count()
    assert got.agg(F.sum("n")).first()[0] == 1000 and got.count() == batch.count()
    for kind in ("sliding", "session"):
        assert _run(st.counts(st.with_lateness(st.read_events(spark, stream_dir), "1 day"), kind, "1 hour", "30 minutes"), kind, "complete").count() > 0


def test_dedup_and_symbols(spark, stream_dir):
    alphabet = spark.createDataFrame([(1, "click", 1), (2, "view", 1)], "etype int, symbol string, n long")
    got = _run(st.encode_symbols(st.dedup(st.with_lateness(st.read_events(spark, stream_dir), "30 days")), alphabet), "dedup")
    assert got.count() == spark.read.parquet(stream_dir).where("event_type in ('click', 'view')").dropDuplicates(["event_type", "ts"]).count()


def test_pairs(spark, stream_dir):
    got = _run(st.pair_join(st.with_lateness(st.read_events(spark, stream_dir), "40 days"), 86400, "click", "view"), "pairs")
    e = spark.read.parquet(stream_dir)
    want = e.where("event_type = 'click'").alias("a").join(e.where("event_type = 'view'").alias("b"), F.expr("a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 86400 SECONDS")).count()
    assert got.count() == want > 0


def test_matcher_equals_batch(spark, tmp_path):
    rows = [("k", e, 20 * k + o) for k in range(1, 30) for e, o in ((1, 0), (2, 2), (3, 5)) if (k + e) % 7]
    df = spark.createDataFrame(rows, "key string, etype int, t long")
    at = str(tmp_path / "m")
    df.where("t < 300").coalesce(1).write.parquet(at)
    df.where("t >= 300").coalesce(1).write.mode("append").parquet(at)
    eps = [Episode((1, 2, 3), (2, 3)), Episode((2, 3), (3,))]
    stream = spark.readStream.schema("key string, etype int, t long").option("maxFilesPerTrigger", 1).parquet(at)
    got = {(r.ep_id, r.start_t) for r in _run(st.match(stream, eps), "matcher").collect()}
    batch = occ.fixed(df.select(F.lit(0).cast("long").alias("seq_id"), "etype", "t"), occ.episodes_frame(spark, eps))
    assert got == {(r.ep_id, r.start_t) for r in batch.collect()}


def test_matcher_lets_idle_keys_go(spark, tmp_path):
    """Batches: key a begins; b moves the watermark far on, which ends a's state; a late row of a is dropped and counted."""
    at, cols = str(tmp_path / "m"), "key string, etype int, t long"
    batches = [[("a", 1, 100), ("a", 2, 102)], [("b", 1, 1000)], [("b", 2, 1002)], [("a", 2, 103), ("b", 1, 1010), ("b", 2, 1012)]]
    for rows in batches:
        spark.createDataFrame(rows, cols).coalesce(1).write.mode("append").parquet(at)
    stream = spark.readStream.schema(cols).option("maxFilesPerTrigger", 1).parquet(at)
    timed = st.with_lateness(stream.withColumn("at", F.timestamp_seconds("t")), "10 seconds", "at")
    out = st.match(timed, [Episode((1, 2), (2,))], time="at")
    q = out.writeStream.format("memory").queryName("expiring").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    late, held = st.late_rows(q), [s["numRowsTotal"] for p in q.recentProgress for s in p["stateOperators"]]
    q.stop()
    assert {(r.key, r.start_t) for r in spark.table("expiring").collect()} == {("a", 100), ("b", 1000), ("b", 1010)}
    assert late == 1 and held[0] == 1 and max(held) == 2 and held[-1] == 1  # a and b, then b alone


def test_refresh_over_a_stored_window(spark, tmp_path):
    ev = spark.createDataFrame([(e, 20 * k + o) for k in range(1, 31) for e, o in ((1, 0), (2, 2), (3, 5))], "etype int, t long")
    models, store = {}, str(tmp_path / "window")
    run = st.refresh(Params(), lambda i, rows: models.update({i: [r.types for r in rows]}), 320, store)
    for epoch in range(3):
        run(ev.where(f"t >= {20 + 200 * epoch} AND t < {220 + 200 * epoch}"), epoch)
    run(ev.where("t >= 420"), 2)  # a repeated epoch replaces its table
    left = spark.read.parquet(store)
    assert sorted(r.epoch for r in left.select("epoch").distinct().collect()) == [1, 2]
    assert left.count() == 60 and models == dict.fromkeys(range(3), [[1, 2, 3]])


def test_monitor_and_refresh(spark):
    ev = spark.createDataFrame([(e, 20 * k + o) for k in range(1, 30) for e, o in ((1, 0), (2, 2), (3, 5))], "etype int, t long")
    seen, models = [], []
    st.monitor(occ.episodes_frame(spark, [Episode((1, 2, 3), (2, 3))]), lambda i, r: seen.append(r), floor=2)(ev, 0)
    assert seen[0] == {"events": 87, "total_units": 6 + 29 + 1, "ratio": 96 / 36, "alarm": False}
    st.refresh(Params(), lambda i, rows: models.append(rows), 10_000)(ev, 0)
    assert [r.types for r in models[0]] == [[1, 2, 3]]


def _plan(df):
    return df._jdf.queryExecution().explainString(df._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_growth_plan(spark, small):
    ev, _ = sequence.encode_alphabet(sequence.conveyor_from_orders(sequence.table(spark, small, "orders"), "two"))
    lay = table.Layout(ev.select("etype", "t"), Params())
    front = lay.home.select(F.col("etype").alias("path"), "block", F.col("t").alias("start_t"), F.col("t").alias("end_t"))
    plan = _plan(table.step(lay, front, lay.home.select(F.col("etype").alias("path"), F.array("etype").alias("types")).distinct()))
    assert "NestedLoop" not in plan and "Cartesian" not in plan and "EvalPython" not in plan and "InPandas" not in plan and "InArrow" not in plan
    lay.drop()


def test_scans_are_pruned_and_filters_pushed(spark, small):
    plan = _plan(__spark_entry__.queries()["filter_eq_range"](spark, small))
    assert "PushedFilters: [" in plan and "o_orderstatus" in plan.split("PushedFilters")[1] and "o_orderpriority" not in plan


def test_interval_overlap_joins_by_size_too(spark, small):
    """Not by the few brands alone, with sizes compared pair by pair."""
    plan = _plan(__spark_entry__.queries()["join_interval_overlap"](spark, small))
    assert "Left keys [2]" in plan and "NestedLoop" not in plan


def _same(value):
    if value is None or (isinstance(value, float) and value != value):
        return "null"
    if isinstance(value, float):
        return str(int(value)) if value.is_integer() else repr(round(value, 6))
    return str(value)


def _rows(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(_same(r[i]) for i in order) for r in rows)


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return c


NAMES = [n for n in __spark_entry__.oracle_sql() if not n.startswith("op") and n != "pipeline"]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, small, duck, name):
    got, want = __spark_entry__.queries()[name](spark, small), duck.sql(__spark_entry__.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert _rows(got.columns, [tuple(r) for r in got.collect()]) == _rows(want.columns, want.fetchall())


def test_entry(spark):
    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 8 and all(r.ratio == rows[0].ratio > 4 for r in rows)
