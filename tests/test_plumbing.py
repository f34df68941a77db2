"""Sources, sinks, stored sketches, plans, streams and the driver's contract."""

import shutil

import pytest
from pyspark.sql import functions as F

from mixedsketch import store
from mixedsketch.operators import cm, composite, exact, ladder
from mixedsketch.plans import inspect
from mixedsketch.sources import streams
from mixedsketch.sources.streams import STREAMS, load
from mixedsketch.spec import TEST
from mixedsketch.streaming import queries as live


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, "a", 0.5), (2, None, 1.5)], "id bigint, s string, v double")
    streams.write(df, str(tmp_path / "t"), fmt)
    got = streams.read(spark, str(tmp_path / "t"), fmt, "id bigint, s string, v double")
    assert sorted(got.collect()) == sorted(df.collect())


def test_scan_reads_only_its_columns(spark, data):
    plan = cm.build(STREAMS["S3"](spark, data), TEST)
    assert inspect.scan_columns(plan) == [{"l_partkey"}]
    early = load(spark, data, "events").filter("event_id < 100").select("user_id")
    assert "event_id" in inspect.pushed_filters(early)[0]


def test_keys_are_summed_before_cells(spark, data):
    text = inspect.plan_text(cm.build(STREAMS["S3"](spark, data), TEST))
    assert text.index("Generate explode") < text.rindex("HashAggregate(keys=[key") and not inspect.operators(ladder.wide(STREAMS["S3"](spark, data), TEST))["MapInArrow"]


def test_store_replaces_batches_and_keeps_specs_apart(spark, data, tmp_path):
    s = STREAMS["S1"](spark, data)
    a, b = s.filter("seq < 500"), s.filter("seq >= 500")
    root = str(tmp_path)
    for i, part in enumerate((a, b, b)):
        store.save(cm.build(part, TEST, "parts"), root, TEST, min(i, 1))  # batch 1 is written twice
    store.save(cm.build(a, TEST.but(K=16), "parts"), root, TEST.but(K=16), 0)
    got = {tuple(r) for r in store.load(spark, root, TEST).select("part", "row", "col", "cnt").collect()}
    assert got == {tuple(r) for r in cm.build(s, TEST, "parts").select("part", "row", "col", "cnt").collect()}
    assert store.load(spark, root, TEST, until=0).filter("row = 0").agg(F.sum("cnt")).first()[0] == 500
    with pytest.raises(ValueError):
        store.merge_checked((TEST, None), (TEST.but(K=16), None))


@pytest.fixture()
def files(spark, data, tmp_path):
    """The events in four files, in order."""
    folder = str(tmp_path / "events")
    e = load(spark, data, "events")
    for i in range(4):
        e.filter(f"event_id >= {i * 250} AND event_id < {(i + 1) * 250}").coalesce(1).write.mode("append").parquet(folder)
    yield folder
    shutil.rmtree(folder)


def test_live_composite_over_batches(spark, data, files, tmp_path):
    events = live.keyed(streams.stream(spark, files, "events"))
    rows = live.run_available(live.live_composite(events, TEST), "live_parts", str(tmp_path / "cp"), "update")
    assert rows.count() >= 8  # several micro-batches
    newest = composite.latest(rows)
    assert newest.agg(F.sum("f1")).first()[0] == 1000
    assert newest.filter("v_begin <> v_end").isEmpty()
    batch = composite.drain(__import__("mixedsketch.operators.buffers", fromlist=["x"]).replay(STREAMS["S1"](spark, data), TEST), TEST)
    want = {r["part"]: [float(v) for v in r["f2rows"]] for r in batch.collect()}
    got = {r["part"]: r["f2rows"] for r in newest.collect()}
    assert all(got[p] == pytest.approx(v) for p, v in want.items())


def test_windowed_cells_into_a_store(spark, data, files, tmp_path):
    events = live.keyed(streams.stream(spark, files, "events"))
    query = live.to_store(live.window_cells(events, TEST, "1 day", "0 seconds"), str(tmp_path / "store"), TEST, str(tmp_path / "cp2"))
    query.awaitTermination()
    stored = store.load(spark, str(tmp_path / "store"), TEST).filter("row = 0").agg(F.sum("cnt")).first()[0]
    last_day = load(spark, data, "events").agg(F.max(F.to_date("ts"))).first()[0]
    closed = load(spark, data, "events").filter(F.to_date("ts") < F.lit(last_day)).count()
    assert stored == closed


def test_window_f2_alarm_and_sessions(spark, data, files, tmp_path):
    events = live.keyed(streams.stream(spark, files, "events"))
    cells = live.run_available(live.window_cells(events, TEST), "cells_by_day", str(tmp_path / "a"), "complete")
    assert live.window_f2(cells).filter("f2 < f1 OR alarm > 1").isEmpty()
    kept = live.run_available(live.deduplicated(live.keyed(streams.stream(spark, files, "events", 4))), "deduplicated", str(tmp_path / "b"), "append")
    assert kept.count() == 1000
    s = live.run_available(live.sessions(live.keyed(streams.stream(spark, files, "events", 4))), "sessions", str(tmp_path / "c"), "complete")
    assert s.agg(F.sum("n")).first()[0] == 1000


def test_report_function(spark):
    live.report_udtf(spark)
    rows = spark.sql("SELECT * FROM f2_report(16)").collect()
    assert len(rows) == 3 and rows[0]["k"] == 1024


def test_contract(spark):
    import __spark_entry__ as entry

    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 80
    assert entry.entry(spark).count() == 12


@pytest.mark.parametrize("name", ["cm_cells", "ladder_report", "buffer_chunks", "f2_projected", "versioned_f2_whole", "unsynced_f2_whole", "ivl_f2", "monotone_matrix", "replay_conserved", "join_asof", "stream_cm_window", "stream_panes", "stream_sliding_f2", "stream_composite_conserved", "stored_state_conserved"])
def test_twins_agree(spark, data, name):
    """The driver compares all of them; a few are held here."""
    import glob
    import os

    import duckdb

    import __spark_entry__ as entry

    con = duckdb.connect()
    for p in glob.glob(f"{data}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    want = con.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, data)
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    a = sorted([str(tuple(r[c] for c in columns)) for r in got.collect()])
    b = sorted([str(r) for r in want.select(*columns).fetchall()])
    assert a == b


def test_moments_of_tokens_match_counts(spark, data):
    s = STREAMS["S7"](spark, data)
    assert exact.moments(s).first()["f1"] == s.count() == exact.moment(s, 1).first()[0]


def test_names_join_a_stream_and_state_is_readable(spark, data, files, tmp_path):
    events = streams.stream(spark, files, "events", 4).select("event_id", "user_id")
    names = spark.range(100).select(F.col("id").alias("user_id"), F.concat(F.lit("u"), F.col("id").cast("string")).alias("name"))
    named = live.run_available(live.with_names(events, names, "user_id"), "named", str(tmp_path / "n"), "append")
    assert named.count() == 1000 and named.filter("user_id < 100 AND name IS NULL").isEmpty()
    counts = live.window_f1(live.keyed(streams.stream(spark, files, "events", 4)))
    live.run_available(counts, "counts", str(tmp_path / "s"), "complete")
    assert store.read_state(spark, str(tmp_path / "s")).count() == counts.sparkSession.table("counts").count()


def test_matrix_as_an_aggregate(spark, data):
    from mixedsketch.functions.aggregates import cm_agg

    s = STREAMS["S2"](spark, data)
    got = s.agg(cm_agg(TEST)("key", "weight").alias("m")).first()["m"]
    want = {(r["row"], r["col"]): r["cnt"] for r in cm.build(s, TEST).collect()}
    assert {(i // TEST.K, i % TEST.K): c for i, c in enumerate(got) if c} == want


def test_live_state_is_read_from_its_checkpoint(spark, data, files, tmp_path):
    """Four batches, state carried in declared columns: it equals the replay of the whole stream, buffers included."""
    from mixedsketch.operators import buffers

    spec = TEST.but(B=20, C=3)  # many hand-overs, and keys that swap
    events = live.keyed(streams.stream(spark, files, "events"))
    live.run_available(live.live_composite(events, spec), "live_stored", str(tmp_path / "cp"), "update")
    state, open_ = live.stored_live_state(spark, str(tmp_path / "cp"))
    handoffs = buffers.replay(STREAMS["S1"](spark, data), spec)
    want = composite.drain(handoffs, spec)
    same = ["part", "cells", "slots", "f2rows", "updates", "hits", "inserts", "misses", "swaps"]
    assert want.agg(F.sum("swaps")).first()[0] > 0
    assert sorted(map(str, state.filter("updates > 0").select(*same).collect())) == sorted(map(str, want.select(*same).collect()))
    lanes = ["owner", "producer", "key", "cnt"]
    assert sorted(open_.select(*lanes).collect()) == sorted(handoffs.filter("NOT handed").select(*lanes).collect())


def test_every_batch_commits_beside_readers(spark, files, tmp_path):
    """A reader that never stops asking holds no batch up, and always finds parts whose versions agree."""
    import os
    import time

    events = live.keyed(streams.stream(spark, files, "events"))
    query = live.live_composite(events, TEST).writeStream.format("memory").queryName("progress").outputMode("update").option("checkpointLocation", str(tmp_path / "p")).trigger(availableNow=True).start()
    until, seen = time.time() + 120, []
    while query.isActive and time.time() < until:
        seen.append(composite.latest(spark.table("progress")).agg(F.coalesce(F.sum("f1"), F.lit(0))).first()[0])
    query.awaitTermination(60)
    assert query.exception() is None and not query.isActive
    assert {n for n in os.listdir(tmp_path / "p" / "commits") if n.isdigit()} == {"0", "1", "2", "3"}
    assert seen == sorted(seen)
    assert composite.latest(spark.table("progress")).agg(F.sum("f1")).first()[0] == 1000


def test_a_torn_part_is_refused(spark, data, tmp_path):
    from mixedsketch.operators import buffers

    handoffs = buffers.replay(STREAMS["S1"](spark, data), TEST)
    state = composite.drain(handoffs, TEST)
    store.save_state(state, handoffs, str(tmp_path), TEST, 0)
    assert store.load_state(spark, str(tmp_path), TEST, 0)[0].count() == state.count()
    store.save_state(state.withColumn("v_begin", F.col("v_begin") + 1), handoffs, str(tmp_path), TEST, 1)
    with pytest.raises(ValueError):
        store.load_state(spark, str(tmp_path), TEST, 1)


def test_late_rows_are_counted(spark, tmp_path):
    import time

    folder = str(tmp_path / "late")
    schema = streams.SCHEMAS["events"]
    for i, days in enumerate(([1, 1, 2], [9, 9], [1, 9], [20])):  # the third file has one row that is days too late
        rows = spark.createDataFrame([(10 * i + j, f"2024-01-{day:02d} 12:00:00") for j, day in enumerate(days)], "event_id bigint, ts string")
        rows = rows.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.lit(1).cast("bigint").alias("user_id"))
        full = spark.createDataFrame([], schema)
        rows = full.unionByName(rows.withColumn("ts", F.col("ts").cast("timestamp_ntz")), allowMissingColumns=True)
        rows.coalesce(1).write.mode("append").parquet(folder)
    late = live.LateRows()
    spark.streams.addListener(late)
    try:
        out = live.run_available(live.window_f1(live.keyed(streams.stream(spark, folder, "events")), late="1 hour"), "late_rows", str(tmp_path / "cp"), "append")
        until = time.time() + 20
        while not late.dropped.get("late_rows") and time.time() < until:
            time.sleep(0.2)
    finally:
        spark.streams.removeListener(late)
    assert late.dropped["late_rows"] == 1
    assert {r["start"].day: r["f1"] for r in out.collect()}.get(1) == 2


def test_rate_source_and_timed_trigger(spark, tmp_path):
    """A synthetic source, the console, and a trigger by time."""
    import time

    rate = spark.readStream.format("rate").option("rowsPerSecond", 200).load().select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), F.pmod("value", F.lit(7)).alias("user_id"))
    query = live.start(live.window_f1(live.keyed(rate), "10 seconds"), "memory", "complete", str(tmp_path / "r"), "500 milliseconds", queryName="rated")
    shown = live.start(live.keyed(rate), "console", "append", str(tmp_path / "c"), "1 second", numRows=1)
    until = time.time() + 60
    while time.time() < until and not spark.table("rated").agg(F.sum("f1")).first()[0]:
        time.sleep(0.3)
    for q in (query, shown):
        q.stop()
        assert q.exception() is None
    assert spark.table("rated").agg(F.sum("f1")).first()[0] > 0


def test_view_of_streams_reads_the_asked_one(spark, data):
    live.f2_view(spark, data, TEST, ["S1", "S2", "S3"])
    df = spark.sql("SELECT * FROM f2_of_streams WHERE stream = 'S2'")
    assert {c for s in inspect.scan_columns(df) for c in s} <= {"event_id", "event_type"}
    row = df.first()
    assert row["exact"] == exact.moments(STREAMS["S2"](spark, data)).first()["f2"] <= row["f2"]
