"""Queries that could stop early see the whole table."""

import glob
import os

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from mixedsketch import workloads
from mixedsketch.operators import baselines, ladder
from mixedsketch.sources.streams import STREAMS
from mixedsketch.spec import TEST


def twin(spark, d, name):
    import duckdb

    con = duckdb.connect()
    for p in glob.glob(f"{d}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    want, got = con.sql(entry.oracle_sql()[name]), entry.queries()[name](spark, d)
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = [r.asDict() for r in got.collect()]
    assert sorted(str(tuple(r[c] for c in columns)) for r in rows) == sorted(str(r) for r in want.select(*columns).fetchall())
    return rows


MOMENTS = ["concurrent_f2_whole", "versioned_f2_whole", "unsynced_missed_whole", "join_interval_whole"]


@pytest.mark.parametrize("name", MOMENTS)
def test_whole_stream_twins_agree(spark, data, name):
    assert twin(spark, data, name)


def test_scans_reach_the_end_of_the_stream(spark):
    """The last scan sees all rows."""
    d = "/root/testdata/sf0.01"
    last = spark.read.parquet(f"{d}/events.parquet").agg({"event_id": "max"}).first()[0]
    rows = entry.queries()["concurrent_f2_whole"](spark, d).collect()
    got = {r["kind"]: r["f2"] for r in rows if r["scan"] == 4}
    s = STREAMS["S1"](spark, d)
    assert got == {"wide": int(ladder.wide(s, TEST).first()[0]), "part_cm": int(ladder.part_cm(s, TEST).first()[0]), "part_slots": int(ladder.part_slots(s, TEST).first()[0])}
    assert {r["scan"] for r in rows} == {1, 2, 3, 4}
    assert max(r["t"] for r in entry.queries()["versioned_f2_whole"](spark, d).collect()) >= last
    assert entry.queries()["join_interval_whole"](spark, d).agg({"n": "sum"}).first()[0] >= last


@pytest.mark.parametrize("name", ["cm_point_all", "settled_point_all", "point_error_all"])
def test_every_key_is_asked(spark, data, name):
    rows = twin(spark, data, name)
    keys = STREAMS["S3"](spark, data).select("key").distinct()
    absent = spark.range(50).select((F.col("id") * 7919 + 13).alias("key"))
    n = keys.union(absent).distinct().count()
    assert n == (sum(r["n"] for r in rows) if name == "point_error_all" else len(rows))
    if name == "cm_point_all":
        assert {r["key"] for r in rows if r["exact"]} == {r["key"] for r in keys.collect()}


def test_accuracy_of_every_key(spark, data):
    """w8 asked 100 heavy and 100 arbitrary keys of a stream."""
    n = STREAMS["S3"](spark, data).select("key").distinct().count()
    rows = workloads.point_accuracy(spark, data).filter("stream = 'S3' AND method = 'matrix'").collect()
    assert sum(r["n"] for r in rows if r["kind"] != "absent") == n


def test_builtin_answers_every_key(spark, data):
    keys = {r["key"] for r in STREAMS["S3"](spark, data).select("key").distinct().collect()}
    got = {r["key"]: r["builtin"] for r in workloads.baseline_point(spark, data).collect()}
    assert set(got) == keys
    some = sorted(keys)[-30:]
    assert [got[k] for k in some] == baselines.builtin_point(STREAMS["S3"](spark, data), some)
