"""Ordered passes over blocks of updates, which the experiments run on."""

import pytest
from pyspark.sql import functions as F

from mixedsketch import workloads
from mixedsketch.operators import blocks, buffers, composite
from mixedsketch.sources import streams
from mixedsketch.sources.streams import STREAMS
from mixedsketch.spec import TEST
from mixedsketch.workspace import Workspace


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def weighted_stream(spark, data):
    """Users with weights that differ, and some updates that share a seq."""
    s = STREAMS["S1"](spark, data)
    return s.select((F.col("seq") - F.when(F.pmod("seq", F.lit(7)) == 0, 4).otherwise(0)).alias("seq"), "key", (1 + F.pmod("key", F.lit(3))).alias("weight"))


def kept(spark, df, tmp_path):
    df.write.parquet(f"{tmp_path}/kept")
    return spark.read.parquet(f"{tmp_path}/kept")


@pytest.mark.parametrize("spec", [TEST, TEST.but(P=1, B=None), TEST.but(P=3, B=5, self_buffer=False), TEST.but(P=2, C=3, hash_family="xxhash64", producer="contiguous"), TEST.but(C=80, B=300)], ids=str)
def test_one_pass_equals_both_stages(spark, data, tmp_path, spec):
    s = STREAMS["S1"](spark, data).select("seq", "key", "weight")
    packed = kept(spark, blocks.pack(s), tmp_path)
    handoffs = buffers.replay(s, spec)
    state = composite.run(packed, spec, kinds="both").cache()
    for kind, twin in (("buffered", composite.drain(handoffs, spec)), ("NOT buffered", composite.replay_slots(s, spec))):
        got = [r for r in rows(state.filter(kind).select(*twin.columns)) if r[twin.columns.index("updates")]]  # owners with nothing but open buffers have a row, too
        assert got == rows(twin)
    left = composite.still_open(state)
    assert rows(left) == rows(handoffs.filter("NOT handed").select(*left.columns))
    assert composite.f1(state.filter("buffered")).first()["f1"] == s.agg(F.sum("weight")).first()[0]


def test_blocks_keep_every_update_in_order(spark, data, tmp_path):
    s = weighted_stream(spark, data)
    packed = kept(spark, blocks.pack(s), tmp_path)
    assert packed.agg(F.sum("n")).first()[0] == s.count()
    state, plain = composite.run(packed, TEST, kinds="direct"), composite.replay_slots(s, TEST)
    asked = ["part", "cells", "slots", "f2rows", "hits", "swaps"]
    assert rows(state.select(*asked)) == rows(plain.select(*asked))
    last = s.agg(F.max("seq")).first()[0] // 3
    for bounds, part in (({"until": last}, s.filter(F.col("seq") <= last)), ({"after": last}, s.filter(F.col("seq") > last))):
        assert rows(composite.run(packed, TEST, kinds="direct", **bounds).select(*asked)) == rows(composite.replay_slots(part, TEST).select(*asked))


def test_numbers_and_flushes_and_arrivals(spark, data, tmp_path):
    s = weighted_stream(spark, data).withColumn("weight", F.lit(1))
    packed = kept(spark, blocks.numbered(kept(spark, blocks.pack(s), tmp_path / "a")), tmp_path / "b")
    n = s.count()
    assert packed.agg(F.min("lo")).first()[0] == 0 and packed.agg(F.max("hi")).first()[0] == n - 1
    order = sorted((r["seq"], r["key"]) for r in s.select("seq", "key").collect())
    again = spark.createDataFrame([(i, k) for i, (_, k) in enumerate(order)], "seq bigint, key bigint")
    chunks = buffers.chunks(again, TEST).filter("handed").groupBy(F.col("owner").alias("part"), "producer", "flush_seq", "key").agg(F.count("*").alias("v"))
    assert rows(blocks.flushes(packed, TEST)) == rows(chunks)
    moments = [10, 11, n // 2, n - 5]
    got = {tuple(r) for r in blocks.arrivals(packed, moments).groupBy("key", "moment").agg(F.sum("n")).collect()}
    want = {}
    for i, (_, k) in enumerate(order[: n - 4]):
        m = next(j for j, at in enumerate(moments) if i <= at)
        want[k, m] = want.get((k, m), 0) + 1
    assert got == {(k, m, v) for (k, m), v in want.items()}


def test_empty_stream(spark, data, tmp_path):
    s = STREAMS["S1"](spark, data).select("seq", "key", "weight").limit(0)
    packed = kept(spark, blocks.pack(s), tmp_path)
    assert packed.count() == 0 and composite.run(packed, TEST).count() == 0 and blocks.flushes(packed, TEST).count() == 0


def forbidden(*args, **more):
    raise AssertionError("hand-overs are written and put in order")


def test_throughput_is_one_pass(spark, data, monkeypatch):
    monkeypatch.setattr(buffers, "replay", forbidden)
    got = workloads.throughput(spark, data, "S8", 1.5, (2,)).collect()
    n = STREAMS["S8"](spark, data).count()
    assert {(r["design"], r["load"]) for r in got} == {(d, o) for d in workloads.DESIGNS for o in ("none", "queries")}
    assert all(r["rows"] == n and r["seconds"] > 0 and (r["rounds"] > 0) == (r["load"] == "queries") for r in got)


def test_queries_read_what_the_update_kept(spark, data):
    work = Workspace(spark, "t")
    s, packed = workloads._kept(STREAMS["S1"](spark, data), work)
    for design in workloads.DESIGNS:
        workloads._update(design, s, packed, TEST, work)
        asked = workloads._queries(design, TEST, work, s.select("key").distinct())
        assert asked["point"]() == s.select("key").distinct().count()
        if "f1" in asked:
            assert asked["f1"]()[0][0] == s.count()
    work.drop()


def test_errors_with_buffers_are_one_pass(spark, data, monkeypatch):
    """The errors of both stages, without hand-overs being written."""
    n, spec = 5_000, workloads.scaled(workloads.fitted(TEST.but(P=2, K=1024), "composite"), 5_000)
    s = streams.s8_zipf(spark, data, 1.5, "0", n)
    handoffs = buffers.replay(s, spec)
    state, truth = composite.drain(handoffs, spec), workloads._truth(s)
    rungs = {"part_slots": composite.f2_ignore_buffers(composite.replay_slots(s, spec)), "ignored": composite.f2_ignore_buffers(state), "exact": composite.f2_exact_buffers(state, handoffs), "projected": composite.f2_projected(state, spec)}
    want = {m: (df.agg(F.sum("f2")).first()[0] - truth) / truth for m, df in rungs.items()}
    monkeypatch.setattr(buffers, "replay", forbidden)
    got = workloads.error_with_buffers(spark, data, (2,), (1.5,), 1, n).collect()
    assert {r["method"]: r["error"] for r in got} == pytest.approx(want, rel=1e-9)


def test_latency_is_one_pass(spark, data, monkeypatch):
    monkeypatch.setattr(buffers, "replay", forbidden)
    got = workloads.latency(spark, data, (2,), 2).collect()
    assert {(r["design"], r["query"]) for r in got} == {(d, q) for d in ("exclusive", "unsynced", "versioned") for q in ("f1", "f2")}
    assert all(r["repeats"] == 2 and 0 < r["median_ms"] <= 1e6 for r in got)
