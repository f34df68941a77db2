"""Streams made in blocks, and what designs and queries make of them."""

import pytest
from pyspark.sql import functions as F

from mixedsketch import workloads
from mixedsketch.jvm import kernels, map_partitions
from mixedsketch.operators import agms, blocks, cm, composite
from mixedsketch.sources import streams
from mixedsketch.sources.streams import STREAMS
from mixedsketch.spec import TEST
from mixedsketch.workspace import Workspace

EVERY = 1 << 62  # a moment after every update


@pytest.fixture()
def work(spark):
    made = Workspace(spark, "t")
    yield made
    made.drop()


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def keys_in_order(packed, spec=TEST.but(P=1, C=1, K=1, B=1)):
    """(seq, key) of every update: each is a hand-over of one key."""
    return rows(blocks.flushes(packed, spec).select("flush_seq", "key"))


@pytest.mark.parametrize(("z", "salt", "n"), [(1.0, None, None), (1.5, "3", 5_000), (3.0, None, None)])
def test_zipf_blocks_are_the_stream(spark, data, work, z, salt, n):
    packed = work.save(blocks.zipf(spark, data, z, salt, n), "blocks")
    assert blocks.in_order(packed) and keys_in_order(packed) == rows(streams.s8_zipf(spark, data, z, salt, n).select("seq", "key"))


TEXTS = ["", None, "one Two  three", "  led by blanks", "...", "İstanbul K Ünï ß9a", "x", "a-b_c9 \n\t z."]


def documents(spark, folder, ids):
    spark.createDataFrame([(i, t, "en", "s", 1) for i, t in ids], streams.SCHEMAS["documents"]).write.parquet(f"{folder}/documents.parquet")
    return str(folder)


def test_word_blocks_are_the_stream(spark, data, tmp_path, work):
    odd = documents(spark, tmp_path, [(7 * i - 9, t) for i, t in enumerate(TEXTS)])
    for i, d in enumerate((data, odd)):
        packed = work.save(blocks.words(spark, d), f"blocks{i}")
        assert blocks.in_order(packed) and keys_in_order(packed) == rows(STREAMS["S7"](spark, d).select("seq", "key"))


def test_words_of_one_id_are_put_in_order(spark, tmp_path, work):
    d = documents(spark, tmp_path, [(5, "b a c a"), (5, "c b a"), (6, "d"), (5, "a")])
    assert not blocks.in_order(work.save(blocks.words(spark, d), "made"))
    packed = blocks.keep(spark, d, "S7", work)
    assert blocks.in_order(work.save(blocks.numbered(packed), "numbered"))
    assert [r["key"] for r in blocks.flushes(packed, TEST.but(P=1, B=1)).collect()] == [r["key"] for r in STREAMS["S7"](spark, d).orderBy("seq", "key").collect()]


def test_throughput_sorts_no_rows(spark, data, monkeypatch):
    def forbidden(*args, **more):
        raise AssertionError("rows of the stream are made and sorted")

    monkeypatch.setattr(streams, "s8_zipf", forbidden)
    monkeypatch.setitem(STREAMS, "S7", forbidden)
    monkeypatch.setattr(blocks, "pack", forbidden)
    for name, z in (("S8", 3.0), ("S7", 0.0)):
        got = workloads.throughput(spark, data, name, z, (2,), ("separate", "versioned")).collect()
        assert len(got) == 4 and all(r["rows"] > 0 for r in got)


def test_sums_and_picked_keys(spark, data, work):
    s = STREAMS["S1"](spark, data).withColumn("weight", 1 + F.pmod("key", F.lit(3)))
    packed = work.save(blocks.pack(s), "blocks")
    lane = F.pmod("seq", F.lit(3)).alias("worker")
    for bounds, part in (({}, s), ({"after": 100, "until": 700}, s.filter("seq > 100 AND seq <= 700"))):
        assert rows(blocks.sums(packed, 3, **bounds)) == rows(part.groupBy(lane, "key").agg(F.sum("weight")))
    assert rows(blocks.picked(packed, 7)) == rows(s.filter(F.pmod(F.xxhash64("seq"), F.lit(7)) == 0).select("key").distinct())


def test_blocks_of_any_seqs_and_weights(spark, work):
    given = [(s, k, w) for s, k, w in zip([-(1 << 40), 0, 0, 300, 70_000, 1 << 33, (1 << 33) + 1], [5, 5, 6, (1 << 62) + 1, -4, 7, 5], [1, 1, 1, 9, 1, 1 << 50, 2], strict=True)]
    packed = work.save(blocks.pack(spark.createDataFrame(given, "seq bigint, key bigint, weight bigint")), "blocks")
    state = composite.run(packed, TEST.but(P=1, C=9, hash_family="xxhash64"), kinds="direct").first()
    assert {s["key"]: s["cnt"] for s in state["slots"]} == {5: 4, 6: 1, (1 << 62) + 1: 9, -4: 1, 7: 1 << 50}
    assert rows(blocks.arrivals(packed, [0, 299, 70_000, EVERY]).groupBy("moment").agg(F.sum("n"))) == [(0, 3), (2, 10), (3, (1 << 50) + 2)]


@pytest.mark.parametrize(("parts", "most"), [(1, 1_200), (3, 100)])
def test_lanes_that_grow_within_a_block(spark, work, parts, most):
    """Buffers without a limit on keys, handed over and filled again beyond their first room."""
    n, half = 3_900, 1_500
    given = [(i, (i % 7 if i < 600 else i % half), 1) for i in range(n)]
    spec = TEST.but(P=parts, B=most)
    packed = work.save(blocks.pack(spark.createDataFrame(given, "seq bigint, key bigint, weight bigint").coalesce(1)), "blocks")
    got = blocks.flushes(packed, spec).groupBy("part", "producer", "flush_seq").agg(F.sum("v").alias("v"), F.count("*").alias("n"), F.countDistinct("key").alias("keys")).collect()
    assert got and all(r["v"] == most and r["n"] == r["keys"] for r in got)
    big = TEST.but(P=1, B=3_000, C=5_000)
    assert {(s["key"], s["cnt"]) for s in composite.run(packed, big).first()["slots"]} == {(k, sum(1 for i, x, _ in given[:3_000] if x == k)) for k in {x for _, x, _ in given[:3_000]}}


@pytest.mark.parametrize("design", ["separate", "versioned"])
def test_kept_tables_have_the_schemas_they_are_read_by(spark, data, work, design):
    packed = work.save(blocks.pack(STREAMS["S1"](spark, data)), "blocks")
    workloads._update(design, None, packed, TEST, work)
    for name, schema in (("matrix", workloads.CELLS), ("signed", workloads.CELLS)) if design == "separate" else (("state", composite.FULL_STATE),):
        found, asked = spark.read.parquet(work.path(name)), spark.read.schema(schema).parquet(work.path(name))
        assert dict(found.dtypes) == dict(asked.dtypes) and rows(asked.select(*found.columns)) == rows(found)


def test_heaviest_keys_of_every_version(spark, work):
    """Runs of versions are not written out; ties go to the lower key, whichever task has it."""
    runs = [(p, k, (k * 7 + p) % 5, 1 + k % 4, 1 + k % 4 + k % 3) for p in (0, 3) for k in range(60)]
    df = spark.createDataFrame(runs, "part int, key bigint, f bigint, version int, until int").repartition(3)
    got = rows(map_partitions(df, kernels(spark).heaviest(4), "part int, version int, key bigint, f bigint"))
    for p in (0, 3):
        for v in range(1, 7):
            want = sorted((-f, k) for q, k, f, a, b in runs if q == p and a <= v <= b)[:4]
            assert sorted((-r[3], r[2]) for r in got if r[:2] == (p, v))[:4] == want


def test_freshness_sorts_no_words(spark, data, monkeypatch):
    def forbidden(*args, **more):
        raise AssertionError("words are made as rows and sorted")

    monkeypatch.setitem(STREAMS, "S7", forbidden)
    monkeypatch.setattr(blocks, "pack", forbidden)
    got = workloads.freshness(spark, data, 5, names=("S7",)).collect()
    assert len(got) == 10 and all(r["hi"] > 0 for r in got)


def test_separate_sketches_sum_keys_once(spark, data, work, monkeypatch):
    s = STREAMS["S1"](spark, data)
    lanes = s.withColumn("worker", F.pmod("seq", F.lit(TEST.P)))
    want = {"matrix": rows(cm.build(lanes, TEST, by=["worker"])), "signed": rows(agms.build(lanes, TEST, ["worker"]))}

    def forbidden(*args, **more):
        raise AssertionError("keys are summed again for a sketch")

    monkeypatch.setattr(cm, "build", forbidden)
    monkeypatch.setattr(agms, "build", forbidden)
    workloads._update("separate", None, work.save(blocks.pack(s), "blocks"), TEST, work)
    for name, cells in want.items():
        assert rows(spark.read.parquet(work.path(name)).select("worker", "part", "row", "col", "cnt")) == cells
