"""What an update reads and writes of blocks, and how often states are built."""

import pytest
from pyspark.sql import functions as F

from mixedsketch import workloads
from mixedsketch.functions import hashing
from mixedsketch.jvm import kernels, map_partitions
from mixedsketch.operators import agms, blocks, buffers, cm, composite
from mixedsketch.sources import streams
from mixedsketch.spec import TEST
from mixedsketch.workspace import Workspace


@pytest.fixture()
def work(spark):
    made = Workspace(spark, "t")
    yield made
    made.drop()


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_first_states_are_built_once_for_an_update_path(spark, data, work, monkeypatch):
    """Designs whose updates are the same share the state of the first tenth, which no clock covers."""
    asked, update = [], workloads._update

    def counted(design, s, packed, spec, work, after=None, until=None):
        asked.append((design, until is not None))
        update(design, s, packed, spec, work, after=after, until=until)

    monkeypatch.setattr(workloads, "_update", counted)
    got = workloads.throughput(spark, data, "S8", 2.0, (2,)).collect()
    assert sorted(d for d, first in asked if first) == ["buffers_only", "buffers_only_unbounded", "exclusive", "separate"]
    assert sorted(d for d, first in asked if not first) == sorted(2 * workloads.DESIGNS)  # whole, alone and beside queries
    assert len(got) == 2 * len(workloads.DESIGNS) and all(r["rows"] == streams.load(spark, data, "lineitem").count() for r in got)


def test_first_states_are_those_of_each_design(spark, data, work):
    packed, spec, until = blocks.keep(spark, data, 3.0, work), TEST.but(P=2), 999
    firsts = workloads._first_states(workloads.DESIGNS, packed, spec, until, work)
    for design in workloads.DESIGNS:
        workloads._update(design, None, packed, spec, work, until=until)
        for name in ("matrix", "signed") if design == "separate" else ("state",):
            assert rows(spark.read.parquet(firsts[design].path(name))) == rows(spark.read.parquet(work.path(name)))


def test_blocks_of_one_owner_are_dealt_as_they_are(spark, data, work):
    """They were taken apart and put together again."""
    other = bytes([0, 0, 0, 2, 0, 0, 0, 1, 1, 0, 0]) + (5).to_bytes(8, "big") + (1).to_bytes(8, "big") + (7).to_bytes(8, "big") + bytes([1]) + 2 * (1).to_bytes(8, "big")  # steps and weights written out, though steps are 1 and weights one
    packed = spark.createDataFrame([(0, 2, 5, 6, bytearray(other))], blocks.BLOCKS)
    assert [bytes(r["data"]) for r in blocks.routed(packed, TEST.but(P=1)).collect()] == [other]
    assert [(r["seqs"], r["n"]) for r in blocks.routed(packed, TEST.but(P=1), until=5).select(F.length("data").alias("n"), F.conv(F.hex(F.substring("data", 1, 4)), 16, 10).cast("int").alias("seqs")).collect()] == [(1, 35)]


@pytest.mark.parametrize("step", [1, 200, 60_000, 70_000_000, 3_000_000_000])
@pytest.mark.parametrize("keys", [1, 300, 70_000])
@pytest.mark.parametrize("weights", [1, 9])
def test_blocks_of_every_width_are_read_as_written(spark, work, step, keys, weights):
    n = 100 if keys == 1 else 2 * keys
    s = spark.range(0, n, 1, 1).select((F.col("id") * step - F.when(F.col("id") % 7 == 3, step // 2).otherwise(0)).alias("seq"), (F.col("id") % keys * 3 - 50).alias("key"), (1 + F.col("id") % weights).alias("weight"))
    packed = map_partitions(s.sortWithinPartitions("seq"), kernels(spark).pack(n), blocks.BLOCKS)
    packed = work.save(packed, "packed")
    assert packed.count() == 1
    got = blocks.flushes(packed, TEST.but(P=1, B=1)).select("flush_seq", "key", "v")  # each update is a hand-over of one key
    assert rows(got) == rows(s)


@pytest.mark.parametrize("z", [1.0, 2.0, 3.0])
@pytest.mark.parametrize("spec", [TEST.but(P=1, B=900), TEST.but(P=4), TEST.but(P=16, B=None), TEST.but(P=3, B=50), TEST.but(P=2, self_buffer=False), TEST.but(P=2, producer="contiguous")], ids=str)
def test_skewed_streams_have_the_states_of_both_stages(spark, data, work, z, spec):
    packed = work.save(blocks.zipf(spark, data, z), "packed")
    handoffs = buffers.replay(streams.s8_zipf(spark, data, z).select("seq", "key", "weight"), spec)
    twin = composite.drain(handoffs, spec)
    state = composite.run(packed, spec)
    assert [r for r in rows(state.select(*twin.columns)) if r[twin.columns.index("updates")]] == rows(twin)
    left = composite.still_open(state)
    assert rows(left) == rows(handoffs.filter("NOT handed").select(*left.columns))


@pytest.mark.parametrize("spec", [TEST, TEST.but(P=3, K=7), TEST.but(P=5, hash_family="xxhash64")], ids=str)
def test_hashes_as_text_are_those_of_columns(spark, spec):
    s = spark.createDataFrame([(k,) for k in (0, 1, 7, 2147483646, *range(3, 2_000_000_000, 99_999_999))], "key bigint")
    x, pairs = F.col("key"), [(hashing.owner(F.col("key"), spec), hashing.owner_text("`key`", spec))]
    for j in range(spec.H):
        pairs += [(hashing.row_hash(x, spec, j), hashing.row_text("`key`", spec, j)), (hashing.sign(x, spec, j), hashing.sign_text("`key`", spec, j))]
    both = s.select(*[c.alias(f"a{i}") for i, (c, _) in enumerate(pairs)], *[F.expr(t).alias(f"b{i}") for i, (_, t) in enumerate(pairs)])
    types = dict(both.dtypes)
    assert all(types[f"a{i}"] == types[f"b{i}"] for i in range(len(pairs)))
    assert both.filter(" OR ".join(f"a{i} <> b{i}" for i in range(len(pairs)))).isEmpty() and both.count() == s.count()
    for layout, shift in (("single", None), ("parts", None), ("wide", hashing.owner(x, spec) * spec.K)):
        part, at = cm.key_places(spec, layout)
        got = s.select("key", part.alias("part"), at.alias("at"))
        want = s.select("key", (hashing.owner(x, spec) if layout == "parts" else F.lit(0)).alias("part"), cm.places(x, spec, shift).alias("at"))
        assert got.dtypes == want.dtypes and rows(got) == rows(want)


def test_sketches_are_made_in_few_calls(spark, monkeypatch):
    """Every term of every hash was a call, some 0.6 s for the two sketches of a worker."""
    calls, made = [], F.lit
    monkeypatch.setattr(F, "lit", lambda v: calls.append(v) or made(v))
    f = spark.createDataFrame([(0, 1, 2)], "worker bigint, key bigint, f bigint")
    cm.from_frequencies(f, TEST, by=["worker"])
    agms.from_frequencies(f, TEST, ["worker"])
    cm.point(cm.from_frequencies(f, TEST), f.select("key"), TEST)
    assert len(calls) < 10
