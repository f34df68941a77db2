"""Worked examples, identities and bounds of the frequency engine."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mixedsketch.functions import hashing
from mixedsketch.functions.hashing import canon_key, check_key_type, fold
from mixedsketch.operators import agms, baselines, buffers, cm, composite, consistency, exact, interleave, ladder, measures, prefix, slots, static_state
from mixedsketch.sources import streams
from mixedsketch.sources.streams import STREAMS, normalise
from mixedsketch.spec import PAPER, TEST, SketchSpec, cm_plus_bounds, fit_width
from mixedsketch.workspace import Workspace
from tests import reference

SMALL = TEST.but(B=8, K=32, C=4)


def one(df):
    return df.first()[0]


def cells_of(spark, rows):
    return spark.createDataFrame(rows, "part int, row int, col int, cnt bigint")


def stream_of(spark, rows):
    return spark.createDataFrame(rows, "seq bigint, key bigint, weight bigint")


def test_toy_examples(spark):
    """Frequencies equal to the keys 1..4: one wide matrix gives 34, two parts give the truth of 30."""
    wide = cells_of(spark, [(0, 0, 0, 1), (0, 0, 2, 5), (0, 0, 3, 4), (0, 1, 0, 4), (0, 1, 1, 3), (0, 1, 3, 3)])
    assert {r["row"]: int(r["sq"]) for r in cm.f2_rows(wide).collect()} == {0: 42, 1: 34}
    assert one(cm.f2_plus_total(wide)) == 34
    parts = cells_of(spark, [(0, 0, 0, 1), (0, 0, 1, 2), (0, 1, 1, 3), (1, 0, 0, 7), (1, 1, 0, 4), (1, 1, 1, 3)])
    assert {r["part"]: int(r["f2"]) for r in cm.f2_plus(parts).collect()} == {0: 5, 1: 25}
    assert one(cm.f2_plus_total(parts)) == 30
    assert one(cm.f2_plus_total(cells_of(spark, [(0, 0, 0, 3)]))) == 9  # keys 1 and 2 in one counter: 4 above the truth


def test_slot_contributions():
    state = composite.OwnerState(TEST)
    state.slots = {7: [10, 2, 3.0]}
    row = state.row(0)
    assert (row["slots"][0]["cnt"] + 4 * 3 / 2) ** 2 - 2**2 == 252
    assert (1 + 2) ** 2 - 1**2 == 2**2 + 2 * 2 * 1 == 8


def test_sizing():
    assert (SketchSpec.from_error(0.01, 0.01).K, SketchSpec.from_error(0.01, 0.01).H) == (272, 5)
    assert cm_plus_bounds(8, 1024, 1.5)[1] == pytest.approx(0.75**8)
    assert [fit_width(PAPER.but(P=p)) for p in (1, 4, 16, 128)] == [1011, 999, 948, 472]
    assert fit_width(PAPER, "slots") == 1016
    assert measures.reads(PAPER.but(P=128), "exact_buffers") == 1_314_816 and measures.reads(PAPER.but(P=128), "projected") == 7_168
    with pytest.raises(ValueError):
        SketchSpec(w=0)


GOLDEN = {"S3": {"single": 15885442, "wide": 5348230, "part_cm": 5301868, "part_slots": 4958576, "agms": 1675133, "minus": 1768720}, "S1": {"single": 988386, "wide": 734908, "part_cm": 709444, "part_slots": 677248, "agms": 636773, "minus": 657647}}


@pytest.mark.parametrize("name", ["S3", "S1"])
def test_golden_values(spark, name):
    got = {r["method"]: (int(r["f2"]), int(r["exact"])) for r in ladder.report(STREAMS[name](spark, "/root/testdata/sf0.01"), TEST).collect()}
    assert {k: v[0] for k, v in got.items()} == GOLDEN[name]
    assert {v[1] for v in got.values()} == {1858320 if name == "S3" else 677248}


@pytest.mark.parametrize("name", ["S1", "S2", "S3", "S4", "S6", "S9", "S12"])
def test_bounds_on_every_stream(spark, data, name):
    s = STREAMS[name](spark, data).cache()
    truth = exact.moments(s).first()
    wide, part, slot = (int(one(f(s, TEST))) for f in (ladder.wide, ladder.part_cm, ladder.part_slots))
    assert truth["f2"] <= part <= wide and slot >= truth["f2"]
    cells = cm.build(s, TEST, "parts")
    assert {r["n"] for r in cells.groupBy("row").agg(F.sum("cnt").alias("n")).collect()} == {truth["f1"]}
    est = cm.point(cells, s.select("key"), TEST, "parts").join(exact.freq(s), "key")
    assert est.filter("est < f").isEmpty()
    light, heavy = slots.settled(s, TEST)
    assert slots.point(light, heavy, s.select("key"), TEST).join(exact.freq(s), "key").filter("est < f").isEmpty()


def test_merge_is_linear(spark, data):
    a, b = STREAMS["S1"](spark, data), STREAMS["S6"](spark, data)
    both = a.select("key", "weight").union(b.select("key", "weight"))
    got = {tuple(r) for r in cm.merge(cm.build(a, TEST), cm.build(b, TEST)).select("row", "col", "cnt").collect()}
    assert got == {tuple(r) for r in cm.build(both, TEST).select("row", "col", "cnt").collect()}


@pytest.mark.parametrize("spec", [SMALL, SMALL.but(P=1), SMALL.but(B=None), SMALL.but(C=16, w=0.3)])
@pytest.mark.parametrize("name", ["S1", "S12"])
def test_replay_against_reference(spark, data, name, spec):
    s = STREAMS[name](spark, data).select("seq", "key", "weight").cache()
    rows = [tuple(r) for r in s.collect()]
    parts, open_buffers = reference.replay(rows, spec)
    handoffs = buffers.replay(s, spec).cache()
    state = composite.drain(handoffs, spec).cache()
    got = {r["part"]: r for r in state.collect()}
    for i, part in enumerate(parts):
        if i not in got:
            assert not part.slot
            continue
        assert {x["key"]: (x["cnt"], x["old"]) for x in got[i]["slots"]} == {k: v[:2] for k, v in part.slot.items()}
        assert [x["avg"] for x in got[i]["slots"]] == pytest.approx([part.slot[k][2] for k in sorted(part.slot)])
        assert [int(v) for v in got[i]["f2rows"]] == part.matrix.squares()
        assert got[i]["v_begin"] == got[i]["v_end"]
    left = {}
    for (p, o), b in open_buffers.items():
        for k, c in b.items():
            left[(p, o, k)] = c
    assert {(r["producer"], r["owner"], r["key"]): r["cnt"] for r in handoffs.filter("NOT handed").collect()} == left
    ignored = sum(p.f2() for p in parts)
    in_buffers = {}
    for (_, _, k), c in left.items():
        in_buffers[k] = in_buffers.get(k, 0) + c
    by_hand = {"ignored": ignored, "exact": sum(p.f2(lambda k, a: in_buffers.get(k, 0)) for p in parts), "projected": sum(p.f2(lambda k, a: spec.P * a / 2) for p in parts)}
    engine = {"ignored": composite.f2_ignore_buffers(state), "exact": composite.f2_exact_buffers(state, handoffs), "projected": composite.f2_projected(state, spec)}
    for k, df in engine.items():
        assert df.agg(F.coalesce(F.sum("f2"), F.lit(0.0))).first()[0] == pytest.approx(by_hand[k]), k
    assert by_hand["ignored"] <= by_hand["exact"]
    want = {tuple(r) for r in cm.build(s, spec, "parts").select("part", "row", "col", "cnt").collect()}
    assert {tuple(r) for r in composite.conserved_cells(state, handoffs, spec).select("part", "row", "col", "cnt").collect()} == want
    points = {r["key"]: r["est"] for r in composite.point(state, handoffs, s.select("key"), spec).collect()}
    for k in {r[1] for r in rows}:
        assert points[k] == parts[reference.owner(spec, k)].ask(k) + in_buffers.get(k, 0)


def test_direct_slots_are_one_sided(spark, data):
    for name in ("S1", "S7", "S12"):
        s = STREAMS[name](spark, data).select("seq", "key", "weight").cache()
        state = composite.replay_slots(s, SMALL).cache()
        assert state.agg(F.sum(F.expr("0"))).first() is not None
        assert composite.f2_ignore_buffers(state).agg(F.sum("f2")).first()[0] >= float(exact.moments(s).first()["f2"])
        assert composite.point(state, None, s.select("key"), SMALL).join(exact.freq(s), "key").filter("est < f").isEmpty()
        parts, _ = reference.replay([tuple(r) for r in s.collect()], SMALL, buffered=False)
        assert composite.f2_ignore_buffers(state).agg(F.sum("f2")).first()[0] == pytest.approx(sum(p.f2() for p in parts))


def test_replay_does_not_depend_on_partitioning(spark, data):
    s = STREAMS["S1"](spark, data).select("seq", "key", "weight")
    a = composite.drain(buffers.replay(s.repartition(7), SMALL), SMALL).orderBy("part").collect()
    b = composite.drain(buffers.replay(s.coalesce(1), SMALL), SMALL).orderBy("part").collect()
    assert a == b


def test_map_side_buffers_conserve_counts(spark, data):
    s = STREAMS["S3"](spark, data)
    out = buffers.combine(s, SMALL).cache()
    assert out.agg(F.sum("cnt")).first()[0] == s.count()
    assert out.count() < s.count()
    fills = out.filter("handed").groupBy("producer", "owner", "flush_seq").agg(F.count("*").alias("k"), F.sum("cnt").alias("n"))
    assert fills.filter(f"k > {SMALL.C}").isEmpty()


def test_buffers_stay_within_bound(spark, data):
    for spec in (TEST, SMALL, SMALL.but(P=2)):
        assert buffers.buffered(buffers.chunks(STREAMS["S1"](spark, data), spec), spec).filter("NOT ok").isEmpty()
    assert one(baselines.separate(STREAMS["S1"](spark, data), TEST)["f1"]) == 1000


def test_exclusive_policy_equals_matrices_of_all_rows(spark, data):
    s = STREAMS["S1"](spark, data)
    state = static_state.build(s, SMALL)
    assert one(static_state.exclusive_f1(state)) == 1000
    assert one(static_state.exclusive_f2(state)) == one(ladder.part_cm(s, SMALL))
    assert one(static_state.exclusive_f2(state, "elementwise")) == one(ladder.single(s, SMALL))


def test_unsynchronised_reads_miss_and_repeat(spark):
    """One lane of eight fills while the scan is between its two looks."""
    spec = SMALL.but(P=1)
    s = stream_of(spark, [(i, 5, 1) for i in range(12)])
    looks = lambda t, order: interleave.unsynced(s, spec, t, 0, 4, order).select("arrived", "in_sketch", "in_buffer", "missed", "doubled").first()
    assert looks(5, "sketch_first") == (6, 0, 2, 6, 0)  # rows 0..5 wait, row 7 hands them over, 8 and 9 wait again
    assert looks(5, "buffers_first") == (6, 8, 6, 0, 6)
    assert looks(7, "sketch_first")[3:] == looks(7, "buffers_first")[3:] == (0, 0)
    first, second = (int(one(interleave.unsynced_f2(s, spec, 5, 0, 4, o).select("f2"))) for o in ("sketch_first", "buffers_first"))
    assert first == 0 and second == (8 + 6) ** 2  # missed: no slot yet, so no buffer is read; double: six rows twice
    v = interleave.versioned(s, spec, 5, 0, 4).first()
    assert (v["retries"], v["v_end"]) == (1, 1) and v["f2"] == (8 + 8 / 2) ** 2
    v = interleave.versioned(s, spec, 8, 0, 2).first()
    assert (v["retries"], v["v_end"]) == (0, 1)


def test_intervals_hold_every_answer(spark, data):
    for name in ("S1", "S8"):
        s = STREAMS[name](spark, data)
        grain = prefix.grain_of(s)
        for f in (consistency.ivl_f1, consistency.ivl_f2):
            t = f(s, SMALL, grain, 4).collect()
            assert len(t) >= 40 and all(r["inside"] for r in t)


def test_relaxation_and_monotonicity(spark, data):
    s = STREAMS["S1"](spark, data)
    assert consistency.relaxed_bound(s, SMALL, 5).filter("NOT ok").isEmpty()
    m = {(r["q1"], r["q2"]): (r["worst"], r["bound"], r["ok"]) for r in consistency.monotone_matrix(s, SMALL, 5).collect()}
    assert len(m) == 9 and all(v[2] for v in m.values())
    assert m[("f2", "point")][0] == m[("f2", "f1")][0] == m[("f1", "point")][0] == 0 and m[("point", "f2")][0] > 0
    assert m[("point", "f1")][0] == 1  # the row that has just entered its buffer


def folded_pair():
    """Two keys with one folded form."""
    seen = {}
    for i in range(400_000):
        x = hashing.fold(f"k{i}")
        if x in seen:
            return f"k{seen[x]}", f"k{i}"
        seen[x] = i


def test_truth_tells_keys_apart_that_fold_together(spark):
    a, b = folded_pair()
    rows = spark.createDataFrame([(a,)] * 3 + [(b,)] * 4 + [("z",)], "word string")
    s = streams.normalise(rows, F.col("word"))
    assert exact.freq(s).count() == 2  # to a sketch they are one
    m = exact.moments(s).first()
    assert (m["f0"], m["f1"], int(m["f2"]), m["max_f"]) == (3, 8, 26, 4) and int(one(exact.moment(s, 2))) == 26
    wide = TEST.but(hash_family="xxhash64", K=4096)
    assert int(one(ladder.part_cm(hashing.rekeyed(s, wide), wide))) == 26 and int(one(ladder.part_cm(s, TEST.but(K=4096)))) == 7**2 + 1


def test_wide_hash_family(spark, data):
    spec = TEST.but(hash_family="xxhash64")
    keys = spark.range(-50, 2000).select((F.col("id") * 7919).alias("key"))
    got = keys.select("key", F.array(*[hashing.row_hash(F.col("key"), spec, j) for j in range(spec.H)]).alias("rows"), hashing.owner(F.col("key"), spec).alias("own"), hashing.sign(F.col("key"), spec, 1).alias("sign")).toPandas()
    x = got["key"].to_numpy()
    assert (np.stack(got["rows"].to_numpy()) == hashing.row_hashes_np(x, spec)).all() and (got["own"].to_numpy() == hashing.owner_np(x, spec)).all()
    assert abs(got["sign"].mean()) < 0.1 and got["own"].value_counts().min() > 400
    s = hashing.rekeyed(STREAMS["S3"](spark, data), spec)
    truth = int(exact.moments(s).first()["f2"])
    assert truth <= int(one(ladder.part_cm(s, spec))) <= int(one(ladder.wide(s, spec))) and abs(int(one(agms.f2(agms.build(s, spec), spec))) - truth) < truth
    s = hashing.rekeyed(STREAMS["S1"](spark, data), SMALL.but(hash_family="xxhash64"))
    spec = SMALL.but(hash_family="xxhash64")
    work = Workspace(spark, "wide")
    handoffs = work.save(buffers.replay(s, spec), "h")
    kept = composite.conserved_cells(composite.drain(handoffs, spec), handoffs, spec)
    assert kept.exceptAll(cm.build(s, spec, "parts").select(kept.columns)).isEmpty()


def test_running_rank_over_blocks(spark):
    s = stream_of(spark, [(i, i % 3, 1) for i in range(100)])
    got = prefix.running_rank(s.withColumn("lane", F.col("seq") % 2), ["lane"], block=7).collect()
    assert all(r["rank"] == r["seq"] // 2 + 1 and r["lane_n"] == 50 for r in got)


@pytest.mark.parametrize("rows", [[], [(0, 5, 1)], [(i, 5, 1) for i in range(40)], [(i, i % 3, 1) for i in range(40)]])
def test_degenerate_streams(spark, rows):
    s = stream_of(spark, rows)
    truth = exact.moments(s).first()
    for f in (ladder.wide, ladder.part_cm, ladder.part_slots):
        assert int(one(f(s, TEST))) == truth["f2"]
    assert one(static_state.f1(s, TEST)) == len(rows) == one(static_state.exclusive_f1(static_state.build(s, TEST)))
    assert one(cm.f1(cm.build(s, TEST))) == len(rows)
    assert sum(r["updates"] for r in composite.drain(buffers.replay(s, SMALL), SMALL).collect()) <= len(rows)
    assert agms.f2(agms.build(s, TEST), TEST).count() == (1 if rows else 0)


def test_bad_weights_and_keys(spark):
    raw = spark.createDataFrame([("a", 1), ("b", 0), ("c", -2), ("d", None), (None, 3)], "k string, w int")
    assert normalise(raw, F.col("k"), F.col("w"), on_bad_weight="drop").count() == 1
    with pytest.raises(Exception, match="weights must be positive"):
        normalise(raw, F.col("k"), F.col("w")).collect()
    with pytest.raises(TypeError):
        normalise(raw, F.lit(1.5))
    kinds = spark.range(1).select(F.lit(5).alias("i"), F.lit("x").alias("s"), F.lit("2020-01-01").cast("date").alias("d"), F.lit(True).alias("b"), F.lit("1.50").cast("decimal(5,2)").alias("dec"))
    for c in kinds.columns:
        check_key_type(kinds.schema[c].dataType)
        assert 0 <= kinds.select(canon_key(F.col(c))).first()[0] < 2**31 - 1
    assert kinds.select(canon_key(F.col("i"))).first()[0] == fold(5)


def test_zipf_stream_counts(spark):
    for z, f0, top in ((1, 1000, 8104), (1.5, 835, 23573), (2, 290, 36556), (3, 51, 49817)):
        m = exact.moments(streams.s8_zipf(spark, "", z, rows=60_000)).first()
        assert (m["f0"], m["f1"], m["max_f"]) == (f0, 60_000, top)


def test_skew_picks_the_estimator(spark, data):
    assert cm.f2_auto(streams.s8_zipf(spark, "", 2, rows=60_000), TEST).first()["kind"] == "plus"
    assert cm.f2_auto(STREAMS["S3"](spark, data), TEST).first()["kind"] == "minus"
    assert cm.f2_auto(STREAMS["S3"](spark, data), TEST, z=1.5).first()["kind"] == "plus"


def test_projection_repairs_ignored_buffers(spark):
    """On a skewed stream, ignoring buffers underestimates and projecting them comes nearer."""
    s = streams.s8_zipf(spark, "", 1.5, "0", 20_000).select("seq", "key", "weight").cache()
    spec = TEST.but(P=4, K=512, B=62)
    handoffs = buffers.replay(s, spec).cache()
    state = composite.drain(handoffs, spec).cache()
    truth = float(exact.moments(s).first()["f2"])
    err = {n: abs(df.agg(F.sum("f2")).first()[0] - truth) / truth for n, df in (("ignored", composite.f2_ignore_buffers(state)), ("projected", composite.f2_projected(state, spec)))}
    assert err["projected"] < err["ignored"] < 0.2


def test_more_parts_and_better_rungs_reduce_error(spark):
    from mixedsketch.workloads import error_by_parts

    t = {(r["z"], r["P"], r["method"]): r["mape"] for r in error_by_parts(spark, "", (1, 4, 16), (1.0, 2.0), 2, 10_000).collect()}
    for z in (1.0, 2.0):
        assert t[(z, 16, "part_cm")] <= t[(z, 4, "part_cm")] <= t[(z, 1, "part_cm")]
        assert t[(z, 16, "part_cm")] <= t[(z, 16, "wide")]


def test_quantiles_from_dyadic_cells(spark):
    s = spark.range(1000).select(F.lit(None).cast("bigint").alias("seq"), F.col("id").alias("value"), F.lit(1).cast("bigint").alias("weight"))
    spec = TEST.but(H=4, K=2048)
    cells = cm.dyadic_build(s, F.col("value"), 10, spec).cache()
    assert abs(cm.dyadic_quantile(cells, 1000, 0.5, 10, spec) - 500) <= 20


def test_builtin_count_min_is_one_sided(spark, data):
    from mixedsketch.workloads import baseline_point

    assert all(r["builtin"] >= r["exact"] for r in baseline_point(spark, data).collect())


def test_own_keys_may_skip_the_buffers(spark, data):
    s = STREAMS["S1"](spark, data).select("seq", "key", "weight")
    spec = SMALL.but(self_buffer=False)
    handoffs = buffers.replay(s, spec).cache()
    assert handoffs.filter("producer = owner AND NOT handed").isEmpty() and handoffs.agg(F.sum("cnt")).first()[0] == 1000
    state = composite.drain(handoffs, spec)
    want = {tuple(r) for r in cm.build(s, spec, "parts").select("part", "row", "col", "cnt").collect()}
    assert {tuple(r) for r in composite.conserved_cells(state, handoffs, spec).select("part", "row", "col", "cnt").collect()} == want


def test_concurrent_rungs_lie_between_begin_and_end(spark, data):
    s = STREAMS["S1"](spark, data)
    for kind, f in (("wide", ladder.wide), ("part_cm", ladder.part_cm)):
        lo, hi = (int(one(f(s.filter(f"seq <= {t}"), SMALL))) for t in (400, 400 + 3 * 50))
        assert lo <= int(one(ladder.concurrent(s, SMALL, kind, 400, 50))) <= hi


def test_buffers_cut_what_is_shuffled(spark):
    """On a skewed stream the map-side buffers move fewer bytes than the rows would."""
    s = streams.s8_zipf(spark, "", 2.0, rows=60_000).select("seq", "key", "weight").cache()
    s.count()
    rows = measures.shuffled_bytes(spark, s.repartition(4, "key"))
    assert 0 < measures.shuffled_bytes(spark, buffers.combine(s, TEST).repartition(4, "owner")) < rows
