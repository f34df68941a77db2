"""Scans of both policies against answers made row by row."""

import pytest
from pyspark.sql import functions as F

from mixedsketch.operators import blocks, buffers, interleave, measures
from mixedsketch.sources.streams import STREAMS
from mixedsketch.spec import TEST
from mixedsketch.workspace import Workspace
from tests import reference


def answer(rows, spec, policy, part, t, b):
    """What a look at one part returns: matrix and slots of t, and buffers of b read or projected."""
    mine = [r for r in rows if r["owner"] == part]
    gone = [r for r in mine if r["flush_seq"] is not None and r["flush_seq"] <= t]
    f = {}
    for r in gone:
        f[r["key"]] = f.get(r["key"], 0) + 1
    heavy = sorted(f, key=lambda k: (-f[k], k))[: spec.C]
    matrix = reference.Matrix(spec)
    for k in f.keys() - set(heavy):
        matrix.add(k, f[k])
    total = min(matrix.squares())
    for k in heavy:
        if policy == "unsynced":
            more = sum(r["key"] == k and r["seq"] <= b and (r["flush_seq"] is None or r["flush_seq"] > b) for r in mine)
        else:
            counts, avg = {}, None
            for r in gone:
                if r["key"] == k:
                    at = r["flush_seq"], r["producer"]
                    counts[at] = counts.get(at, 0) + 1
            for at in sorted(counts):
                avg = counts[at] if avg is None else spec.w * counts[at] + (1 - spec.w) * avg
            more = spec.P / 2 * avg
        total += (f[k] + more) ** 2
    return total


@pytest.mark.parametrize("spec", [TEST.but(P=2, C=3, B=9), TEST.but(P=3, C=2, B=40, K=8)], ids=str)
def test_freshness_equals_looks_row_by_row(spark, data, spec):
    s, scans = STREAMS["S1"](spark, data).withColumn("weight", F.lit(1)).cache(), 4
    rows = [r.asDict() for r in buffers.chunks(s, spec).collect()]
    work = Workspace(spark, "t")
    got = interleave.freshness(work.save(blocks.pack(s), "blocks"), spec, scans, work).collect()
    assert len(got) == 2 * scans
    last = max(r["seq"] for r in rows)
    slow = max(1, last // (4 * scans * spec.P))
    quick = max(1, slow * measures.reads(spec, "projected") // measures.reads(spec, "exact_buffers"))
    for r in got:
        policy, step, t = r["policy"], slow if r["policy"] == "unsynced" else quick, r["t_start"]
        late = max(1, slow // 2) if policy == "unsynced" else 0
        assert r["t_end"] == t + spec.P * step
        looks = {"lo": lambda p: (t, t), "val": lambda p: (t + p * step, t + p * step + late), "hi": lambda p: (r["t_end"], r["t_end"])}
        for which, at in looks.items():
            assert r[which] == pytest.approx(sum(answer(rows, spec, policy, p, *at(p)) for p in range(spec.P)), rel=1e-12)
    work.drop()


def test_equal_states_give_equal_answers(spark, data):
    """A versioned scan during which nothing was handed over lies inside its interval, to the last bit."""
    from mixedsketch.workloads import freshness

    rows = freshness(spark, data, 30, names=(1.5, "S7")).filter("policy = 'versioned'").collect()
    close = [r for r in rows if abs(r["hi"] - r["lo"]) <= 1e-9 * r["hi"]]
    assert len(rows) == 60 and close
    assert all(r["lo"] == r["val"] == r["hi"] and r["inside"] for r in close)
