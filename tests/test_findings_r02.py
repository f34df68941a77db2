"""What the findings of round 2 asked for."""

from pyspark.sql import functions as F

from mixedsketch import registry
from mixedsketch.operators import buffers, composite
from mixedsketch.spec import TEST
from mixedsketch.sources.streams import STREAMS
from tests import reference


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_replays_run_in_the_jvm(spark, data):
    s = STREAMS["S1"](spark, data).select("seq", "key", "weight")
    handoffs = buffers.replay(s, TEST)
    for df in (handoffs, buffers.combine(s, TEST), composite.drain(handoffs, TEST), composite.replay_slots(s, TEST), composite.drain_split(handoffs, TEST)[0]):
        assert "MapPartitions" in plan(df) and "InArrow" not in plan(df)


def test_squares_beyond_a_long(spark):
    rows = [(i, i % 5, 1 << 30) for i in range(40)]
    spec = TEST.but(P=1, C=1, K=2)
    s = spark.createDataFrame(rows, "seq bigint, key bigint, weight bigint").withColumn("weight", F.col("weight") * 4)
    state = composite.replay_slots(s, spec).first()
    parts, _ = reference.replay([(a, k, 4 * w) for a, k, w in rows], spec, buffered=False)
    assert [int(v) for v in state["f2rows"]] == parts[0].matrix.squares() and max(parts[0].matrix.squares()) > 1 << 63


def test_third_moments_beyond_a_long(spark):
    s = spark.createDataFrame([(i, 7, 1 << 20) for i in range(20)], "seq bigint, key bigint, weight bigint")
    big = registry._narrowed(registry._powers(s), "f2", "f3")
    n = 20 << 20
    assert int(big.first()["f3"]) == n**3 > 1 << 63 and dict(big.dtypes)["f2"] == "bigint"
    assert dict(registry._narrowed(registry._powers(s.limit(1)), "f2", "f3").dtypes)["f3"] == "bigint"


def test_reports_read_a_table(spark, data):
    """Sizes and reads stand beside those of exact counts of the pairs in lineitem."""
    keys = STREAMS["S10"](spark, data).select("k").distinct().count()
    for name, column, each in (("memory_report", "exact_bytes", 16), ("reads_report", "exact_reads", 1)):
        df = registry.QUERIES[name](spark, data)
        assert "lineitem" in plan(df) and {r[column] for r in df.collect()} == {each * keys}
