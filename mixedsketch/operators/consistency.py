"""Intervals of permitted answers, relaxation bounds, and monotonicity between query types."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..spec import SketchSpec
from . import buffers, cm, prefix


def _intervals(s: DataFrame, spec: SketchSpec, grain: int, every: int) -> DataFrame:
    """(t_start, t_end, part, t): queries that begin every ``every`` buckets and read part i in bucket t_start + i."""
    last = s.agg(F.coalesce(F.max(prefix.bucket(F.col("seq"), grain)), F.lit(0)).alias("last"))
    starts = last.select(F.explode(F.sequence(F.lit(0).cast("bigint"), F.greatest(F.col("last") - spec.P, F.lit(0)).cast("bigint"), F.lit(every).cast("bigint"))).alias("t_start"))
    parts = F.explode(F.sequence(F.lit(0), F.lit(spec.P - 1))).alias("part")
    return starts.select("t_start", (F.col("t_start") + spec.P).alias("t_end"), parts).withColumn("t", F.col("t_start") + F.col("part"))


def _at(history: DataFrame, points: DataFrame, by: str, value: str) -> DataFrame:
    """The history's last ``value`` at or before each (by, t) of ``points``: an as-of join on one row a bucket."""
    both = points.select(by, F.col("t").alias("bucket"), F.lit(None).cast(history.schema[value].dataType).alias(value), F.lit(1).alias("asked")).unionByName(history.select(by, "bucket", value, F.lit(0).alias("asked")))
    order = Window.partitionBy(by).orderBy("bucket", "asked")
    return both.withColumn(value, F.last(value, ignorenulls=True).over(order)).filter("asked = 1").select(by, F.col("bucket").alias("t"), F.coalesce(value, F.lit(0)).alias(value)).distinct()


def ivl_f1(s: DataFrame, spec: SketchSpec, grain: int, every: int = 4) -> DataFrame:
    """(t_start, t_end, lo, val, hi, inside): the count read from one producer counter after another."""
    s = s.withColumn("part", buffers.producer(spec))
    history = prefix.f1_history(s, grain, ["part"]).select("part", "bucket", F.col("total").alias("v"))
    return _interval_table(_intervals(s, spec, grain, every), history, "bigint")


def ivl_f2(s: DataFrame, spec: SketchSpec, grain: int, every: int = 4) -> DataFrame:
    """(t_start, t_end, lo, val, hi, inside): the partitioned estimate, parts read one after another."""
    asked = _intervals(s, spec, grain, every)
    times = asked.select(F.explode(F.array("t_start", "t", "t_end")).alias("bucket")).distinct()
    history = prefix.f2_history(s, spec, grain, times).select("part", "bucket", F.col("f2").alias("v"))
    return _interval_table(asked, history, cm.BIG)


def _interval_table(asked: DataFrame, history: DataFrame, kind: str) -> DataFrame:
    points = asked.select("part", F.explode(F.array("t_start", "t", "t_end")).alias("t")).distinct()
    value = _at(history, points, "part", "v")
    out = asked
    for name, column in (("lo", "t_start"), ("val", "t"), ("hi", "t_end")):
        out = out.join(value.select("part", F.col("t").alias(column), F.col("v").alias(name)), ["part", column])
    sums = out.groupBy("t_start", "t_end").agg(*[F.sum(c).cast(kind).alias(c) for c in ("lo", "val", "hi")])
    return sums.withColumn("inside", (F.col("lo") <= F.col("val")) & (F.col("val") <= F.col("hi")))


def relaxed_bound(s: DataFrame, spec: SketchSpec, grain: int) -> DataFrame:
    """(part, bucket, total, seen, bound, ok): rows that arrived and rows handed over by each time point, and r = P * B."""
    rows = buffers.chunks(s, spec)
    came = rows.groupBy(F.col("owner").alias("part"), prefix.bucket(F.col("seq"), grain).alias("bucket")).agg(F.count("*").alias("n"))
    gone = rows.filter("handed").groupBy(F.col("owner").alias("part"), prefix.bucket(F.col("flush_seq"), grain).alias("bucket")).agg(F.count("*").alias("h"))
    both = came.join(gone, ["part", "bucket"], "full")
    over = Window.partitionBy("part").orderBy("bucket")
    run = both.select("part", "bucket", F.sum(F.coalesce("n", F.lit(0))).over(over).alias("total"), F.sum(F.coalesce("h", F.lit(0))).over(over).alias("seen"))
    bound = spec.P * spec.B
    return run.select("part", "bucket", "total", "seen", F.lit(bound).cast("bigint").alias("bound"), (F.col("total") - F.col("seen") <= bound).alias("ok"))


def visibility(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """(seq, key, t_point, t_f1, t_f2): the step at which an update shows to each query type; null for never.

    Three steps a row: into the buffer, counted by the producer, handed over.
    """
    return buffers.chunks(s, spec).select("seq", "key", (3 * F.col("seq")).alias("t_point"), (3 * F.col("seq") + 1).alias("t_f1"), (3 * F.col("flush_seq") + 2).alias("t_f2"))


QUERIES = ["point", "f1", "f2"]


def monotone_matrix(s: DataFrame, spec: SketchSpec, grain: int) -> DataFrame:
    """(q1, q2, worst, bound, ok): the most updates that a query sees and the next one, right after it, does not.

    Asked right after some row has entered its buffer, once a ``grain`` of rows
    (the last such moment of each), when its producer has not counted it yet.
    The updates that q1 sees by T and q2 does not are those of t_q1 <= T less
    those of max(t_q1, t_q2) <= T, and such a maximum is one of the three times,
    so three histograms over the time points answer all nine pairs.
    """
    seen = visibility(s, spec).withColumn("part", owner(F.col("key"), spec))
    times = F.explode(F.array(*[F.struct(F.lit(q).alias("q"), F.col(f"t_{q}").alias("t")) for q in QUERIES])).alias("x")
    # the moments are the t_point of the last row of each grain, 3 * grain * i: the first one not before t is number ceil(t / (3 * grain))
    hist = seen.select("part", times).select("part", "x.q", F.ceil(F.col("x.t") / F.lit(3 * grain)).cast("bigint").alias("bucket")).filter("bucket IS NOT NULL").groupBy("part", "q", "bucket").agg(F.count("*").alias("n"))
    bound = {("point", "f1"): spec.P, ("point", "f2"): spec.P * spec.B, ("f1", "f2"): spec.P * spec.P * spec.B}
    worst = None
    for local in (True, False):  # a point query sees one part, the others all of them
        by = ["part", "bucket"] if local else ["bucket"]
        counts = hist.groupBy(*by).agg(*[F.sum(F.when(F.col("q") == q, F.col("n")).otherwise(0)).alias(q) for q in QUERIES])
        over = Window.partitionBy(*by[:-1]).orderBy("bucket")  # a row a time point
        run = counts.select("bucket", *[F.sum(q).over(over).alias(q) for q in QUERIES])
        pairs = [(a, b, F.greatest(F.col(a) - F.col(b), F.lit(0)), bound.get((a, b), 0)) for a in QUERIES for b in QUERIES if (a == "point") == local]
        cells = F.explode(F.array(*[F.struct(F.lit(a).alias("q1"), F.lit(b).alias("q2"), d.cast("bigint").alias("d"), F.lit(r).cast("bigint").alias("bound")) for a, b, d, r in pairs])).alias("c")
        rows = run.select(cells).groupBy("c.q1", "c.q2", "c.bound").agg(F.max("c.d").alias("worst"))
        worst = rows if worst is None else worst.unionByName(rows)
    return worst.select("q1", "q2", F.col("worst").cast("bigint").alias("worst"), "bound", (F.col("worst") <= F.col("bound")).alias("ok"))
