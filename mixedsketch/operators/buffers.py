"""Hand-off buffers between producers and owners.

Two forms.  ``chunks`` is the order-preserving one without a limit on keys: the
rows of a (producer, owner) lane fill buffers of B rows one after the other, so
a row's buffer follows from its rank in the lane.  ``combine`` is the production
form: a scan task is a producer, its buffers hold C keys or B counts each, and
what is shuffled is one row per buffered key, a bounded map-side combiner.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..jvm import kernels, map_partitions
from ..spec import SketchSpec
from . import prefix


def producer(spec: SketchSpec, grain: int | None = None):
    """round_robin deals rows by seq mod P; contiguous by ranges of ``grain`` consecutive seq."""
    if spec.producer == "round_robin":
        return F.pmod(F.col("seq"), F.lit(spec.P)).cast("int")
    return F.pmod(F.floor(F.col("seq") / F.lit(grain or 1000)), F.lit(spec.P)).cast("int")


def chunks(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """(seq, key, producer, owner, chunk, handed, flush_seq): unit-weight rows with the buffer they go through.

    A buffer is handed over by the row that fills it (``flush_seq``); the last,
    incomplete one of a lane stays (handed false, flush_seq null).  With
    B = None nothing is ever handed over.
    """
    rows = s.select("seq", "key", producer(spec).alias("producer"), owner(F.col("key"), spec).alias("owner"))
    if spec.B is None:
        return rows.select("*", F.lit(0).cast("bigint").alias("chunk"), F.lit(False).alias("handed"), F.lit(None).cast("bigint").alias("flush_seq"))
    ranked = prefix.running_rank(rows, ["producer", "owner"])
    ranked = ranked.withColumn("chunk", F.floor((F.col("rank") - 1) / spec.B).cast("bigint")).withColumn("handed", (F.col("chunk") + 1) * spec.B <= F.col("lane_n"))
    ends = ranked.filter(f"handed AND rank % {spec.B} = 0").select("producer", "owner", "chunk", F.col("seq").alias("flush_seq"))
    out = ranked.drop("rank", "lane_n").join(ends, ["producer", "owner", "chunk"], "left")
    return out.select("seq", "key", "producer", "owner", "chunk", "handed", "flush_seq")


def residual(rows: DataFrame) -> DataFrame:
    """(producer, owner, key, cnt): what still lies in buffers."""
    return rows.filter("NOT handed").groupBy("producer", "owner", "key").agg(F.count("*").alias("cnt"))


def buffered(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    """(owner, n, bound, ok): buffered rows of each owner against r = P * B."""
    bound = spec.P * spec.B if spec.B is not None else None
    n = rows.groupBy("owner").agg(F.sum((~F.col("handed")).cast("bigint")).alias("n"))
    return n.select("owner", "n", F.lit(bound).cast("bigint").alias("bound"), (F.col("n") <= F.lit(bound)).alias("ok"))


class Lane:
    """One buffer between a producer and an owner: at most ``keys`` keys, and ``total`` counts when it is handed over."""

    __slots__ = ("counts", "total")

    def __init__(self):
        self.counts: dict[int, int] = {}
        self.total = 0

    def add(self, key: int, weight: int, spec: SketchSpec) -> dict[int, int] | None:
        """The contents, if this update fills the buffer (it is empty afterwards)."""
        counts = self.counts
        counts[key] = counts.get(key, 0) + weight
        self.total += weight
        if len(counts) < spec.C and (spec.B is None or self.total < spec.B):
            return None
        self.counts, self.total = {}, 0
        return counts


HANDOFF = "owner int, producer long, flush_seq long, pos int, key long, cnt long, handed boolean"


def _lanes(rows: DataFrame, spec: SketchSpec, task_is_producer: bool) -> DataFrame:
    """HANDOFF rows of (seq, key, weight, producer, owner) rows, in the order of each partition."""
    direct = not spec.self_buffer and not task_is_producer  # own keys go to their slots at once
    run = kernels(rows.sparkSession).lanes(spec.P, spec.C, (1 << 63) - 1 if spec.B is None else spec.B, spec.flush_lag, direct, task_is_producer)
    return map_partitions(rows.select("seq", "key", "weight", "producer", "owner"), run, HANDOFF)


def replay(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """Hand-overs of every lane in stream order: rows of HANDOFF; handed is false for what stays buffered.

    Lanes are streamed in their tasks and hold at most C keys each.
    """
    rows = s.select("seq", "key", F.col("weight").cast("bigint").alias("weight"), producer(spec).alias("producer"), owner(F.col("key"), spec).alias("owner"))
    tasks = min(spec.P * spec.P, max(spec.P, int(s.sparkSession.conf.get("spark.sql.shuffle.partitions"))))  # a task may have several lanes
    lanes = rows.repartitionById(tasks, F.pmod(F.col("producer") * spec.P + F.col("owner"), F.lit(tasks)).cast("int")).sortWithinPartitions("seq", "key")
    return _lanes(lanes, spec, False)


def combine(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """The production form: no shuffle before the buffers; the scan task is the producer and its row numbers the order."""
    rows = s.select(F.lit(0).cast("bigint").alias("seq"), "key", F.col("weight").cast("bigint").alias("weight"), F.lit(0).alias("producer"), owner(F.col("key"), spec).alias("owner"))
    return _lanes(rows, spec, True)
