"""Order-dependent replay of a composite sketch, one owner at a time.

Hand-overs reach an owner in flush order; each of their keys goes to its slot,
takes a free one, or updates the matrix and swaps with the lightest slot when
its estimate is higher.  An owner is one sequential writer, so its rows stream
through one task, in which it holds a matrix, C slots and H partial sums: the
state is bounded whatever the length of the stream.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..jvm import kernels, map_partitions
from ..spec import SketchSpec
from . import blocks, buffers, cm

STATE = (
    "part int, cells array<bigint>, slots array<struct<key:bigint,cnt:bigint,old:bigint,avg:double>>, f2rows array<decimal(38,0)>, "
    "v_begin bigint, v_end bigint, updates bigint, hits bigint, inserts bigint, misses bigint, swaps bigint"
)


class OwnerState:
    """Matrix, slots, partial sums and versions of one part, for the live sketch; batches have the same in ``jvm/Kernels.java``."""

    def __init__(self, spec: SketchSpec):
        self.spec = spec
        self.cells = [[0] * spec.K for _ in range(spec.H)]
        self.f2rows = [0] * spec.H
        self.slots: dict[int, list] = {}  # key -> [cnt, old, avg]
        self.cols: dict[int, list[int]] = {}  # columns of the slots' keys
        self.weakest: int | None = None  # key of the lightest slot, while known
        self.v_begin = self.v_end = 0
        self.updates = self.hits = self.inserts = self.misses = self.swaps = 0

    def _add(self, cols, v: int) -> int:
        """Add to the matrix, keep the partial sums, and return the estimate afterwards."""
        least = None
        for j, (row, col) in enumerate(zip(self.cells, cols, strict=True)):
            c = row[col]
            row[col] = n = c + v
            self.f2rows[j] += v * (c + n)  # n^2 - c^2
            if least is None or n < least:
                least = n
        return least

    def update(self, key: int, v: int, cols) -> None:
        self.updates += v
        slot = self.slots.get(key)
        if slot is not None:
            self.hits += 1
            slot[0] += v
            slot[2] = self.spec.w * v + (1 - self.spec.w) * slot[2]
            if key == self.weakest:
                self.weakest = None
        elif len(self.slots) < self.spec.C:
            self.inserts += 1
            self.slots[key], self.cols[key], self.weakest = [v, 0, float(v)], cols, None
        else:
            self.misses += 1
            est = self._add(cols, v)
            if not self.slots:
                return
            if self.weakest is None:
                self.weakest = min((x[0], k) for k, x in self.slots.items())[1]
            weakest = self.weakest
            cnt, old, _ = self.slots[weakest]
            if est > cnt:
                self.swaps += 1
                if cnt > old:
                    self._add(self.cols[weakest], cnt - old)
                del self.slots[weakest], self.cols[weakest]
                self.slots[key], self.cols[key], self.weakest = [est, est, float(v)], cols, None

    def row(self, part: int) -> dict:
        slots = [{"key": k, "cnt": s[0], "old": s[1], "avg": s[2]} for k, s in sorted(self.slots.items())]
        return {"part": part, "cells": [c for row in self.cells for c in row], "slots": slots, "f2rows": [Decimal(v) for v in self.f2rows], "v_begin": self.v_begin, "v_end": self.v_end} | {n: getattr(self, n) for n in ("updates", "hits", "inserts", "misses", "swaps")}


def _owner(spark, spec: SketchSpec, plain: bool):
    factors = ",".join(str(v) for j in range(spec.H) for v in spec.row(j))
    return kernels(spark).drain(spec.C, spec.H, spec.K, float(spec.w), spec.hash_family == "xxhash64", factors, plain)


def _drain(rows: DataFrame, spec: SketchSpec, plain: bool = False) -> DataFrame:
    """STATE rows from (owner, producer, flush_seq, key, cnt) rows that lie by owner and in flush order; a new (flush_seq, producer) is a new hand-over."""
    return map_partitions(rows.select("owner", "producer", "flush_seq", "key", "cnt"), _owner(rows.sparkSession, spec, plain), STATE)


#: STATE with one counter a producer, and the buffers that are still open; ``buffered`` is false where every update went to its owner directly.
FULL_STATE = STATE + ", buffered boolean, counters array<bigint>, open array<struct<producer:int,key:bigint,cnt:bigint>>"


def run(packed: DataFrame, spec: SketchSpec, plain: bool = False, after: int | None = None, until: int | None = None, kinds: str = "buffered") -> DataFrame:
    """FULL_STATE rows of a stream in ``blocks``, one an owner that any update reached and kind: ``buffered``, ``direct`` or ``both``.

    Buffers and owner are one pass: an owner takes a buffer in the moment that
    fills it, so hand-overs are neither written nor put in order.  The states
    are those of ``drain`` on ``buffers.replay``, and of ``replay_slots``.
    """
    modes = {"buffered": 1, "direct": 2, "both": 3}[kinds]
    owners = kernels(packed.sparkSession).replay(_owner(packed.sparkSession, spec, plain), spec.P, *blocks.limits(spec), not spec.self_buffer, modes)
    return map_partitions(blocks.routed(packed, spec, after, until), owners, FULL_STATE)


def still_open(state: DataFrame) -> DataFrame:
    """The buffers of FULL_STATE rows that nobody has taken, in the form of ``buffers.replay``."""
    return state.select(F.col("part").alias("owner"), F.explode("open").alias("b")).select("owner", "b.producer", "b.key", "b.cnt", F.lit(False).alias("handed"))


def f1(state: DataFrame) -> DataFrame:
    """One row: f1 of FULL_STATE rows, from one counter a producer."""
    each = state.select(F.posexplode("counters").alias("producer", "n")).groupBy("producer").agg(F.sum("n").alias("f1"))
    return each.agg(F.coalesce(F.sum("f1"), F.lit(0)).cast("bigint").alias("f1"))


def drain(handoffs: DataFrame, spec: SketchSpec, plain: bool = False) -> DataFrame:
    """STATE rows, one an owner that got anything, from the handed-over rows of ``buffers.replay``; ``plain`` owners serve point queries alone."""
    rows = handoffs.filter("handed").select("owner", "producer", "flush_seq", "pos", "key", "cnt")
    return _drain(rows.repartitionById(spec.P, "owner").sortWithinPartitions("owner", "flush_seq", "producer", "pos"), spec, plain)


def drain_split(handoffs: DataFrame, spec: SketchSpec, splits: int = 8) -> tuple[DataFrame, DataFrame]:
    """(cells, slots) of the parts, each drained by ``splits`` writers side by side: the form for few parts and many cores.

    A writer has the keys of one share of its part, and everything of them in
    order.  Their matrices add up; of their slots each part keeps the C with the
    highest counts, and what the others gained goes to the matrix.
    """
    share = F.pmod(F.xxhash64("key"), F.lit(splits))
    rows = handoffs.filter("handed").select((F.col("owner") * splits + share).cast("int").alias("owner"), "producer", "flush_seq", "pos", "key", "cnt")
    states = _drain(rows.repartitionById(spec.P * splits, "owner").sortWithinPartitions("owner", "flush_seq", "producer", "pos"), spec)
    states = states.withColumn("part", F.floor(F.col("part") / splits).cast("int"))
    ranked = unpack_slots(states).withColumn("rank", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("cnt"), "key")))
    slots = ranked.filter(F.col("rank") <= spec.C).drop("rank")
    gone = ranked.filter(F.col("rank") > spec.C).select("key", (F.col("cnt") - F.col("old")).alias("f")).filter("f > 0")
    return cm.merge(unpack_cells(states, spec), cm.from_frequencies(gone, spec, "parts")), slots


def merged_f2(cells: DataFrame, slots: DataFrame, spec: SketchSpec, projected: bool = True) -> DataFrame:
    """One row: f2 of ``drain_split``, with projected buffers or without buffers."""
    cnt = F.col("cnt") + (F.lit(spec.P / 2) * F.col("avg") if projected else F.lit(0.0))
    h = slots.agg(F.sum(F.pow(cnt.cast("double"), F.lit(2)) - F.pow(F.col("old").cast("double"), F.lit(2))).alias("h"))
    return cm.f2_plus_total(cells).crossJoin(h).select((F.col("f2").cast("double") + F.coalesce("h", F.lit(0.0))).alias("f2"))


def replay_slots(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """STATE rows of a stream whose every update goes to its owner directly, in seq order."""
    rows = s.select(owner(F.col("key"), spec).alias("owner"), F.lit(0).cast("bigint").alias("producer"), F.col("seq").alias("flush_seq"), "key", F.col("weight").cast("bigint").alias("cnt"))
    return _drain(rows.repartitionById(spec.P, "owner").sortWithinPartitions("owner", "flush_seq", "key"), spec)


def unpack_cells(state: DataFrame, spec: SketchSpec) -> DataFrame:
    """cells(part, row, col, cnt) of STATE rows."""
    at = state.select("part", F.posexplode("cells").alias("i", "cnt")).filter("cnt <> 0")
    return at.select("part", F.floor(F.col("i") / spec.K).cast("int").alias("row"), F.pmod("i", F.lit(spec.K)).cast("int").alias("col"), "cnt")


def unpack_slots(state: DataFrame) -> DataFrame:
    return state.select("part", F.explode("slots").alias("s")).select("part", "s.key", "s.cnt", "s.old", "s.avg")


def conserved_cells(state: DataFrame, handoffs: DataFrame | None, spec: SketchSpec) -> DataFrame:
    """Cells plus slot gains plus what is still buffered, all by hash: those of ``part_cm`` on the whole stream."""
    rest = unpack_slots(state).select("key", (F.col("cnt") - F.col("old")).alias("f")).filter("f > 0")
    if handoffs is not None:
        rest = rest.unionByName(handoffs.filter("NOT handed").groupBy("key").agg(F.sum("cnt").alias("f")))
    return cm.merge(unpack_cells(state, spec), cm.from_frequencies(rest, spec, "parts"))


def _least():
    return F.array_min("f2rows").cast("double")


def f2_projected(state: DataFrame, spec: SketchSpec) -> DataFrame:
    """(part, f2): partial sums and C slots of each part, nothing else is read."""
    half = spec.P / 2
    slots = F.aggregate("slots", F.lit(0.0), lambda a, s: a + F.pow(s["cnt"] + F.lit(half) * s["avg"], F.lit(2)) - F.pow(s["old"].cast("double"), F.lit(2)))
    return state.select("part", (_least() + slots).alias("f2"))


def f2_ignore_buffers(state: DataFrame) -> DataFrame:
    """(part, f2) of what owners have."""
    slots = F.aggregate("slots", F.lit(0.0), lambda a, s: a + F.pow(s["cnt"].cast("double"), F.lit(2)) - F.pow(s["old"].cast("double"), F.lit(2)))
    return state.select("part", (_least() + slots).alias("f2"))


def f2_exact_buffers(state: DataFrame, handoffs: DataFrame) -> DataFrame:
    """(part, f2) with every buffer read for every heavy key."""
    buf = handoffs.filter("NOT handed").groupBy("key").agg(F.sum("cnt").alias("buf"))
    heavy = unpack_slots(state).join(buf, "key", "left").groupBy("part").agg(F.sum(F.pow((F.col("cnt") + F.coalesce("buf", F.lit(0))).cast("double"), F.lit(2)) - F.pow(F.col("old").cast("double"), F.lit(2))).alias("h"))
    return state.join(heavy, "part", "left").select("part", (_least() + F.coalesce("h", F.lit(0.0))).alias("f2"))


def point(state: DataFrame, handoffs: DataFrame | None, keys: DataFrame, spec: SketchSpec) -> DataFrame:
    """(key, est): the slot of the key, else the least of its cells, plus its buffered counts."""
    base = cm.point(unpack_cells(state, spec), keys, spec, "parts").join(unpack_slots(state).select("key", "cnt"), "key", "left")
    est = F.coalesce("cnt", "est")
    if handoffs is not None:
        buf = handoffs.filter("NOT handed").groupBy("key").agg(F.sum("cnt").alias("buf"))
        base, est = base.join(buf, "key", "left"), est + F.coalesce("buf", F.lit(0))
    return base.select("key", est.cast("bigint").alias("est"))


def metrics(state: DataFrame, handoffs: DataFrame) -> DataFrame:
    """(part, updates, handoffs, hits, inserts, misses, swaps, mean_fill): what the replay counted."""
    fills = handoffs.filter("handed").groupBy(F.col("owner").alias("part"), "producer", "flush_seq").agg(F.sum("cnt").alias("fill"))
    fills = fills.groupBy("part").agg(F.count("*").alias("handoffs"), F.avg("fill").alias("mean_fill"))
    return state.select("part", "updates", "hits", "inserts", "misses", "swaps").join(fills, "part", "left")


def latest(states: DataFrame) -> DataFrame:
    """Per part the newest row whose two versions agree: the most hand-overs, then the most updates seen."""
    order = [F.desc(c) for c in ("v_end", "f1", "updates") if c in states.columns]
    newest = F.row_number().over(Window.partitionBy("part").orderBy(*order))
    return states.filter("v_begin = v_end").withColumn("n", newest).filter("n = 1").drop("n")
