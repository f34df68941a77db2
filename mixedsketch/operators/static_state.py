"""A composite sketch in tables: what owners have, in cells and slots, and what lies in buffers.

Slots are the C heaviest handed-over keys of each owner (static slots: old = 0),
buffers the unlimited-key form.  All of it is order-free given the chunks, so
every answer has an exact SQL twin.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..spec import SketchSpec
from . import buffers, cm


@dataclass
class State:
    spec: SketchSpec
    chunks: DataFrame
    cells: DataFrame
    slots: DataFrame
    residual: DataFrame


def ewma(flushes: DataFrame, w: float) -> DataFrame:
    """(part, key, avg): the moving average of a key's counts over flushes, in flush order.

    In closed form: the last flush weighs w, the one before it w(1-w), and so on;
    the first weighs what is left.
    """
    order = Window.partitionBy("part", "key").orderBy(F.desc("flush_seq"), F.desc("producer"))
    aged = flushes.withColumn("age", F.row_number().over(order) - 1).withColumn("n", F.count("*").over(Window.partitionBy("part", "key")))
    factor = F.pow(F.lit(1 - w), F.col("age")) * F.when(F.col("age") == F.col("n") - 1, F.lit(1.0)).otherwise(F.lit(w))
    return aged.groupBy("part", "key").agg(F.sum(factor * F.col("v")).alias("avg"))


def build(s: DataFrame, spec: SketchSpec, until: int | None = None) -> State:
    """State after the whole stream, or after ``until`` (hand-overs and rows later than it have not happened)."""
    rows = buffers.chunks(s, spec)
    if until is not None:
        rows = rows.filter(F.col("seq") <= until).withColumn("handed", F.coalesce(F.col("handed") & (F.col("flush_seq") <= until), F.lit(False)))
    handed = rows.filter("handed").groupBy("key").agg(F.count("*").alias("f")).withColumn("part", owner(F.col("key"), spec))
    rank = F.row_number().over(Window.partitionBy("part").orderBy(F.desc("f"), "key"))
    heavy = handed.withColumn("rank", rank).filter(F.col("rank") <= spec.C).select("part", "key", F.col("f").alias("cnt"))
    few = F.broadcast(heavy.select("key"))  # at most P * C keys
    light = handed.join(few, "key", "left_anti").select("key", "f")
    flushes = rows.filter("handed").join(few, "key", "left_semi").groupBy(F.col("owner").alias("part"), "key", "producer", "flush_seq").agg(F.count("*").alias("v"))
    slots = heavy.join(ewma(flushes, spec.w), ["part", "key"]).select("part", "key", "cnt", F.lit(0).cast("bigint").alias("old"), "avg")
    return State(spec, rows, cm.from_frequencies(light, spec, "parts"), slots, buffers.residual(rows))


def _buffered(state: State) -> DataFrame:
    return state.residual.groupBy("key").agg(F.sum("cnt").cast("bigint").alias("buf"))


def point(state: State, keys: DataFrame) -> DataFrame:
    """(key, est): slot or cells at the owner, plus what the buffers hold of the key."""
    base = cm.point(state.cells, keys, state.spec, "parts")
    out = base.join(state.slots.select("key", "cnt"), "key", "left").join(_buffered(state), "key", "left")
    return out.select("key", (F.coalesce("cnt", "est") + F.coalesce("buf", F.lit(0))).cast("bigint").alias("est"))


def f1(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row: f1 from one counter a producer."""
    counters = s.groupBy(buffers.producer(spec).alias("producer")).agg(F.sum("weight").alias("f1"))
    return counters.agg(F.coalesce(F.sum("f1"), F.lit(0)).cast("bigint").alias("f1"))


def _with_slots(state: State, per_slot) -> DataFrame:
    heavy = state.slots.join(_buffered(state), "key", "left").withColumn("buf", F.coalesce("buf", F.lit(0)))
    h = heavy.agg(F.sum(per_slot).alias("h"))
    return cm.f2_plus_total(state.cells).crossJoin(h)


def f2_exact_buffers(state: State) -> DataFrame:
    """One row: f2, with the buffers read for every heavy key (light keys in buffers are left out)."""
    v = (cm.square(F.col("cnt") + F.col("buf")) - cm.square(F.col("old"))).cast(cm.BIG)
    return _with_slots(state, v).select((F.col("f2") + F.coalesce("h", F.lit(0))).cast(cm.BIG).alias("f2"))


def f2_ignore_buffers(state: State) -> DataFrame:
    """One row: f2 of what owners have."""
    v = (cm.square(F.col("cnt")) - cm.square(F.col("old"))).cast(cm.BIG)
    return _with_slots(state, v).select((F.col("f2") + F.coalesce("h", F.lit(0))).cast(cm.BIG).alias("f2"))


def f2_projected(state: State) -> DataFrame:
    """One row: f2 (double), each heavy key's buffers replaced by P half-full ones of its average flush."""
    v = F.pow(F.col("cnt") + F.lit(state.spec.P / 2) * F.col("avg"), F.lit(2)) - F.pow(F.col("old").cast("double"), F.lit(2))
    return cm.f2_plus_total(state.cells).crossJoin(state.slots.agg(F.sum(v).alias("h"))).select((F.col("f2").cast("double") + F.coalesce("h", F.lit(0.0))).alias("f2"))


def drained(state: State) -> DataFrame:
    """Cells by part after every slot's gain and every buffer has gone into its matrix: those of ``part_cm`` on all rows."""
    gains = state.slots.select("key", (F.col("cnt") - F.col("old")).alias("f"))
    rest = state.residual.select("key", F.col("cnt").alias("f"))
    return cm.merge(state.cells, cm.from_frequencies(gains.unionByName(rest), state.spec, "parts"))


def exclusive_f1(state: State) -> DataFrame:
    """One row: f1 under the exclusive policy: a row of every matrix, the gains of slots, and buffers."""
    row = cm.f1(state.cells)
    gain = state.slots.agg(F.coalesce(F.sum(F.col("cnt") - F.col("old")), F.lit(0)).alias("g"))
    rest = state.residual.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("b"))
    return row.crossJoin(gain).crossJoin(rest).select((F.col("f1") + F.col("g") + F.col("b")).cast("bigint").alias("f1"))


def exclusive_f2(state: State, merge: str = "partitioned") -> DataFrame:
    """One row: f2 after draining; parts keep their own rows, or are added cell by cell first (``elementwise``)."""
    cells = drained(state)
    if merge == "elementwise":
        cells = cells.groupBy(F.lit(0).alias("part"), "row", "col").agg(F.sum("cnt").cast("bigint").alias("cnt"))
    return cm.f2_plus_total(cells)


def topk(state: State, k: int) -> DataFrame:
    """(key, est): the k heaviest slot keys with their buffers."""
    return state.slots.join(_buffered(state), "key", "left").select("key", (F.col("cnt") + F.coalesce("buf", F.lit(0))).cast("bigint").alias("est")).orderBy(F.desc("est"), "key").limit(k)
