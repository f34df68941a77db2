"""The ladder of estimators of the second moment, from one matrix to slots in front of parts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..spec import SketchSpec
from . import agms, cm, exact, slots


def owner_load(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """(part, keys, updates): how evenly owners share keys and updates."""
    return exact.freq(s).groupBy(owner(F.col("key"), spec).alias("part")).agg(F.count("*").alias("keys"), F.sum("f").cast("bigint").alias("updates"))


def single(s: DataFrame, spec: SketchSpec) -> DataFrame:
    return cm.f2_plus_total(cm.build(s, spec))


def wide(s: DataFrame, spec: SketchSpec, aligned: bool = True) -> DataFrame:
    """One H x (P*K) matrix; aligned columns make it comparable with ``part_cm`` as an inequality."""
    return cm.f2_plus_total(cm.build(s, spec, "wide") if aligned else cm.build(s, spec.but(K=spec.P * spec.K)))


def part_cm(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """P matrices, one a sub-domain; each chooses its best row."""
    return cm.f2_plus_total(cm.build(s, spec, "parts"))


def part_slots(s: DataFrame, spec: SketchSpec) -> DataFrame:
    return slots.f2(*slots.settled(s, spec))


def report(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """(method, f2, exact): every rung on one stream beside the truth."""
    truth = exact.moments(s).select(F.col("f2").alias("exact"))
    rungs = {"single": single(s, spec), "wide": wide(s, spec), "part_cm": part_cm(s, spec), "part_slots": part_slots(s, spec), "agms": agms.f2(agms.build(s, spec), spec), "minus": cm.f2_minus(cm.build(s, spec), spec).select("f2")}
    out = None
    for name, df in rungs.items():
        row = df.select(F.lit(name).alias("method"), "f2")
        out = row if out is None else out.unionByName(row)
    return out.crossJoin(truth)


def concurrent(s: DataFrame, spec: SketchSpec, kind: str, t0: int, step: int) -> DataFrame:
    """One row: f2 of a rung whose part i is read at t0 + i * step, each counter or part at one moment.

    ``kind``: wide (aligned), part_cm or part_slots.  What a part has seen by
    its moment is a prefix of its rows, so the answer lies between those at the
    first and the last moment.
    """
    seen = s.filter(F.col("seq") <= F.lit(t0) + owner(F.col("key"), spec) * F.lit(step))
    return {"wide": wide, "part_cm": part_cm, "part_slots": part_slots}[kind](seen, spec)
