"""Heavy-key slots in front of the matrices of a partitioned sketch.

``settled`` is the order-free form for batches: the C heaviest keys of every
owner have slots from the start, so nothing of them is in the matrix (old = 0).
The order-dependent form, in which keys earn their slots as updates arrive, is
replayed per owner in ``composite``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..spec import SketchSpec
from . import cm, exact


def settled(s: DataFrame, spec: SketchSpec) -> tuple[DataFrame, DataFrame]:
    """(cells of the light keys by part, slots(part, key, cnt, old)).

    The rank filter is one that Spark applies before the exchange as well, so a
    task sends at most C keys an owner.  Ties go to the smaller key.
    """
    f = exact.freq(s).withColumn("part", owner(F.col("key"), spec))
    rank = F.row_number().over(Window.partitionBy("part").orderBy(F.desc("f"), "key"))
    heavy = f.withColumn("rank", rank).filter(F.col("rank") <= spec.C)
    slots = heavy.select("part", "key", F.col("f").cast("bigint").alias("cnt"), F.lit(0).cast("bigint").alias("old"))
    light = f.join(F.broadcast(slots.select("key")), "key", "left_anti")  # at most P * C keys
    return cm.from_frequencies(light.select("key", "f"), spec, "parts"), slots


def settled_by(f: DataFrame, spec: SketchSpec, by: list[str]) -> tuple[DataFrame, DataFrame]:
    """(heavy, light) rows (by, key, f) of labelled counts (by, key, weight): the C heaviest keys of each owner in each group, and the rest."""
    f = f.groupBy(*by, "key").agg(F.sum("weight").alias("f")).withColumn("part", owner(F.col("key"), spec))
    ranked = f.withColumn("rank", F.row_number().over(Window.partitionBy(*by, "part").orderBy(F.desc("f"), "key")))
    return ranked.filter(F.col("rank") <= spec.C).select(*by, "key", "f"), ranked.filter(F.col("rank") > spec.C).select(*by, "key", "f")


def f2(cells: DataFrame, slots: DataFrame) -> DataFrame:
    """One row: f2 = least squared rows of the parts + sum over slots of cnt^2 - old^2; never below the truth."""
    light = cm.f2_plus_total(cells)
    heavy = slots.agg(F.coalesce(F.sum((cm.square(F.col("cnt")) - cm.square(F.col("old"))).cast(cm.BIG)), F.lit(0)).cast(cm.BIG).alias("h"))
    return light.crossJoin(heavy).select((F.col("f2") + F.col("h")).cast(cm.BIG).alias("f2"))


def point(cells: DataFrame, slots: DataFrame, keys: DataFrame, spec: SketchSpec) -> DataFrame:
    """(key, est): the slot's count where the key has one, else the least of its cells."""
    light = cm.point(cells, keys, spec, "parts")
    return light.join(slots.select("key", F.col("cnt").alias("slot")), "key", "left").select("key", F.coalesce("slot", "est").alias("est"))
