"""Order-aware passes over a stream that never put a whole lane into one task.

A lane (all rows of some keys) is cut into blocks of consecutive ``seq``; ranks
and running sums are taken inside a block and shifted by the totals of the
blocks before it, which is a table of one row a block.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import owner
from ..spec import SketchSpec
from . import cm

BLOCK = 1 << 16


def running_rank(s: DataFrame, lane: list[str], block: int = BLOCK) -> DataFrame:
    """Adds ``rank`` (1, 2, ... by seq within the lane) and ``lane_n`` (rows of the lane)."""
    s = s.withColumn("__b", F.floor(F.col("seq") / block))
    at = F.row_number().over(Window.partitionBy(*lane, "__b").orderBy("seq", "key"))
    over = Window.partitionBy(*lane).orderBy("__b")
    blocks = s.groupBy(*lane, "__b").agg(F.count("*").alias("__n"))
    blocks = blocks.select(*lane, "__b", F.coalesce(F.sum("__n").over(over.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"), F.sum("__n").over(Window.partitionBy(*lane)).alias("lane_n"))
    return s.withColumn("__at", at).join(blocks, [*lane, "__b"]).withColumn("rank", F.col("__at") + F.col("__before")).drop("__b", "__at", "__before")


def bucket(seq, grain: int):
    """Least i with seq <= i * grain."""
    return F.ceil(seq / F.lit(grain)).cast("bigint")


def grain_of(s: DataFrame, points: int = 200) -> int:
    """Spacing of time points so that a stream has about ``points`` of them; 1 for an empty one."""
    return max(1, (s.agg(F.max("seq")).first()[0] or 0) // points)


def f1_history(s: DataFrame, grain: int, by: list[str]) -> DataFrame:
    """(by, bucket, n, total): updates of each bucket, and up to its end."""
    n = s.groupBy(*by, bucket(F.col("seq"), grain).alias("bucket")).agg(F.sum("weight").cast("bigint").alias("n"))
    return n.withColumn("total", F.sum("n").over(Window.partitionBy(*by).orderBy("bucket")).cast("bigint"))


def f2_history(s: DataFrame, spec: SketchSpec, grain: int, points: DataFrame) -> DataFrame:
    """(part, bucket, f2) of the partitioned matrix at the end of each of the ``points(bucket)``.

    A counter going from c to c + v changes its square by 2cv + v^2, so one pass
    over increments per (bucket, cell) gives the squared rows of all prefixes.
    """
    own = owner(F.col("key"), spec)
    inc = s.groupBy("key", bucket(F.col("seq"), grain).alias("bucket")).agg(F.sum("weight").alias("f"))
    inc = inc.select(own.alias("part"), "bucket", "f", F.explode(cm.places(F.col("key"), spec)).alias("c")).groupBy("part", "bucket", F.col("c.row").alias("row"), F.col("c.col").alias("col")).agg(F.sum("f").cast("bigint").alias("v"))
    before = F.coalesce(F.sum("v").over(Window.partitionBy("part", "row", "col").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    c, v = F.col("c").cast("decimal(18,0)"), F.col("v").cast("decimal(18,0)")
    delta = inc.withColumn("c", before).select("part", "bucket", "row", (2 * c * v + v * v).cast(cm.BIG).alias("d"))
    rows = delta.groupBy("part", "bucket", "row").agg(F.sum("d").cast(cm.BIG).alias("d"))
    lanes = s.sparkSession.range(spec.P * spec.H).select(F.floor(F.col("id") / spec.H).cast("int").alias("part"), F.pmod("id", F.lit(spec.H)).cast("int").alias("row"))
    grid = points.select("bucket").distinct().crossJoin(F.broadcast(lanes)).select("part", "bucket", "row", F.lit(0).cast(cm.BIG).alias("d"), F.lit(1).alias("asked"))  # P * H rows a time point
    run = rows.withColumn("asked", F.lit(0)).unionByName(grid).withColumn("sq", F.sum("d").over(Window.partitionBy("part", "row").orderBy("bucket", "asked").rowsBetween(Window.unboundedPreceding, 0)))
    sums = run.filter("asked = 1").select("part", "row", "bucket", F.col("sq").cast(cm.BIG).alias("sq"))
    return sums.groupBy("part", "bucket").agg(F.min("sq").alias("f2"))
