"""Exact frequencies and moments, the truth that estimators are judged by."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BIG = "decimal(38,0)"
RUN = 100_000  # ranks that one row stands for at most while they are dealt out


def freq(s: DataFrame) -> DataFrame:
    """(key, f): one row per distinct key, summed on the map side first."""
    return s.groupBy("key").agg(F.sum("weight").alias("f"))


def counts(s: DataFrame) -> DataFrame:
    """(k, key, f): one row per distinct key as it was given, beside its folded form.

    The truth is counted on these: two keys that fold to one value are one key
    to a sketch, but not here.  Streams that carry folded keys alone count those.
    """
    if "k" not in s.columns:
        return freq(s).select(F.col("key").cast("string").alias("k"), "key", "f")
    return s.groupBy(F.col("k").cast("string").alias("k")).agg(F.first("key").alias("key"), F.sum("weight").alias("f"))


def moment(s: DataFrame, n: int) -> DataFrame:
    """One row: F_n, the sum of f^n over distinct keys (n = 0 counts them); 0 for an empty stream."""
    power = F.lit(1).cast(BIG)
    for _ in range(n):
        power = (power * F.col("f").cast("decimal(19,0)")).cast(BIG)
    return counts(s).agg(F.coalesce(F.sum(power), F.lit(0)).cast(BIG).alias(f"f{n}"))


def moments(s: DataFrame) -> DataFrame:
    """One row: n, f0, f1, f2, max_f."""
    f = F.col("f").cast("decimal(19,0)")
    return counts(s).agg(
        F.count("*").alias("f0"),
        F.coalesce(F.sum("f"), F.lit(0)).cast("bigint").alias("f1"),
        F.coalesce(F.sum((f * f).cast(BIG)), F.lit(0)).cast(BIG).alias("f2"),
        F.coalesce(F.max("f"), F.lit(0)).cast("bigint").alias("max_f"),
    )


def skew(s: DataFrame) -> DataFrame:
    """One row: z, minus the slope of log frequency on log rank.

    Ranks come from the histogram of frequencies, which has as many rows as
    there are distinct frequencies, so no task sorts all keys: the m keys of one
    frequency take the m ranks after those of higher frequencies.
    """
    hist = counts(s).groupBy("f").agg(F.count("*").alias("m"))
    above = F.coalesce(F.sum("m").over(Window.orderBy(F.desc("f")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    runs = hist.withColumn("a", above).select("f", F.col("a") + 1, F.explode(F.sequence(F.lit(0), F.col("m") - 1, F.lit(RUN))).alias("at"), (F.col("a") + F.col("m")).alias("last")).toDF("f", "first", "at", "last")
    pieces = runs.select("f", (F.col("first") + F.col("at")).alias("lo"), F.least(F.col("first") + F.col("at") + RUN - 1, F.col("last")).alias("hi")).repartition("lo")
    points = pieces.select(F.ln(F.col("f").cast("double")).alias("y"), F.explode(F.sequence("lo", "hi")).alias("r"))
    return points.select((-F.regr_slope("y", F.ln(F.col("r").cast("double")))).alias("z"))
