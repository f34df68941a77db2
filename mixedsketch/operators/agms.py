"""Signed sketches: the bucketed second-moment sketch, and the original one of single counters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import row_and_sign, row_text, sign, sign_text
from ..spec import SketchSpec
from . import cm, exact


UNROLLED = 16  # rows up to which each has its own expression; more of them would outgrow a compiled method


def build(s: DataFrame, spec: SketchSpec, by: list[str] | None = None) -> DataFrame:
    """cells(part, row, col, cnt) with signed counts; a cell may sum to 0.  ``by`` adds grouping columns: one sketch per group."""
    return from_frequencies(s.groupBy(*(by or []), "key").agg(F.sum("weight").alias("f")), spec, by)


def from_frequencies(keys: DataFrame, spec: SketchSpec, by: list[str] | None = None) -> DataFrame:
    """Signed cells of (key, f) rows."""
    keep = by or []
    x = F.col("key")
    if spec.H > UNROLLED:
        rows = keys.select(*keep, "key", "f", F.explode(F.sequence(F.lit(0), F.lit(spec.H - 1))).alias("row"))
        col, plus = row_and_sign(x, F.col("row"), spec)
        cells = rows.select(*keep, F.lit(0).alias("part"), "row", col.alias("col"), (plus * F.col("f")).alias("v"))
        return cells.groupBy(*keep, "part", "row", "col").agg(F.sum("v").cast("bigint").alias("cnt"))
    at = ", ".join(f"named_struct('row', {j}, 'col', {row_text('`key`', spec, j)}, 'v', {sign_text('`key`', spec, j)} * f)" for j in range(spec.H))
    cells = keys.select(*keep, F.lit(0).alias("part"), F.explode(F.expr(f"array({at})")).alias("c"))
    return cells.groupBy(*keep, "part", F.col("c.row").alias("row"), F.col("c.col").alias("col")).agg(F.sum("c.v").cast("bigint").alias("cnt"))


def f2(cells: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row: f2, the median over rows of squared signed counters."""
    return cm.median_of_rows(cm.f2_rows(cells), spec.H).select("f2")


def classic(s: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row: f2, the mean over H copies of one squared signed counter each (single pass, no buckets)."""
    x = F.col("key")
    sums = exact.freq(s).agg(*[F.coalesce(F.sum(sign(x, spec, j) * F.col("f")), F.lit(0)).alias(f"c{j}") for j in range(spec.H)])
    total = cm.square(F.col("c0"))
    for j in range(1, spec.H):
        total = (total + cm.square(F.col(f"c{j}"))).cast(cm.BIG)
    return sums.select(F.floor(total / spec.H).cast(cm.BIG).alias("f2"))
