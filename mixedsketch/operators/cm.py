"""Count-Min matrices as long tables, and what is estimated from them.

A matrix is ``cells(part, row, col, cnt)`` with zero cells left out.  Keys are
summed before their H cells are made, so a frequent key costs one row a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import owner_text, row_hash, row_text
from ..spec import SketchSpec
from . import exact

BIG = "decimal(38,0)"


def square(c: Column) -> Column:
    return (c.cast("decimal(19,0)") * c.cast("decimal(19,0)")).cast(BIG)


def places(x: Column, spec: SketchSpec, width: Column | None = None) -> Column:
    """Array of (row, col) of a folded key; ``width`` shifts the columns of aligned wide matrices."""
    return F.array(*[F.struct(F.lit(j).alias("row"), (row_hash(x, spec, j) + (width if width is not None else F.lit(0))).cast("int").alias("col")) for j in range(spec.H)])


def key_places(spec: SketchSpec, layout: str) -> tuple[Column, Column]:
    """(part, ``places``) of ``key`` in a layout, each as one expression."""
    own = owner_text("`key`", spec)
    shift = f"{own} * {spec.K}" if layout == "wide" else "0"
    cells = ", ".join(f"named_struct('row', {j}, 'col', CAST({row_text('`key`', spec, j)} + {shift} AS INT))" for j in range(spec.H))
    return F.expr(own if layout == "parts" else "0"), F.expr(f"array({cells})")


def from_frequencies(f: DataFrame, spec: SketchSpec, layout: str = "single", by: list[str] | None = None) -> DataFrame:
    """Cells of (key, f) rows.

    Layouts: ``single`` (one H x K matrix, part 0), ``parts`` (each owner its own),
    ``wide`` (one H x P*K matrix whose columns are owner * K + hash: aligned with
    ``parts``).  ``by`` adds grouping columns: one sketch per group.
    """
    part, at = key_places(spec, layout)
    keep = by or []
    cells = f.select(*keep, part.alias("part"), "f", F.explode(at).alias("c"))
    return cells.groupBy(*keep, "part", F.col("c.row").alias("row"), F.col("c.col").alias("col")).agg(F.sum("f").cast("bigint").alias("cnt"))


def build(s: DataFrame, spec: SketchSpec, layout: str = "single", by: list[str] | None = None) -> DataFrame:
    """Cells of a stream of (key, weight)."""
    keys = s.groupBy(*(by or []), "key").agg(F.sum("weight").alias("f"))
    return from_frequencies(keys, spec, layout, by)


def merge(*cells: DataFrame) -> DataFrame:
    """The sketch of the union of streams: cells add up."""
    both = cells[0]
    for c in cells[1:]:
        both = both.unionByName(c)
    return both.groupBy("part", "row", "col").agg(F.sum("cnt").cast("bigint").alias("cnt"))


def point(cells: DataFrame, keys: DataFrame, spec: SketchSpec, layout: str = "single") -> DataFrame:
    """(key, est) for distinct ``keys(key)``; a missing cell counts 0.

    Keys are asked in sets of any size: cells meet them in an equi join, which
    Spark broadcasts when the smaller side is small.
    """
    part, at = key_places(spec, layout)
    asked = keys.select("key").distinct()
    asked = asked.select("key", part.alias("part"), F.explode(at).alias("c")).select("key", "part", F.col("c.row").alias("row"), F.col("c.col").alias("col"))
    return asked.join(cells, ["part", "row", "col"], "left").groupBy("key").agg(F.min(F.coalesce("cnt", F.lit(0))).cast("bigint").alias("est"))


def f1(cells: DataFrame, row: int = 0) -> DataFrame:
    """One row: f1, exact from any row of the matrix."""
    return cells.filter(F.col("row") == row).agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("bigint").alias("f1"))


def f2_rows(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(part, row, sq): the sum of squared counters of each row."""
    return cells.groupBy(*(by or []), "part", "row").agg(F.sum(square(F.col("cnt"))).cast(BIG).alias("sq"))


def f2_plus(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(part, f2): least row of squared counters; never below the truth."""
    return f2_rows(cells, by).groupBy(*(by or []), "part").agg(F.min("sq").alias("f2"))


def f2_plus_total(cells: DataFrame) -> DataFrame:
    """One row: f2, summed over parts."""
    return f2_plus(cells).agg(F.coalesce(F.sum("f2"), F.lit(0)).cast(BIG).alias("f2"))


def f2_minus(cells: DataFrame, spec: SketchSpec) -> DataFrame:
    """(part, f2): median over rows of the squared differences of neighbouring column pairs, for little skew.

    For an even number of rows the mean of the middle two, cut to whole numbers.
    A part none of whose rows has cells is missing.
    """
    signed = F.when(F.col("col") % 2 == 0, F.col("cnt")).otherwise(-F.col("cnt"))
    pairs = cells.groupBy("part", "row", F.floor(F.col("col") / 2).alias("pair")).agg(F.sum(signed).alias("d"))
    rows = pairs.groupBy("part", "row").agg(F.sum(square(F.col("d"))).cast(BIG).alias("sq"))
    return median_of_rows(rows, spec.H)


def median_of_rows(rows: DataFrame, h: int, by: list[str] | None = None) -> DataFrame:
    sq = F.array_sort(F.collect_list("sq"))  # at most H entries
    lo, hi = F.element_at(sq, (h + 1) // 2), F.element_at(sq, h // 2 + 1)
    return rows.groupBy(*(by or []), "part").agg(F.floor((lo + hi) / 2).cast(BIG).alias("f2"))


def f2_auto(s: DataFrame, spec: SketchSpec, z: float | None = None) -> DataFrame:
    """(z, kind, f2): the squared-counter estimate for z > 1, the paired-difference one otherwise.

    Both come from one matrix; which is returned is decided in the plan, so no
    intermediate answer goes through the driver.
    """
    f = exact.freq(s)
    cells = from_frequencies(f, spec)
    skew = exact.skew(s) if z is None else s.sparkSession.createDataFrame([(float(z),)], "z double")
    plus = f2_plus_total(cells).withColumnRenamed("f2", "plus")
    minus = f2_minus(cells, spec).agg(F.coalesce(F.sum("f2"), F.lit(0)).cast(BIG).alias("minus"))
    steep = F.col("z") > 1
    return skew.crossJoin(plus).crossJoin(minus).select("z", F.when(steep, "plus").otherwise("minus").alias("kind"), F.when(steep, F.col("plus")).otherwise(F.col("minus")).alias("f2"))


def inner(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: est, an upper estimate of the join size of two streams with one spec."""
    rows = a.join(b.withColumnRenamed("cnt", "other"), ["part", "row", "col"]).groupBy("row").agg(F.sum((F.col("cnt").cast("decimal(19,0)") * F.col("other").cast("decimal(19,0)")).cast(BIG)).alias("v"))
    return rows.agg(F.coalesce(F.min("v"), F.lit(0)).cast(BIG).alias("est"))


def dyadic_build(s: DataFrame, value: Column, bits: int, spec: SketchSpec) -> DataFrame:
    """Cells (level, part, row, col, cnt) of the dyadic ranges of an integer ``value`` below 2^bits."""
    levels = F.explode(F.array(*[F.struct(F.lit(i).alias("level"), F.shiftright(value, i).alias("range")) for i in range(bits)]))
    ranges = s.select(levels.alias("d"), "weight").select(F.col("d.level").alias("level"), F.col("d.range").alias("key"), "weight")
    return build(ranges, spec, by=["level"])


def dyadic_quantile(cells: DataFrame, total: int, q: float, bits: int, spec: SketchSpec) -> int:
    """Smallest value whose estimated rank reaches q * total, by one point query a level (``bits`` small jobs)."""
    spark, low, need = cells.sparkSession, 0, q * total
    for level in range(bits - 1, -1, -1):
        half = low >> level
        est = point(cells.filter(F.col("level") == level).drop("level"), spark.createDataFrame([(half,)], "key bigint"), spec).first()["est"]
        if est < need:
            need -= est
            low += 1 << level
    return low
