"""Accuracy, memory and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..spec import BUFFER_HEAD_BYTES, BUFFER_KEY_BYTES, COUNTER_BYTES, SLOT_BYTES, SketchSpec, fit_width
from . import cm, exact


def mape(estimates: DataFrame, by: list[str]) -> DataFrame:
    """(by, mape): mean of |f2 - exact| / exact over the rows of each group; rows with exact 0 are left out."""
    err = F.abs(F.col("f2").cast("double") - F.col("exact").cast("double")) / F.col("exact").cast("double")
    return estimates.filter("exact <> 0").groupBy(*by).agg(F.avg(err).alias("mape"))


def point_error(est: DataFrame, truth: DataFrame, heavy_from: int) -> DataFrame:
    """(kind, n, avg_error, max_error, exact_share) over asked keys: heavy, light, and absent ones."""
    both = est.join(truth, "key", "left").withColumn("f", F.coalesce("f", F.lit(0)))
    kind = F.when(F.col("f") == 0, "absent").when(F.col("f") >= heavy_from, "heavy").otherwise("light")
    e = F.abs(F.col("est") - F.col("f"))
    return both.groupBy(kind.alias("kind")).agg(F.count("*").alias("n"), F.avg(e.cast("double")).alias("avg_error"), F.max(e).cast("bigint").alias("max_error"), F.avg((e == 0).cast("double")).alias("exact_share"))


#: One worker's sketches where every query type has its own, in the published comparison: matrix and signed sketch.
SEPARATE = SketchSpec(H=6, K=8192)
HLL_BYTES = 4096  # 2^12 registers


def separate_bytes(matrix: SketchSpec, signed: SketchSpec, distinct: bool = False) -> int:
    """Bytes of one worker's set of sketches."""
    return COUNTER_BYTES * (matrix.H * matrix.K + signed.H * signed.K) + (HLL_BYTES if distinct else 0)


def memory_bytes(spec: SketchSpec, layout: str, matrix: SketchSpec = SEPARATE, signed: SketchSpec = SEPARATE) -> tuple[int, int]:
    """(a part, all parts) in bytes with the columns that fit the budget; ``separate`` is a set of sketches of their own sizes a worker."""
    if layout.startswith("separate"):
        part = separate_bytes(matrix, signed, layout == "separate_f0")
        return part, part * spec.P
    k = fit_width(spec, layout)
    part = COUNTER_BYTES * spec.H * k
    part += spec.C * SLOT_BYTES if layout in ("slots", "composite") else 0
    part += spec.P * (spec.C * BUFFER_KEY_BYTES + BUFFER_HEAD_BYTES) if layout == "composite" else 0
    return part, part * spec.P


def reads(spec: SketchSpec, method: str) -> int:
    """Counters a second-moment query reads: all matrices and buffers, matrices and slots, or partial sums and slots."""
    P, H, K, C = spec.P, spec.H, spec.K, spec.C
    return {"exact_buffers": P * H * K + P * P * C + 2 * P * C, "ignore_buffers": P * (H + 2 * C), "projected": P * (H + 3 * C), "single": H * K, "wide": H * P * K, "part_cm": P * H * K}[method]


EXACT_KEY_BYTES = 16  # a key and its count


def _keys(s: DataFrame) -> DataFrame:
    """One row: keys, the distinct keys of a stream, which are what exact counting holds and reads."""
    return exact.counts(s).agg(F.count("*").alias("keys"))


def memory_report(s: DataFrame, spec: SketchSpec, parts: list[int]) -> DataFrame:
    """(P, layout, k, part_bytes, total_bytes, exact_bytes, smaller): sketches beside exact counts of the keys of a stream."""
    rows = [(p, layout, SEPARATE.K if layout.startswith("separate") else fit_width(spec.but(P=p), layout), *memory_bytes(spec.but(P=p), layout)) for p in parts for layout in ("plain", "slots", "composite", "separate", "separate_f0")]
    sizes = s.sparkSession.createDataFrame(rows, "P int, layout string, k int, part_bytes bigint, total_bytes bigint")
    whole = _keys(s).select((F.col("keys") * EXACT_KEY_BYTES).cast("bigint").alias("exact_bytes"))
    return sizes.crossJoin(whole).withColumn("smaller", F.col("total_bytes") < F.col("exact_bytes"))


def reads_report(s: DataFrame, spec: SketchSpec, parts: list[int]) -> DataFrame:
    """(P, method, reads, exact_reads, fewer): counters a second-moment query reads beside the exact counts of a stream's keys."""
    rows = [(p, m, reads(spec.but(P=p), m)) for p in parts for m in ("exact_buffers", "ignore_buffers", "projected", "part_cm")]
    counters = s.sparkSession.createDataFrame(rows, "P int, method string, reads bigint")
    return counters.crossJoin(_keys(s).select(F.col("keys").alias("exact_reads"))).withColumn("fewer", F.col("reads") < F.col("exact_reads"))


def grouped_report(s: DataFrame, spec: SketchSpec, by: list[str]) -> DataFrame:
    """(by, method, f2, exact) of single, wide and partitioned matrices for every group of a labelled stream, in one pass."""
    f = s.groupBy(*by, "key").agg(F.sum("weight").alias("f"))
    given = s.groupBy(*by, "k").agg(F.sum("weight").alias("f")) if "k" in s.columns else f
    truth = given.groupBy(*by).agg(F.sum(cm.square(F.col("f"))).cast(cm.BIG).alias("exact"))
    out = None
    for name, layout in (("single", "single"), ("wide", "wide"), ("part_cm", "parts")):
        one = cm.f2_plus(cm.from_frequencies(f, spec, layout, by), by).groupBy(*by).agg(F.sum("f2").cast(cm.BIG).alias("f2")).select(*by, F.lit(name).alias("method"), "f2")
        out = one if out is None else out.unionByName(one)
    return out.join(truth, by)


def shuffled_bytes(spark: SparkSession, df: DataFrame) -> int:
    """Bytes that running ``df`` writes to shuffles, from Spark's own stage figures."""

    def total() -> int:
        sc = spark.sparkContext._jsc.sc()
        sc.listenerBus().waitUntilEmpty(10_000)
        stages = sc.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))

    before = total()
    df.write.format("noop").mode("overwrite").save()
    return total() - before
