"""What the composite sketch is measured against."""

from __future__ import annotations

import struct

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import SketchSpec
from . import agms, buffers, cm, composite, exact


def separate(s: DataFrame, spec: SketchSpec, workers: int = 4, agms_spec: SketchSpec | None = None) -> dict[str, DataFrame]:
    """One sketch per query type and worker, merged before any query: {"cells", "f1", "f2", "f0"}.

    Linear sketches of workers add up, so the merged tables are those of the
    whole stream; what differs is the memory, ``workers`` times one set.
    """
    other = agms_spec or spec
    lanes = s.withColumn("worker", F.pmod(F.coalesce("seq", F.xxhash64("key")), F.lit(workers)))
    cells = cm.merge(cm.build(lanes, spec, by=["worker"]).drop("worker"))
    signed = cm.merge(agms.build(lanes, other, by=["worker"]).drop("worker"))
    hll = lanes.groupBy("worker").agg(F.hll_sketch_agg("key", 12).alias("sk")).agg(F.hll_sketch_estimate(F.hll_union_agg("sk")).alias("f0"))
    return {"cells": cells, "f1": cm.f1(cells), "f2": agms.f2(signed, other), "f0": hll, "signed": signed}


def buffers_only(s: DataFrame, keys: DataFrame, spec: SketchSpec) -> DataFrame:
    """(key, est): point queries of parts with slots and buffers that keep no partial sums, averages or versions (B may be None)."""
    handoffs = buffers.replay(s, spec)
    return composite.point(composite.drain(handoffs, spec, plain=True), handoffs, keys, spec)


def builtin(s: DataFrame) -> DataFrame:
    """One row of what Spark has: approximate and exact distinct keys, f1, and the exact f2."""
    approx = s.agg(F.approx_count_distinct("key", 0.02).alias("f0_approx"))
    return approx.crossJoin(exact.moments(s).select("f0", "f1", "f2"))


def builtin_point(s: DataFrame, keys: list[int], eps: float = 0.001, confidence: float = 0.99, seed: int = 7) -> list[int]:
    """Point queries from Spark's own Count-Min aggregate, asked in the JVM."""
    blob = s.agg(F.count_min_sketch("key", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sk")).first()["sk"]
    jvm = s.sparkSession.sparkContext._jvm
    sketch = jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytes(blob))
    return [int(sketch.estimateCount(jvm.java.lang.Long(k))) for k in keys]


def builtin_points(s: DataFrame, keys: DataFrame, eps: float = 0.001, confidence: float = 0.99, seed: int = 7) -> DataFrame:
    """(key, est) of the same aggregate for any number of keys: its counters become a table that the keys meet in a join.

    Keys stay below 2^31, as folded ones do, so that the products of its row hashes fit.
    """
    blob = bytes(s.agg(F.count_min_sketch("key", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sk")).first()["sk"])
    _, _, depth, width = struct.unpack_from(">iqii", blob)
    factors = struct.unpack_from(f">{depth}q", blob, 20)
    table = struct.unpack_from(f">{depth * width}q", blob, 20 + 8 * depth)
    cells = s.sparkSession.createDataFrame([(i // width, i % width, c) for i, c in enumerate(table) if c], "row int, col bigint, cnt bigint")
    product = [F.col("key") * F.lit(a) for a in factors]
    at = F.array(*[((p + F.shiftright(p, 32)).bitwiseAND(F.lit((1 << 31) - 1)) % F.lit(width)) for p in product])
    asked = keys.select("key").distinct().select("key", F.posexplode(at).alias("row", "col"))
    return asked.join(F.broadcast(cells), ["row", "col"], "left").groupBy("key").agg(F.min(F.coalesce("cnt", F.lit(0))).alias("est"))
