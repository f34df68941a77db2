"""Global queries that scan parts at different moments, on a deterministic history.

Part i is scanned at t0 + i * step.  Without coordination its buffers are read
``delta`` later than its matrix (or earlier): a hand-over in between is missed
(or counted twice).  With versions every part is read at one moment, and a
hand-over during the read costs one retry at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..jvm import kernels, map_partitions
from ..spec import SketchSpec
from . import blocks, buffers, cm, measures, static_state


def _scan_time(spec: SketchSpec, t0: int, step: int, part="owner"):
    return (F.lit(t0) + F.col(part) * F.lit(step)).cast("bigint")


def _looks(s: DataFrame, spec: SketchSpec, t0: int, step: int, delta: int, order: str) -> DataFrame:
    """Rows with ``t`` and whether the look at the sketch and the look at the buffers find them."""
    if order not in ("sketch_first", "buffers_first"):
        raise ValueError(order)
    rows = buffers.chunks(s, spec).withColumn("t", _scan_time(spec, t0, step))
    sketch_at, buffer_at = (F.col("t"), F.col("t") + delta) if order == "sketch_first" else (F.col("t") + delta, F.col("t"))
    flush = F.coalesce("flush_seq", F.lit(1 << 62))
    return rows.withColumn("in_sketch", (flush <= sketch_at).cast("bigint")).withColumn("in_buffer", ((F.col("seq") <= buffer_at) & (flush > buffer_at)).cast("bigint"))


def unsynced(s: DataFrame, spec: SketchSpec, t0: int, step: int, delta: int, order: str = "sketch_first") -> DataFrame:
    """(part, t, arrived, in_sketch, in_buffer, missed, doubled): what the two looks of a scan find of each part.

    ``arrived`` rows were there when the scan of the part began.  Those that
    neither look finds are missed; rows that both find are counted twice.
    """
    rows = _looks(s, spec, t0, step, delta, order)
    here = (F.col("seq") <= F.col("t")).cast("bigint")
    missed = here * (1 - F.greatest("in_sketch", "in_buffer"))
    total = lambda c: F.sum(c).cast("bigint")
    return rows.groupBy(F.col("owner").alias("part"), "t").agg(total(here).alias("arrived"), total("in_sketch").alias("in_sketch"), total("in_buffer").alias("in_buffer"), total(missed).alias("missed"), total(F.col("in_sketch") * F.col("in_buffer")).alias("doubled"))


def _slots_of(f: DataFrame, spec: SketchSpec) -> tuple[DataFrame, DataFrame]:
    """(heavy, light) rows of f(part, key, f, ...): the C heaviest keys of each part at that moment, and the rest."""
    heavy = f.filter("f > 0").withColumn("rank", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("f"), "key"))).filter(F.col("rank") <= spec.C).drop("rank")
    return heavy, f.join(F.broadcast(heavy.select("key")), "key", "left_anti")  # at most P * C keys


def unsynced_f2(s: DataFrame, spec: SketchSpec, t0: int, step: int, delta: int, order: str = "sketch_first") -> DataFrame:
    """(part, f2): what the uncoordinated query returns: matrix and slots at one moment, the buffers of the slots' keys at another.

    Slots are those of the look at the sketch: the keys heaviest by what had been handed over.
    """
    rows = _looks(s, spec, t0, step, delta, order)
    f = rows.groupBy(F.col("owner").alias("part"), "key").agg(F.sum("in_sketch").alias("f"), F.sum("in_buffer").alias("buf"))
    heavy, rest = _slots_of(f, spec)
    light = cm.f2_plus(cm.from_frequencies(rest.filter("f > 0").select("key", "f"), spec, "parts"))
    heavy = heavy.groupBy("part").agg(F.sum(cm.square(F.col("f") + F.col("buf"))).alias("h"))
    parts = s.sparkSession.range(spec.P).select(F.col("id").cast("int").alias("part"))
    return parts.join(light, "part", "left").join(heavy, "part", "left").select("part", (F.coalesce("f2", F.lit(0)) + F.coalesce("h", F.lit(0))).cast(cm.BIG).alias("f2"))


def versioned(s: DataFrame, spec: SketchSpec, t0: int, step: int, width: int = 0) -> DataFrame:
    """(part, t, v_end, retries, f2): each part from one snapshot.

    ``v_end`` counts the hand-overs up to the scan; a hand-over within ``width``
    of its begin makes the versions differ, so the part is read again, after it,
    once (the flag holds back the next one).
    """
    rows = buffers.chunks(s, spec).withColumn("t", _scan_time(spec, t0, step))
    flush = F.coalesce("flush_seq", F.lit(1 << 62))
    ends = rows.filter("handed").select("owner", "producer", "flush_seq", "t").distinct()
    first = ends.filter((F.col("flush_seq") > F.col("t")) & (F.col("flush_seq") <= F.col("t") + width)).groupBy("owner").agg(F.min("flush_seq").alias("again"))
    at = F.coalesce("again", "t")
    rows = rows.join(F.broadcast(first), "owner", "left").withColumn("seen_at", at)
    seen = rows.filter(flush <= F.col("seen_at"))
    f = seen.groupBy(F.col("owner").alias("part"), "key").agg(F.count("*").alias("f"))
    top, rest = _slots_of(f, spec)  # the slots of that moment
    light = cm.f2_plus(cm.from_frequencies(rest.select("key", "f"), spec, "parts"))
    flushes = seen.join(F.broadcast(top.select("key")), "key", "left_semi").groupBy(F.col("owner").alias("part"), "key", "producer", "flush_seq").agg(F.count("*").alias("v"))
    avg = static_state.ewma(flushes, spec.w)
    heavy = top.join(avg, ["part", "key"]).groupBy("part").agg(F.sum(F.pow(F.col("f") + F.lit(spec.P / 2) * F.col("avg"), F.lit(2))).alias("h"))
    parts = s.sparkSession.range(spec.P).select(F.col("id").cast("int").alias("part")).withColumn("t", _scan_time(spec, t0, step, "part"))
    version = ends.join(F.broadcast(first), "owner", "left").filter(F.col("flush_seq") <= F.coalesce("again", "t")).groupBy(F.col("owner").alias("part")).agg(F.count("*").alias("v_end"))
    out = parts.join(version, "part", "left").join(first.withColumnRenamed("owner", "part"), "part", "left").join(light, "part", "left").join(heavy, "part", "left")
    return out.select("part", "t", F.coalesce("v_end", F.lit(0)).alias("v_end"), F.col("again").isNotNull().cast("int").alias("retries"), (F.coalesce("f2", F.lit(0)).cast("double") + F.coalesce("h", F.lit(0.0))).alias("f2"))


def freshness(packed: DataFrame, spec: SketchSpec, scans: int, work) -> DataFrame:
    """(policy, scan, t_start, t_end, lo, val, hi): answers of both policies beside their own at begin and end, for a stream in ``blocks``, each update counting once.

    ``scans`` begin all along the stream.  How long one takes follows from the
    counters it reads: an uncoordinated scan reads every matrix and buffer, its
    buffers after its matrices; a versioned one reads partial sums and slots.

    What an owner has changes with its hand-overs alone, so matrices and slots
    are made once for each number of hand-overs, and a scan reads those of its
    moment: slots from the heaviest keys of every task, matrices from the sums
    of what each hand-over adds to a cell, without the keys that have slots.  A buffer holds of a key what
    had come by the moment, less what had been handed over.
    """
    flushes = work.save(blocks.flushes(packed, spec), "flushes")
    last = packed.agg(F.max("hi")).first()[0] or 0
    full, small = measures.reads(spec, "exact_buffers"), measures.reads(spec, "projected")
    slow = max(1, last // (4 * scans * spec.P))
    quick = max(1, slow * small // full)
    delta = max(1, slow // 2)
    ask = []
    for i in range(1, scans + 1):
        t = last * i // (scans + 1)
        for policy, step in (("unsynced", slow), ("versioned", quick)):
            end = t + spec.P * step
            for part in range(spec.P):
                at = t + part * step
                ask += [(policy, i, t, end, "lo", part, t, t), (policy, i, t, end, "val", part, at, at + (delta if policy == "unsynced" else 0)), (policy, i, t, end, "hi", part, end, end)]
    moments = sorted({a[-1] for a in ask if a[0] == "unsynced"})
    points = _points(packed.sparkSession, ask, moments)
    cell = ["policy", "scan", "which", "part"]
    ends = flushes.select("part", "flush_seq").distinct().withColumn("version", F.row_number().over(Window.partitionBy("part").orderBy("flush_seq")))
    ends = F.broadcast(work.save(ends, "ends"))  # some 20 hand-overs a buffer, P * P buffers
    versions = points.join(ends, (points["part"] == ends["part"]) & (ends["flush_seq"] <= points["t"]), "left").groupBy(*[points[c] for c in points.columns]).agg(F.coalesce(F.max("version"), F.lit(0)).alias("version"))
    points = F.broadcast(work.save(versions, "points"))  # 6 * scans * P rows
    asked = F.broadcast(points.select("part", "version").distinct())
    came = flushes.join(ends, ["part", "flush_seq"])
    step = work.save(came.groupBy("part", "key", "version").agg(F.sum("v").alias("v")), "step")
    final = ends.agg(F.max("version")).first()[0] or 0

    def runs(steps: DataFrame, *of: str) -> DataFrame:
        """The sums of ``v`` so far, and the versions from ``version`` until ``until`` that have them."""
        over = Window.partitionBy(*of).orderBy("version")
        return steps.select(*of, F.sum("v").over(over).alias("f"), "version", F.coalesce(F.lead("version").over(over) - 1, F.lit(final)).alias("until"))

    tops = map_partitions(runs(step, "part", "key").select("part", "key", "f", "version", "until"), kernels(packed.sparkSession).heaviest(spec.C), "part int, version int, key bigint, f bigint")
    rank = F.row_number().over(Window.partitionBy("part", "version").orderBy(F.desc("f"), "key"))
    heavy = tops.withColumn("rank", rank).filter(F.col("rank") <= spec.C).join(asked, ["part", "version"], "left_semi")
    heavy = work.save(heavy.select("part", "version", "key", "f"), "heavy")
    at = ["part", "row", "col"]  # a matrix has the sums of its steps, but for those of keys that have slots
    cells = runs(cm.from_frequencies(step.select("version", "key", F.col("v").alias("f")), spec, "parts", ["version"]).withColumnRenamed("cnt", "v"), *at)
    cells = cells.select(*at, "f", F.explode(F.sequence("version", "until")).alias("version")).join(asked, ["part", "version"], "left_semi")
    gone = cm.from_frequencies(heavy.select("version", "key", (-F.col("f")).alias("f")), spec, "parts", ["version"])
    cells = cells.select("version", *at, F.col("f").alias("cnt")).unionByName(gone).groupBy("version", *at).agg(F.sum("cnt").cast("bigint").alias("cnt"))
    light = cm.f2_plus(cells, ["version"])
    few = F.broadcast(heavy.select("key").distinct())  # keys that have a slot at some moment
    seen = work.save(came.join(few, "key", "left_semi"), "seen")
    age = F.row_number().over(Window.partitionBy("part", "at", "key").orderBy(F.desc("flush_seq"), F.desc("producer"))) - 1
    aged = heavy.select("part", "key", F.col("version").alias("at")).join(seen, ["part", "key"]).filter("version <= at").withColumn("age", age).withColumn("n", F.count("*").over(Window.partitionBy("part", "at", "key")))
    avg = aged.groupBy("part", "key", F.col("at").alias("version")).agg(F.sum(F.pow(F.lit(1 - spec.w), F.col("age")) * F.when(F.col("age") == F.col("n") - 1, F.lit(1.0)).otherwise(F.lit(spec.w)) * F.col("v")).alias("avg"))
    top = heavy.join(avg, ["part", "version", "key"], "left").groupBy("part", "version").agg(F.sum(F.pow(F.col("f") + F.lit(spec.P / 2) * F.coalesce("avg", F.lit(0.0)), F.lit(2))).alias("projected"))
    held = work.save(points.filter("policy = 'unsynced'").join(heavy, ["part", "version"]).select(*cell, "b", "moment", "key", "f"), "held")
    arrived = work.save(blocks.arrivals(packed, moments).join(few, "key", "left_semi").groupBy("key", F.col("moment").alias("m")).agg(F.sum("n").alias("n")), "arrived")
    reads = held.select(*cell, "key", "b", "moment")
    parts = reads.join(arrived, "key").filter("m <= moment").select(*cell, "key", "n").unionByName(reads.join(seen.drop("part"), "key").filter("flush_seq <= b").select(*cell, "key", (-F.col("v")).alias("n")))
    buf = parts.groupBy(*cell, "key").agg(F.sum("n").alias("buf"))
    read = held.join(buf, [*cell, "key"], "left").groupBy(*cell).agg(F.sum(F.pow((F.col("f") + F.coalesce("buf", F.lit(0))).cast("double"), F.lit(2))).alias("read"))
    out = points.join(light, ["part", "version"], "left").join(top, ["part", "version"], "left").join(read, cell, "left")
    h = F.coalesce(F.when(F.col("policy") == "versioned", F.col("projected")).otherwise(F.col("read")), F.lit(0.0))
    out = out.withColumn("v", F.coalesce(F.col("f2").cast("double"), F.lit(0.0)) + h)

    def total(which: str):  # parts in their order, so that equal states give equal answers
        return F.aggregate(F.array_sort(F.collect_list(F.when(F.col("which") == which, F.struct("part", "v")))), F.lit(0.0), lambda a, x: a + x["v"]).alias(which)

    return out.groupBy("policy", "scan", "t_start", "t_end").agg(*[total(w) for w in ("lo", "val", "hi")])


def _points(spark, ask: list, moments: list[int]) -> DataFrame:
    """Looks (policy, scan, t_start, t_end, which, part, t, b) with the number of ``b`` among the moments, null where it is none of them."""
    number = {m: i for i, m in enumerate(moments)}
    return spark.createDataFrame([(*a, number.get(a[-1])) for a in ask], "policy string, scan int, t_start bigint, t_end bigint, which string, part int, t bigint, b bigint, moment int")
