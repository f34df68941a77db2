"""The published experiments on the given tables.

Each returns a small table of what the experiment reports.  Times are of this
machine; relative orders, errors and counts are what carries over.
"""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import agms, baselines, blocks, buffers, cm, composite, consistency, exact, interleave, ladder, measures, prefix, slots
from .sources import streams
from .sources.streams import STREAMS
from .spec import PAPER, TEST, SketchSpec, fit_width
from .workspace import Workspace


def scaled(spec: SketchSpec, n: int) -> SketchSpec:
    """Buffers as large as a stream of n rows can bear: about n / (20 P^2) counts, four at least."""
    return spec.but(B=max(4, n // (20 * spec.P * spec.P)))


def fitted(spec: SketchSpec, layout: str) -> SketchSpec:
    """The spec with the columns that its budget leaves in a layout."""
    return spec.but(K=max(1, fit_width(spec, layout)))


def _timed(df: DataFrame) -> float:
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def _truth(s: DataFrame) -> int:
    return int(exact.moments(s).first()["f2"])


def zipf_rows(spark: SparkSession, d: str) -> int:
    """Length of the salted streams: a third of lineitem, 20,000 at least."""
    return max(20_000, streams.load(spark, d, "lineitem", ["l_partkey"]).count() // 3)


#: The designs that are compared: what owners keep, how long buffers grow, and what a second-moment query reads (None: point queries alone).
DESIGNS = ("separate", "buffers_only_unbounded", "buffers_only", "exclusive", "unsynced", "versioned")


def _kept(s: DataFrame, work: Workspace) -> tuple[DataFrame, DataFrame]:
    """(rows, blocks) of a stream, both written once."""
    s = work.save(s.select("seq", "key", "weight"), "stream")
    return s, work.save(blocks.pack(s), "blocks")


def _update(design: str, s: DataFrame | None, packed: DataFrame, spec: SketchSpec, work: Workspace, after: int | None = None, until: int | None = None) -> None:
    """Run the update path of a design over a stream in blocks and keep its state; seqs are later than ``after`` and not later than ``until``.  No design reads the rows ``s``."""
    if design == "separate":
        lanes = work.save(blocks.sums(packed, spec.P, after, until), "keys")  # what every sketch of a worker is made of
        f = lanes.withColumnRenamed("weight", "f")
        sketches = {"matrix": cm.from_frequencies(f, spec, by=["worker"]), "signed": agms.from_frequencies(f, spec, ["worker"]), "distinct": lanes.groupBy("worker").agg(F.hll_sketch_agg("key", 12).alias("sk"))}
        with ThreadPoolExecutor(len(sketches)) as pool:  # small tables, side by side
            list(pool.map(lambda name: work.save(sketches[name], name), sketches))
        return
    spec = spec.but(B=None) if design == "buffers_only_unbounded" else spec
    work.save(composite.run(packed, spec, design.startswith("buffers_only"), after, until), "state")


def _path(design: str) -> str:
    """The first design with the same update path: what readers do is all that sets apart ``exclusive``, ``unsynced`` and ``versioned``."""
    return "exclusive" if design in ("unsynced", "versioned") else design


def _first_states(designs, packed: DataFrame, spec: SketchSpec, until: int, given: Workspace) -> dict[str, Workspace]:
    """Per design the kept state of the updates not later than ``until``: one for each update path, built side by side as no clock runs."""
    made = {path: Workspace(given.spark, "w1c") for path in dict.fromkeys(map(_path, designs))}
    with ThreadPoolExecutor(max(1, len(made))) as pool:
        list(pool.map(lambda path: _update(path, None, packed, spec, made[path], until=until), made))
    return {design: made[_path(design)] for design in designs}


CELLS = "worker bigint, part int, row int, col int, cnt bigint"


def _saved(work: Workspace, schema: str, *names: str) -> list[DataFrame]:
    return [work.spark.read.schema(schema).parquet(work.path(n)) for n in names]


def _queries(design: str, spec: SketchSpec, work: Workspace, keys: DataFrame) -> dict[str, Callable[[], object]]:
    """The queries that a design answers, from its kept state."""
    if design == "separate":
        matrix, signed = _saved(work, CELLS, "matrix", "signed")
        merged = cm.merge(matrix.drop("worker"))
        return {"f1": cm.f1(merged).collect, "f2": agms.f2(cm.merge(signed.drop("worker")), spec).collect, "point": cm.point(merged, keys, spec).count}
    state = _saved(work, composite.FULL_STATE, "state")[0]
    handoffs = composite.still_open(state)
    point = composite.point(state, handoffs, keys, spec).count
    if design.startswith("buffers_only"):
        return {"point": point}
    if design == "exclusive":  # everything is drained first
        whole = composite.conserved_cells(state, handoffs, spec)
        return {"f1": cm.f1(whole).collect, "f2": cm.f2_plus_total(whole).collect, "point": point}
    f2 = composite.f2_exact_buffers(state, handoffs) if design == "unsynced" else composite.f2_projected(state, spec)
    return {"f1": composite.f1(state).collect, "f2": f2.agg(F.sum("f2")).collect, "point": point}


def _beside(run: Callable[[], None], asked: dict[str, Callable[[], object]], rate: float) -> tuple[float, dict[str, list[float]]]:
    """(seconds of ``run``, seconds of every query asked meanwhile): one round of queries each 1 / ``rate`` seconds, one at least."""
    took: dict[str, list[float]] = {n: [] for n in asked}
    over = threading.Event()

    def ask():
        while True:
            began = time.perf_counter()
            for name, query in asked.items():
                t = time.perf_counter()
                query()
                took[name].append(time.perf_counter() - t)
            if over.wait(max(0.0, 1 / rate - (time.perf_counter() - began))):
                return

    reader = threading.Thread(target=ask)
    t = time.perf_counter()
    reader.start()
    run()
    seconds = time.perf_counter() - t
    over.set()
    reader.join()
    return seconds, took


def throughput(spark: SparkSession, d: str, name: str = "S8", z: float = 1.5, parts=(1, 2, 4, 8, 16), designs=DESIGNS, rate: float = 2.0) -> DataFrame:
    """(stream, z, design, P, load, rows, seconds, rows_per_second, rounds, reads): updates alone, and with F1, F2 and point queries on 0.1 % of the keys beside them.

    Queries read the state of the first tenth, which is built before the clock
    starts, once for designs with one update path, and is the warm-up.  Where readers exclude writers, updates wait for
    every round of queries.  ``reads`` is what one second-moment query reads.
    The stream is put in order and kept in blocks before the clock starts; an
    update reads it, deals it to the owners, and runs buffers and owners.
    """
    out = []
    given = Workspace(spark, "w1")
    packed = blocks.keep(spark, d, z if name == "S8" else name, given)
    n, last = (v or 0 for v in packed.agg(F.sum("n"), F.max("hi")).first())
    keys = given.save(blocks.picked(packed, 1000), "keys")
    for p in parts:
        spec = scaled(TEST.but(P=p), n)
        reads = {"separate": measures.reads(spec, "single"), "exclusive": measures.reads(spec, "exact_buffers"), "unsynced": measures.reads(spec, "exact_buffers"), "versioned": measures.reads(spec, "projected")}
        firsts = _first_states(designs, packed, spec, last // 10, given)
        for design in designs:
            work = Workspace(spark, "w1b")
            asked = _queries(design, spec, firsts[design], keys)
            t = time.perf_counter()
            _update(design, None, packed, spec, work)
            alone = time.perf_counter() - t
            if design == "exclusive":
                t = time.perf_counter()
                _update(design, None, packed, spec, work)
                rounds = max(1, round(alone * rate))
                for _ in range(rounds):
                    for query in asked.values():
                        query()
                loaded = time.perf_counter() - t
            else:
                loaded, took = _beside(lambda: _update(design, None, packed, spec, work), asked, rate)
                rounds = len(took["point"])
            out += [(name, z, design, p, load, n, round(sec, 3), round(n / sec), r, reads.get(design, 0)) for load, sec, r in (("none", alone, 0), ("queries", loaded, rounds))]
            work.drop()
        for first in firsts.values():
            first.drop()
    given.drop()
    return spark.createDataFrame(out, "stream string, z double, design string, P int, load string, rows bigint, seconds double, rows_per_second bigint, rounds int, reads bigint")


AGMS_BUDGETS = ((6, 8192), (8, 1024), (128, 8 * 1024))


def error_by_parts(spark: SparkSession, d: str, parts=(1, 2, 4, 8, 16, 32, 64, 128), zs=(1.0, 1.5, 2.0), salts: int = 5, rows: int | None = None, base: SketchSpec = TEST, budgets=AGMS_BUDGETS) -> DataFrame:
    """(z, P, method, mape) over salted streams: matrices and slots with the columns that one budget a part leaves, and signed sketches of several budgets (P = 1)."""
    rows = rows or zipf_rows(spark, d)
    labelled = None
    for z in zs:
        for salt in range(salts):
            s = streams.s8_zipf(spark, d, z, str(salt), rows).select(F.lit(z).alias("z"), F.lit(salt).alias("salt"), "k", "key", "weight")
            labelled = s if labelled is None else labelled.unionByName(s)
    by, work = ["z", "salt"], Workspace(spark, "w3")
    labelled = work.save(labelled.groupBy(*by, "k", "key").agg(F.sum("weight").cast("bigint").alias("weight")), "streams")
    truth = work.save(labelled.groupBy(*by).agg(F.sum(cm.square(F.col("weight"))).cast(cm.BIG).alias("exact")), "truth")
    out = None
    for p in parts:
        report = measures.grouped_report(labelled, base.but(P=p), by)
        slotted = fitted(base.but(P=p), "slots")
        heavy, light = slots.settled_by(labelled, slotted, by)
        matrix = cm.f2_plus(cm.from_frequencies(light, slotted, "parts", by), by).groupBy(*by).agg(F.sum("f2").alias("l"))
        both = heavy.groupBy(*by).agg(F.sum(cm.square(F.col("f"))).alias("h")).join(matrix, by, "left").select(*by, F.lit("part_slots").alias("method"), (F.col("h") + F.coalesce("l", F.lit(0))).cast(cm.BIG).alias("f2")).join(truth, by)
        row = measures.mape(report.unionByName(both), ["z", "method"]).select("z", F.lit(p).alias("P"), "method", "mape")
        out = row if out is None else out.unionByName(row)
    for h, k in budgets:
        spec = base.but(H=h, K=k)
        f2 = cm.median_of_rows(cm.f2_rows(agms.build(labelled, spec, by), by), h, by).select(*by, F.lit(f"agms_{h}x{k}").alias("method"), "f2").join(truth, by)
        out = out.unionByName(measures.mape(f2, ["z", "method"]).select("z", F.lit(1).alias("P"), "method", "mape"))
    return out


def error_with_buffers(spark: SparkSession, d: str, parts=(1, 2, 4, 8, 16, 32, 64, 128), zs=(1.0, 1.5, 2.0), salts: int = 5, rows: int | None = None, base: SketchSpec = TEST) -> DataFrame:
    """(z, P, method, mape, error): the replayed rungs, from slots alone to projected buffers; ``error`` is the mean signed one."""
    rows = rows or zipf_rows(spark, d)
    out = []
    for z in zs:
        for salt in range(salts):
            given = Workspace(spark, "w3b")
            s = given.save(streams.s8_zipf(spark, d, z, str(salt), rows).select("seq", "k", "key", "weight"), "stream")
            truth, packed = _truth(s), given.save(blocks.pack(s), "blocks")
            for p in parts:
                spec = scaled(fitted(base.but(P=p, K=1024), "composite"), rows)
                work = Workspace(spark, "w3c")
                both = work.save(composite.run(packed, spec, kinds="both"), "state")
                state, plain, handoffs = both.filter("buffered"), both.filter("NOT buffered"), composite.still_open(both)
                rungs = {"part_slots": composite.f2_ignore_buffers(plain), "ignored": composite.f2_ignore_buffers(state), "exact": composite.f2_exact_buffers(state, handoffs), "projected": composite.f2_projected(state, spec)}
                all_rungs = None
                for name, df in rungs.items():
                    row = df.agg(F.sum("f2").alias("f2")).select(F.lit(name).alias("method"), "f2")
                    all_rungs = row if all_rungs is None else all_rungs.unionByName(row)
                out += [(z, p, r["method"], (r["f2"] - truth) / truth) for r in all_rungs.collect()]
                work.drop()
            given.drop()
    got = spark.createDataFrame(out, "z double, P int, method string, e double")
    return got.groupBy("z", "P", "method").agg(F.avg(F.abs("e")).alias("mape"), F.avg("e").alias("error"))


def latency(spark: SparkSession, d: str, parts=(1, 2, 4, 8, 16), repeats: int = 20, designs=("exclusive", "unsynced", "versioned")) -> DataFrame:
    """(P, design, query, median_ms, p95_ms, repeats, reads): F1 and F2 of each policy while updates run.

    State and first answers come from the first tenth of the stream, which is
    the warm-up; then queries are repeated while the rest is being replayed.
    """
    out = []
    given = Workspace(spark, "w5")
    packed = blocks.keep(spark, d, "S8", given)
    last = packed.agg(F.max("hi")).first()[0] or 0
    none = spark.createDataFrame([], "key bigint")
    for p in parts:
        spec = TEST.but(P=p)
        for design in designs:
            first, rest = Workspace(spark, "w5b"), Workspace(spark, "w5c")
            _update(design, None, packed, spec, first, until=last // 10)
            asked = {n: q for n, q in _queries(design, spec, first, none).items() if n != "point"}
            for query in asked.values():
                query()
            stop = threading.Event()

            def updates(spec=spec, design=design, rest=rest, stop=stop):
                while not stop.is_set():
                    _update(design, None, packed, spec, rest, after=last // 10)

            writer = threading.Thread(target=updates)
            writer.start()
            for name, query in asked.items():
                times = []
                for _ in range(repeats):
                    t = time.perf_counter()
                    query()
                    times.append(1000 * (time.perf_counter() - t))
                times.sort()
                reads = p if name == "f1" and design != "exclusive" else measures.reads(spec, "projected" if design == "versioned" else "exact_buffers")
                out.append((p, design, name, round(times[len(times) // 2], 2), round(times[int(0.95 * (len(times) - 1))], 2), repeats, reads))
            stop.set()
            writer.join()
            first.drop()
            rest.drop()
    given.drop()
    return spark.createDataFrame(out, "P int, design string, query string, median_ms double, p95_ms double, repeats int, reads bigint")


def ablation(spark: SparkSession, d: str, rows: int | None = None, z: float = 1.5) -> DataFrame:
    """(parameter, value, error, handoffs, swaps, hits): what B, C, w and the self buffer change for the projected estimate."""
    rows = rows or zipf_rows(spark, d)
    s = Workspace(spark, "w6").save(streams.s8_zipf(spark, d, z, "0", rows).select("seq", "k", "key", "weight"), "stream")
    truth = _truth(s)
    base = scaled(TEST, rows)
    cases = [("B", str(b), base.but(B=b)) for b in (16, 64, 256, 1000, None)] + [("C", str(c), base.but(C=c)) for c in (4, 16, 64)] + [("w", str(w), base.but(w=w)) for w in (0.2, 0.5, 0.8, 1.0)] + [("self_buffer", str(b), base.but(self_buffer=b)) for b in (True, False)]
    out = []
    for name, value, spec in cases:
        work = Workspace(spark, "w6b")
        handoffs = work.save(buffers.replay(s, spec), "handoffs")
        state = work.save(composite.drain(handoffs, spec), "state")
        m = composite.metrics(state, handoffs).agg(F.coalesce(F.sum("handoffs"), F.lit(0)), F.coalesce(F.sum("swaps"), F.lit(0)), F.coalesce(F.sum("hits"), F.lit(0))).first()
        est = composite.f2_projected(state, spec).agg(F.coalesce(F.sum("f2"), F.lit(0.0))).first()[0]
        out.append((name, value, (est - truth) / truth, int(m[0]), int(m[1]), int(m[2])))
    return spark.createDataFrame(out, "parameter string, value string, error double, handoffs bigint, swaps bigint, hits bigint")


def freshness(spark: SparkSession, d: str, scans: int = 50, spec: SketchSpec = TEST, names=("S1", "S7", 1.0, 1.5, 2.0)) -> DataFrame:
    """(stream, policy, scan, t_start, t_end, lo, val, hi, inside, position, width): versioned and uncoordinated scans on one replay.

    ``lo`` and ``hi`` are the policy's own answers with all parts read at the
    begin, and at the end; ``width`` is their distance relative to ``hi``.
    """
    out = None
    for name in names:
        work = Workspace(spark, "w7")
        packed = blocks.keep(spark, d, name, work)  # streams of this experiment have weights of 1
        if name == "S7":  # consecutive numbers for the time axis: documents first, then places
            packed = work.save(blocks.numbered(packed), "numbered")
        rows = packed.agg(F.sum("n")).first()[0] or 0
        t = interleave.freshness(packed, scaled(spec, rows), scans, work).select(F.lit(str(name)).alias("stream"), "*")
        out = t if out is None else out.unionByName(t)
    width = F.col("hi") - F.col("lo")
    out = out.withColumn("inside", F.col("val").between(F.least("lo", "hi"), F.greatest("lo", "hi")))
    return out.withColumn("position", F.when(width > 0, (F.col("val") - F.col("lo")) / width)).withColumn("width", F.when(F.col("hi") > 0, width / F.col("hi")))


def point_accuracy(spark: SparkSession, d: str, spec: SketchSpec = TEST) -> DataFrame:
    """(stream, method, kind, n, avg_error, max_error, exact_share): all keys, heavy from the count of the 100th on, and 50 absent ones."""
    out = None
    for name in ("S1", "S3", "S7"):
        s = STREAMS[name](spark, d)
        truth = Workspace(spark, "w8").save(exact.freq(s), "truth")
        keys = truth.select("key").union(spark.range(50).select((F.col("id") * 7919 + 13).alias("key"))).distinct()
        bar = truth.orderBy(F.desc("f")).limit(100).agg(F.min("f")).first()[0] or 1
        light, heavy = slots.settled(s, spec)
        for method, est in (("matrix", cm.point(cm.build(s, spec), keys, spec)), ("parts", cm.point(cm.build(s, spec, "parts"), keys, spec, "parts")), ("slots", slots.point(light, heavy, keys, spec))):
            row = measures.point_error(est, truth, bar).select(F.lit(name).alias("stream"), F.lit(method).alias("method"), "*")
            out = row if out is None else out.unionByName(row)
    return out


def weighted(spark: SparkSession, d: str, spec: SketchSpec = TEST) -> DataFrame:
    """(method, f2, exact) of all order-free methods on weighted updates."""
    return ladder.report(STREAMS["S4"](spark, d), spec)


def under_load(spark: SparkSession, d: str, spec: SketchSpec = TEST, batches: int = 5) -> DataFrame:
    """(batch, rows, f1, f2, exact, points, update_seconds, query_seconds, rows_per_second): a stream in equal batches; after each one F1, one projected F2, and a point query for every thousandth update.

    Hand-overs of all batches are computed once; a batch's update is its state
    from them, and its queries read that state.
    """
    s = Workspace(spark, "w2").save(streams.s1_users(spark, d), "stream")
    last = s.agg(F.max("seq")).first()[0] or 0
    out = []
    for i in range(1, batches + 1):
        until = last * i // batches
        seen, work = s.filter(F.col("seq") <= until), Workspace(spark, "w2b")
        t = time.perf_counter()
        handoffs = work.save(buffers.replay(seen, spec), "handoffs")
        state = work.save(composite.drain(handoffs, spec), "state")
        update, t = time.perf_counter() - t, time.perf_counter()
        f1 = handoffs.agg(F.sum("cnt")).first()[0]
        f2 = composite.f2_projected(state, spec).agg(F.sum("f2")).first()[0]
        points = composite.point(state, handoffs, seen.filter("seq % 1000 = 0").select("key"), spec).count()
        asked = time.perf_counter() - t
        n = seen.count()
        out.append((i, n, int(f1), float(f2), _truth(seen), int(points), round(update, 3), round(asked, 3), round(n / update)))
        work.drop()
    return spark.createDataFrame(out, "batch int, rows bigint, f1 bigint, f2 double, exact bigint, points bigint, update_seconds double, query_seconds double, rows_per_second bigint")


def quantiles(spark: SparkSession, d: str, bits: int = 11, spec: SketchSpec = PAPER) -> DataFrame:
    """(q, value): quantiles of part keys from dyadic matrices."""
    s = STREAMS["S3"](spark, d).withColumn("value", F.col("k").cast("bigint"))
    bits = max(bits, int(s.agg(F.max("value")).first()[0] or 1).bit_length())
    cells = Workspace(spark, "w13").save(cm.dyadic_build(s, F.col("value"), bits, spec), "cells")
    total = s.count()
    return spark.createDataFrame([(q, cm.dyadic_quantile(cells, total, q, bits, spec)) for q in (0.25, 0.5, 0.75)], "q double, value bigint")


def disagreement(spark: SparkSession, d: str, spec: SketchSpec = TEST) -> DataFrame:
    """(bucket, f1, f2_seen, composite_lag, separate_f1, separate_f2, separate_lag): updates by which F1 is ahead of F2 at each moment.

    In the composite F2 lags by what the buffers hold.  Separate sketches are
    replayed as they are merged: every worker's matrix answers F1, its signed
    sketch F2, and workers take turns, one sketch of one worker a bucket of time,
    so each answer is the count (a row of the sketch) of what its merges had seen.
    """
    s = streams.s1_users(spark, d)
    grain = prefix.grain_of(s)
    seen = consistency.relaxed_bound(s, spec, grain).groupBy("bucket").agg(F.sum("total").cast("bigint").alias("f1"), F.sum("seen").cast("bigint").alias("f2_seen"))
    came = s.groupBy(F.pmod("seq", F.lit(spec.P)).cast("int").alias("worker"), prefix.bucket(F.col("seq"), grain).alias("at")).agg(F.sum("weight").alias("n"))
    moments = Workspace(spark, "w11").save(seen.select("bucket").distinct(), "moments")  # some 200 moments
    turn = 2 * spec.P  # a merge of the worker's matrix in turn 2w, of its signed sketch in turn 2w + 1
    merged = [F.col("bucket") - F.pmod(F.col("bucket") - (2 * F.col("worker") + i), F.lit(turn)) for i in (0, 1)]
    both = F.broadcast(moments).join(came, F.col("at") <= F.col("bucket"))
    counts = both.groupBy("bucket").agg(*[F.sum(F.when(F.col("at") <= m, F.col("n")).otherwise(0)).cast("bigint").alias(c) for m, c in zip(merged, ("separate_f1", "separate_f2"), strict=True)])
    out = seen.join(counts, "bucket")
    return out.select("bucket", "f1", "f2_seen", (F.col("f1") - F.col("f2_seen")).alias("composite_lag"), "separate_f1", "separate_f2", F.abs(F.col("separate_f1") - F.col("separate_f2")).alias("separate_lag"))


def baseline_point(spark: SparkSession, d: str) -> DataFrame:
    """(key, builtin, exact): Spark's own Count-Min aggregate on all keys."""
    s = streams.s3_parts(spark, d)
    truth = exact.freq(s)
    return baselines.builtin_points(s, truth).join(truth, "key").select("key", F.col("est").alias("builtin"), F.col("f").cast("bigint").alias("exact"))


FEW = (1, 4, 16)  # parts of the registered experiments; the functions take any, by default those of the published grids

WORKLOADS = {
    "w1_throughput": lambda spark, d: throughput(spark, d, "S8", 1.5, FEW),
    "w1_throughput_z1": lambda spark, d: throughput(spark, d, "S8", 1.0, FEW),
    "w1_throughput_z2": lambda spark, d: throughput(spark, d, "S8", 2.0, FEW),
    "w1_throughput_z3": lambda spark, d: throughput(spark, d, "S8", 3.0, FEW),
    "w1_throughput_tokens": lambda spark, d: throughput(spark, d, "S7", 0.0, (4, 16)),
    "w2_under_load": under_load,
    "w3_error_by_parts": error_by_parts,
    "w3_error_with_buffers": lambda spark, d: error_with_buffers(spark, d, (1, 4, 16, 64), salts=2),
    "w5_latency": lambda spark, d: latency(spark, d, FEW),
    "w6_ablation": ablation,
    "w7_freshness": lambda spark, d: freshness(spark, d, names=("S1", 1.0, 1.5, 2.0)),
    "w7_freshness_tokens": lambda spark, d: freshness(spark, d, names=("S7",)),
    "w8_point_accuracy": point_accuracy,
    "w11_disagreement": disagreement,
    "w13_quantiles": quantiles,
    "builtin_point": baseline_point,
}
