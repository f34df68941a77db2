"""Frequency queries while a stream arrives."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.listener import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import canon_key, owner, row_hashes_np
from ..operators import buffers, cm, composite
from ..spec import SketchSpec


def keyed(events: DataFrame, key: str = "user_id") -> DataFrame:
    """(event_id, ts, key, weight) of an events stream; null keys are dropped."""
    return events.filter(F.col(key).isNotNull()).select("event_id", "ts", canon_key(F.col(key)).alias("key"), F.lit(1).cast("bigint").alias("weight"))


def window_f1(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, end, f1) per tumbling or sliding window of event time; rows later than ``late`` are dropped."""
    at = F.window("ts", window, slide)  # the watermark's own column: a cast of it would have no watermark
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy(at.alias("w")).agg(F.sum("weight").alias("f1")).select("w.start", "w.end", "f1")


def window_cells(events: DataFrame, spec: SketchSpec, window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, part, row, col, cnt): one matrix per window, a plain aggregation and so append-only once a window closes."""
    at = F.window("ts", window)
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    cells = rows.select("ts", "weight", F.explode(cm.places(F.col("key"), spec)).alias("c"))
    return cells.groupBy(at.alias("w"), F.col("c.row").alias("row"), F.col("c.col").alias("col")).agg(F.sum("weight").alias("cnt")).select("w.start", F.lit(0).alias("part"), "row", "col", "cnt")


def window_f2(cells: DataFrame) -> DataFrame:
    """(start, f2, f1, alarm): the second moment of each finished window and its share of f1 squared, a sign of skew."""
    rows = cells.groupBy("start", "part", "row").agg(F.sum(cm.square(F.col("cnt"))).alias("sq"), F.sum("cnt").alias("n"))
    parts = rows.groupBy("start", "part").agg(F.min("sq").alias("sq"), F.max("n").alias("n"))  # any row has all counts
    out = parts.groupBy("start").agg(F.sum("sq").cast("double").alias("f2"), F.sum("n").cast("double").alias("f1"))
    return out.withColumn("alarm", F.col("f2") / (F.col("f1") * F.col("f1")))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(key, start, end, n) per session of a key."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return rows.groupBy("key", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("key", "w.start", "w.end", "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once within the watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_names(events: DataFrame, names: DataFrame, on: str) -> DataFrame:
    """Each arriving row with the columns that a table has for its key; rows without any stay."""
    return events.join(names, on, "left")


_SNAPSHOT = "part int, v_begin bigint, v_end bigint, f1 bigint, f2_projected double, f2rows array<double>, hits bigint, swaps bigint"

_COUNTERS = ("v_begin", "v_end", "updates", "hits", "inserts", "misses", "swaps")

#: What an owner keeps between micro-batches, in declared columns: a changed class still reads it, and so does SQL.
LIVE_STATE = (
    "cells array<bigint>, slot_key array<bigint>, slot_cnt array<bigint>, slot_old array<bigint>, slot_avg array<double>, f2rows array<decimal(38,0)>, "
    "buf_producer array<bigint>, buf_key array<bigint>, buf_cnt array<bigint>, f1 bigint, " + ", ".join(f"{n} bigint" for n in _COUNTERS)
)


def _columns_of(keys: list[int], spec: SketchSpec) -> dict[int, list[int]]:
    return dict(zip(keys, row_hashes_np(np.array(keys, dtype="int64"), spec).tolist(), strict=True)) if keys else {}


def _packed(state: composite.OwnerState, lanes: dict[int, buffers.Lane], seen: int) -> tuple:
    """The LIVE_STATE row of an owner."""
    slots = [(k, *s) for k, s in sorted(state.slots.items())]
    bufs = [(p, k, c) for p, lane in lanes.items() for k, c in lane.counts.items()]
    flat = [c for row in state.cells for c in row]
    return (flat, *([s[i] for s in slots] for i in range(4)), [Decimal(v) for v in state.f2rows], *([b[i] for b in bufs] for i in range(3)), seen, *(getattr(state, n) for n in _COUNTERS))


def _unpacked(row: tuple, spec: SketchSpec) -> tuple[composite.OwnerState, dict[int, buffers.Lane], int]:
    cells, keys, cnts, olds, avgs, f2rows, producers, buf_keys, buf_cnts, seen, *counters = row
    state, lanes = composite.OwnerState(spec), {}
    state.cells = [list(cells[j * spec.K : (j + 1) * spec.K]) for j in range(spec.H)]
    state.slots = {k: [c, o, a] for k, c, o, a in zip(keys, cnts, olds, avgs, strict=True)}
    state.cols = _columns_of(list(keys), spec)
    state.f2rows = [int(v) for v in f2rows]
    for p, k, c in zip(producers, buf_keys, buf_cnts, strict=True):
        lane = lanes.setdefault(p, buffers.Lane())
        lane.counts[k] = c
        lane.total += c
    for name, v in zip(_COUNTERS, counters, strict=True):
        setattr(state, name, v)
    return state, lanes, seen


def _live(spec: SketchSpec):
    """The owner's state across micro-batches: matrix, slots, sums, versions, and one open buffer a producer."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        part = int(key[0])
        state, lanes, seen = _unpacked(held.get, spec) if held.exists else (composite.OwnerState(spec), {}, 0)
        rows = pd.concat(list(frames)).sort_values(["event_id"], kind="stable")
        keys = rows["key"].to_numpy()
        known = _columns_of([k for lane in lanes.values() for k in lane.counts], spec)
        known.update(_columns_of(keys.tolist(), spec))
        for seq, k, v in zip(rows["event_id"].tolist(), keys.tolist(), rows["weight"].tolist(), strict=True):
            seen += v
            full = lanes.setdefault(seq % spec.P, buffers.Lane()).add(k, v, spec)
            if full is not None:
                state.v_begin += 1
                for k2, c in full.items():
                    state.update(k2, c, known[k2])
                state.v_end = state.v_begin
        held.update(_packed(state, lanes, seen))
        projected = min(state.f2rows) + sum((s[0] + spec.P * s[2] / 2) ** 2 - s[1] ** 2 for s in state.slots.values())
        yield pd.DataFrame({"part": [part], "v_begin": [state.v_begin], "v_end": [state.v_end], "f1": [seen], "f2_projected": [float(projected)], "f2rows": [[float(v) for v in state.f2rows]], "hits": [state.hits], "swaps": [state.swaps]})

    return run


def live_composite(events: DataFrame, spec: SketchSpec) -> DataFrame:
    """A snapshot row per owner and micro-batch from keyed stateful processing.

    A batch commits all owners at once, so the newest rows of all parts are one
    consistent snapshot.  Owners hold bounded state: the matrix, C slots, H sums
    and P open buffers of C keys.
    """
    rows = events.select("event_id", "key", "weight", owner(F.col("key"), spec).alias("part"))
    return rows.groupBy("part").applyInPandasWithState(_live(spec), _SNAPSHOT, LIVE_STATE, "update", GroupStateTimeout.NoTimeout)


def stored_live_state(spark: SparkSession, checkpoint: str) -> tuple[DataFrame, DataFrame]:
    """(state, buffers) of ``live_composite`` as its last committed batch left them, read from the stream's checkpoint.

    The columns are those of a batch replay (``composite.STATE``) and of its
    hand-overs that stay buffered, so all of ``composite`` applies to them.
    """
    from .. import store

    rows = store.read_state(spark, checkpoint).select(F.col("key.part").alias("part"), "value.groupState.*")
    slots = F.transform(F.arrays_zip("slot_key", "slot_cnt", "slot_old", "slot_avg"), lambda s: F.struct(s["slot_key"].alias("key"), s["slot_cnt"].alias("cnt"), s["slot_old"].alias("old"), s["slot_avg"].alias("avg")))
    state = rows.select("part", "cells", slots.alias("slots"), "f2rows", *_COUNTERS, "f1")
    open_ = rows.select(F.col("part").alias("owner"), F.posexplode(F.arrays_zip("buf_producer", "buf_key", "buf_cnt")).alias("pos", "b"))
    none = F.lit(None).cast("bigint").alias("flush_seq")
    return state, open_.select("owner", F.col("b.buf_producer").alias("producer"), none, "pos", F.col("b.buf_key").alias("key"), F.col("b.buf_cnt").alias("cnt"), F.lit(False).alias("handed"))


def run_available(df: DataFrame, name: str, checkpoint: str, mode: str) -> DataFrame:
    """Process what is there into a memory table and return it (tests and small results)."""
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def start(df: DataFrame, sink: str, mode: str, checkpoint: str | None = None, every: str | None = None, **options):
    """Start a stream into ``sink`` (memory, console, parquet, noop ...): once over what is there, or ``every`` so often."""
    writer = df.writeStream.format(sink).outputMode(mode).options(**options)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    return (writer.trigger(processingTime=every) if every else writer.trigger(availableNow=True)).start()


def to_store(cells: DataFrame, root: str, spec: SketchSpec, checkpoint: str):
    """Write each micro-batch's finished cells to a sketch store; a batch that is tried again replaces itself."""
    from .. import store

    return cells.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(lambda df, i: store.save(df.select("part", "row", "col", "cnt"), root, spec, i)).trigger(availableNow=True).start()


def panes_to_store(events: DataFrame, root: str, spec: SketchSpec, checkpoint: str, pane: str = "1 day"):
    """Write each micro-batch's cells by pane of event time, with no state between batches.

    A batch is a table, so its keys are summed before their H cells are made;
    matrices add up, so rows of a pane may come in any batch and none is late.
    A batch that is tried again replaces itself.
    """
    from .. import store

    def add(df: DataFrame, batch_id: int) -> None:
        f = df.groupBy(F.window(F.col("ts").cast("timestamp"), pane)["start"].alias("start"), "key").agg(F.sum("weight").alias("f"))
        store.save(cm.from_frequencies(f, spec, "single", ["start"]), root, spec, batch_id)

    return events.writeStream.option("checkpointLocation", checkpoint).foreachBatch(add).trigger(availableNow=True).start()


def sliding_cells(panes: DataFrame, pane_days: int, count: int) -> DataFrame:
    """Cells (start, part, row, col, cnt) of windows of ``count`` panes that begin at each pane: the sums of their panes' matrices."""
    starts = F.explode(F.transform(F.sequence(F.lit(0), F.lit(count - 1)), lambda i: F.col("start") - i * F.expr(f"INTERVAL {pane_days} DAYS")))
    return panes.select(starts.alias("start"), "part", "row", "col", "cnt").groupBy("start", "part", "row", "col").agg(F.sum("cnt").alias("cnt"))


class LateRows(StreamingQueryListener):
    """Counts what watermarks dropped, by name or id of the query.

    The figure is Spark's: rows that reach a stateful operator too late, so
    where a task sums first it counts sums (windows of a task), not updates.
    """

    def __init__(self):
        self.dropped: dict[str, int] = {}

    def onQueryStarted(self, event):
        self.dropped.setdefault(event.name or str(event.id), 0)

    def onQueryProgress(self, event):
        p = event.progress
        name = p.name or str(p.id)
        self.dropped[name] = self.dropped.get(name, 0) + sum(o.numRowsDroppedByWatermark for o in p.stateOperators)

    def onQueryIdle(self, event):
        pass

    def onQueryTerminated(self, event):
        pass


def arrow_bytes(df: DataFrame) -> int:
    """Size of a small result in memory."""
    return pa.Table.from_pandas(df.toPandas()).nbytes


def report_udtf(spark: SparkSession):
    """Registers ``f2_report(p)``: SELECT * FROM f2_report(16) gives fitted widths and reads of a spec with p parts."""
    from pyspark.sql.functions import udtf

    from ..operators.measures import reads
    from ..spec import PAPER, fit_width

    @udtf(returnType="layout string, k int, reads bigint")
    class F2Report:
        def eval(self, p: int):
            spec = PAPER.but(P=p)
            for layout, method in (("plain", "part_cm"), ("composite", "exact_buffers"), ("composite", "projected")):
                yield layout, fit_width(spec, layout), reads(spec.but(K=max(1, fit_width(spec, layout))), method)

    spark.udtf.register("f2_report", F2Report)


def f2_view(spark: SparkSession, d: str, spec: SketchSpec, names: list[str], view: str = "f2_of_streams") -> None:
    """Registers a view (stream, f1, f2, exact) over streams: SELECT * FROM f2_of_streams WHERE stream = 'S3' reads S3 alone."""
    from ..operators import exact, ladder
    from ..sources.streams import STREAMS

    out = None
    for name in names:
        s = STREAMS[name](spark, d)
        row = ladder.part_cm(s, spec).crossJoin(exact.moments(s).select("f1", F.col("f2").alias("exact"))).select(F.lit(name).alias("stream"), "f1", "f2", "exact")
        out = row if out is None else out.unionByName(row)
    out.createOrReplaceTempView(view)
