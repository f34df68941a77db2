"""Queries of the frequency engine and their DuckDB twins.

Estimates stand beside the exact value, so an estimator that is secretly exact
would show.  Sums that may pass 2^63 are cast to BIGINT on the test tables.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import store
from .functions.hashing import canon_key, sql_fold, sql_owner, sql_row, sql_sign
from .operators import agms, baselines, buffers, cm, composite, consistency, exact, interleave, ladder, measures, slots, static_state
from .relational import RELATIONAL
from .sources import streams
from .sources.streams import STREAMS, sql_stream
from .spec import TEST, SketchSpec
from .streaming import queries as live
from .workloads import WORKLOADS, weighted, zipf_rows
from .workspace import Workspace

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def _long(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("bigint") for c in columns})


# ------------------------------------------------------------------ SQL pieces

T = TEST
H, K, P, C, B = T.H, T.K, T.P, T.C, T.B


def _freq(stream: str, z: float = 1.5) -> str:
    """WITH s(seq, k, x, weight), raw(k, x, f) of keys as given, f(x, f, part) of folded ones."""
    return f"""s AS (SELECT seq, k, {sql_fold("k")} AS x, weight FROM ({sql_stream(stream, z)})),
raw AS (SELECT k, any_value(x) AS x, CAST(sum(weight) AS BIGINT) AS f FROM s GROUP BY k),
f AS (SELECT x, CAST(sum(weight) AS BIGINT) AS f, {sql_owner("x", T)} AS part FROM s GROUP BY x)"""


def _cells(source: str, part: str, shift: str = "0", spec: SketchSpec = T) -> str:
    """A cell table over rows (x, f, part)."""
    return " UNION ALL ".join(f"SELECT {part} AS part, {j} AS row, CAST({sql_row('x', spec, j)} + {shift} AS INT) AS col, sum(f) AS cnt FROM {source} GROUP BY ALL" for j in range(spec.H))


def _plus(cells: str) -> str:
    return f"(SELECT coalesce(sum(v), 0) FROM (SELECT part, min(sq) AS v FROM (SELECT part, row, sum(cnt * cnt) AS sq FROM {cells} GROUP BY part, row) GROUP BY part))"


def _median(cells: str) -> str:
    lo, hi = (H + 1) // 2, H // 2 + 1
    return f"(SELECT (list_sort(list(sq))[{lo}] + list_sort(list(sq))[{hi}]) // 2 FROM (SELECT row, sum(cnt * cnt) AS sq FROM {cells} GROUP BY row))"


_MINUS = f"""(SELECT (list_sort(list(sq))[{(H + 1) // 2}] + list_sort(list(sq))[{H // 2 + 1}]) // 2 FROM (SELECT row, sum(d * d) AS sq FROM
  (SELECT row, col // 2 AS pair, sum(CASE WHEN col % 2 = 0 THEN cnt ELSE -cnt END) AS d FROM c1 GROUP BY ALL) GROUP BY row))"""
_EXACT2 = "(SELECT CAST(sum(f * f) AS BIGINT) FROM raw)"


def _signed(source: str = "f") -> str:
    return " UNION ALL ".join(f"SELECT 0 AS part, {j} AS row, {sql_row('x', T, j)} AS col, sum(f * {sql_sign('x', T, j)}) AS cnt FROM {source} GROUP BY ALL" for j in range(H))


_SINGLE, _PARTS, _WIDE = _cells("f", "0"), _cells("f", "part"), _cells("f", "0", f"part * {K}")
_SETTLED = f"""h AS (SELECT x, f, part FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY f DESC, x) AS r FROM f) WHERE r <= {C}),
light AS (SELECT * FROM f WHERE x NOT IN (SELECT x FROM h))"""


# ------------------------------------------------------------------ exact


@register("exact_freq", f"SELECT k AS key, CAST(sum(weight) AS BIGINT) AS f FROM ({sql_stream('S3')}) GROUP BY k")
def exact_freq(spark, d):
    return exact.counts(STREAMS["S3"](spark, d)).select(F.col("k").alias("key"), F.col("f").cast("bigint").alias("f"))


@register(
    "exact_moments",
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {_freq(n)} SELECT '{n}' AS stream, count(*) AS f0, CAST(sum(f) AS BIGINT) AS f1, CAST(sum(f * f) AS BIGINT) AS f2, CAST(sum(f * f * f) AS BIGINT) AS f3, max(f) AS max_f FROM raw)"
        for n in ("S1", "S2", "S3", "S4", "S5", "S6", "S7", "S8", "S9", "S10", "S11", "S12")
    ),
)
def exact_moments(spark, d):
    out = None
    for n in ("S1", "S2", "S3", "S4", "S5", "S6", "S7", "S8", "S9", "S10", "S11", "S12"):
        row = _powers(STREAMS[n](spark, d)).select(F.lit(n).alias("stream"), "*")
        out = row if out is None else out.unionByName(row)
    return _narrowed(Workspace(spark, "moments").save(out, "rows"), "f2", "f3")


def _powers(s: DataFrame) -> DataFrame:
    """One row: f0, f1, f2, f3, max_f; the sums of powers as decimals, which hold what BIGINT does not."""
    f = F.col("f").cast("decimal(12,0)")
    sums = [F.sum(cm.square(F.col("f"))).alias("f2"), F.sum(f * f * f).cast(cm.BIG).alias("f3")]
    return exact.counts(s).agg(F.count("*").alias("f0"), F.sum("f").cast("bigint").alias("f1"), *[c.cast(cm.BIG) for c in sums], F.max("f").cast("bigint").alias("max_f")).toDF("f0", "f1", "f2", "f3", "max_f")


def _narrowed(df: DataFrame, *columns: str) -> DataFrame:
    """Columns whose values all fit in BIGINT as BIGINT, as the twins have them; the others stay decimals, with every digit."""
    most = df.agg(*[F.max(c).alias(c) for c in columns]).first()
    return _long(df, *[c for c in columns if (most[c] or 0) < 1 << 63])


@register(
    "skew_fit",
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {_freq(n)}, r AS (SELECT ln(f) AS y, ln(row_number() OVER (ORDER BY f DESC)) AS lr FROM raw) SELECT '{n}' AS stream, round(-regr_slope(y, lr), 6) AS z FROM r)" for n in ("S1", "S7", "S8")
    ),
)
def skew_fit(spark, d):
    out = None
    for n in ("S1", "S7", "S8"):
        row = exact.skew(STREAMS[n](spark, d)).select(F.lit(n).alias("stream"), F.round("z", 6).alias("z"))
        out = row if out is None else out.unionByName(row)
    return out


# ------------------------------------------------------------------ linear sketches


@register("cm_cells", f"WITH {_freq('S3')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def cm_cells(spark, d):
    return cm.build(STREAMS["S3"](spark, d), T, "parts")


def _asked(spark, d, stream: str = "S3") -> DataFrame:
    """All keys of the stream, and absent ones."""
    here = STREAMS[stream](spark, d).select("key")
    return here.union(spark.range(50).select((F.col("id") * 7919 + 13).alias("key"))).distinct()


_ASKED = "q AS (SELECT x FROM f UNION SELECT range * 7919 + 13 FROM range(50))"


def _estimates(cells: str, part: str = "0") -> str:
    rows = " UNION ALL ".join(f"SELECT x, {part} AS part, {j} AS row, {sql_row('x', T, j)} AS col FROM q" for j in range(H))
    return f"SELECT a.x, min(coalesce(c.cnt, 0)) AS est FROM ({rows}) a LEFT JOIN {cells} c ON a.part = c.part AND a.row = c.row AND a.col = c.col GROUP BY a.x"


def _beside_truth(est: DataFrame, s: DataFrame) -> DataFrame:
    """(key, est, exact) per key as it was given; absent ones by their folded form."""
    return est.join(exact.counts(s), "key", "left").select(F.coalesce("k", F.col("key").cast("string")).alias("key"), "est", F.coalesce("f", F.lit(0)).cast("bigint").alias("exact"))


@register("cm_point_all", f"WITH {_freq('S3')}, {_ASKED}, c1 AS ({_SINGLE}), e AS ({_estimates('c1')}) SELECT coalesce(k, CAST(e.x AS VARCHAR)) AS key, CAST(est AS BIGINT) AS est, coalesce(f, 0) AS exact FROM e LEFT JOIN raw USING (x)")
def cm_point_all(spark, d):
    s = STREAMS["S3"](spark, d)
    est = cm.point(cm.build(s, T), _asked(spark, d), T)
    return _beside_truth(est, s)


@register("cm_f1", f"WITH {_freq('S4')}, c1 AS ({_SINGLE}) SELECT row, CAST(sum(cnt) AS BIGINT) AS f1 FROM c1 GROUP BY row")
def cm_f1(spark, d):
    cells = cm.build(STREAMS["S4"](spark, d), T)
    out = None
    for j in range(H):
        row = cm.f1(cells, j).select(F.lit(j).alias("row"), "f1")
        out = row if out is None else out.unionByName(row)
    return out


@register("cm_f2_plus", f"WITH {_freq('S4')}, c1 AS ({_SINGLE}) SELECT CAST({_plus('c1')} AS BIGINT) AS f2, {_EXACT2} AS exact")
def cm_f2_plus(spark, d):
    s = STREAMS["S4"](spark, d)
    return _long(cm.f2_plus_total(cm.build(s, T)).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


@register("cm_f2_minus", f"WITH {_freq('S3')}, c1 AS ({_SINGLE}) SELECT CAST({_MINUS} AS BIGINT) AS f2, {_EXACT2} AS exact")
def cm_f2_minus(spark, d):
    s = STREAMS["S3"](spark, d)
    return _long(cm.f2_minus(cm.build(s, T), T).select("f2").crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


@register("cm_f2_rows", f"WITH {_freq('S7')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, CAST(sum(cnt * cnt) AS BIGINT) AS sq FROM c GROUP BY part, row")
def cm_f2_rows(spark, d):
    return _long(cm.f2_rows(cm.build(STREAMS["S7"](spark, d), T, "parts")), "sq")


@register("cm_merge", f"WITH a AS (SELECT 0 AS part, {sql_fold('k')} AS x, weight AS f FROM ({sql_stream('S1')}) UNION ALL SELECT 0, {sql_fold('k')}, weight FROM ({sql_stream('S3')})), c AS ({_cells('a', 'part')}) SELECT part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def cm_merge(spark, d):
    return cm.merge(cm.build(STREAMS["S1"](spark, d), T), cm.build(STREAMS["S3"](spark, d), T))


@register(
    "cm_inner",
    f"""WITH {_freq('S1')}, c1 AS ({_SINGLE}), g AS (SELECT k, {sql_fold('k')} AS x, sum(weight) AS f FROM ({sql_stream('S6')}) GROUP BY ALL), c2 AS ({_cells('g', '0')})
    SELECT CAST(min(v) AS BIGINT) AS est, (SELECT CAST(sum(raw.f * g.f) AS BIGINT) FROM raw JOIN g USING (k)) AS exact FROM (SELECT c1.row, sum(c1.cnt * c2.cnt) AS v FROM c1 JOIN c2 USING (row, col) GROUP BY c1.row)""",
)
def cm_inner(spark, d):
    a, b = STREAMS["S1"](spark, d), STREAMS["S6"](spark, d)
    truth = exact.counts(a).drop("key").join(exact.counts(b).drop("key").withColumnRenamed("f", "g"), "k").agg(F.sum(F.col("f") * F.col("g")).cast("bigint").alias("exact"))
    return _long(cm.inner(cm.build(a, T), cm.build(b, T)).crossJoin(truth), "est")


@register("agms_f2", f"WITH {_freq('S3')}, c AS ({_signed()}) SELECT CAST({_median('c')} AS BIGINT) AS f2, {_EXACT2} AS exact")
def agms_f2(spark, d):
    s = STREAMS["S3"](spark, d)
    return _long(agms.f2(agms.build(s, T), T).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


@register("ams_f2", f"WITH {_freq('S3')} SELECT CAST(floor((" + " + ".join(f"(SELECT sum(f * {sql_sign('x', T, j)}) ** 2 FROM f)" for j in range(H)) + f") / {H}) AS BIGINT) AS f2, {_EXACT2} AS exact")
def ams_f2(spark, d):
    s = STREAMS["S3"](spark, d)
    return _long(agms.classic(s, T).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


@register(
    "f2_auto",
    " UNION ALL ".join(
        f"""SELECT * FROM (WITH {_freq(n, z)}, c1 AS ({_SINGLE}), z AS (SELECT -regr_slope(ln(f), lr) AS z FROM (SELECT f, ln(row_number() OVER (ORDER BY f DESC)) AS lr FROM raw))
      SELECT '{n}' AS stream, CASE WHEN z > 1 THEN 'plus' ELSE 'minus' END AS kind, CAST(CASE WHEN z > 1 THEN {_plus('c1')} ELSE {_MINUS} END AS BIGINT) AS f2, {_EXACT2} AS exact FROM z)"""
        for n, z in (("S3", 0), ("S8", 2))
    ),
)
def f2_auto(spark, d):
    out = None
    for n, s in (("S3", STREAMS["S3"](spark, d)), ("S8", streams.s8_zipf(spark, d, 2))):
        row = cm.f2_auto(s, T).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))).select(F.lit(n).alias("stream"), "kind", "f2", "exact")
        out = row if out is None else out.unionByName(row)
    return _long(out, "f2", "exact")


# ------------------------------------------------------------------ ladder


@register("owner_load", f"WITH {_freq('S7')} SELECT CAST(part AS INT) AS part, count(*) AS keys, CAST(sum(f) AS BIGINT) AS updates FROM f GROUP BY part")
def owner_load(spark, d):
    return ladder.owner_load(STREAMS["S7"](spark, d), T)


def _rung(name: str, fn, cells: str, stream: str):
    @register(name, f"WITH {_freq(stream)}, c AS ({cells}) SELECT CAST({_plus('c')} AS BIGINT) AS f2, {_EXACT2} AS exact")
    def run(spark, d):
        s = STREAMS[stream](spark, d)
        return _long(fn(s, T).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


_rung("wide_f2", ladder.wide, _WIDE, "S3")
_rung("part_cm_f2", ladder.part_cm, _PARTS, "S3")


@register("settled_slots", f"WITH {_freq('S7')}, {_SETTLED} SELECT CAST(part AS INT) AS part, x AS key, f AS cnt FROM h")
def settled_slots(spark, d):
    return slots.settled(STREAMS["S7"](spark, d), T)[1].select("part", "key", "cnt")


@register("settled_f2", f"WITH {_freq('S3')}, {_SETTLED}, c AS ({_cells('light', 'part')}) SELECT CAST({_plus('c')} + (SELECT sum(f * f) FROM h) AS BIGINT) AS f2, {_EXACT2} AS exact")
def settled_f2(spark, d):
    s = STREAMS["S3"](spark, d)
    return _long(ladder.part_slots(s, T).crossJoin(exact.moments(s).select(F.col("f2").alias("exact"))), "f2", "exact")


@register("settled_point_all", f"WITH {_freq('S3')}, {_SETTLED}, {_ASKED}, c AS ({_cells('light', 'part')}), e AS ({_estimates('c', sql_owner('x', T))}) SELECT e.x AS key, CAST(coalesce(h.f, est) AS BIGINT) AS est FROM e LEFT JOIN h USING (x)")
def settled_point_all(spark, d):
    cells, top = slots.settled(STREAMS["S3"](spark, d), T)
    return slots.point(cells, top, _asked(spark, d), T)


@register(
    "ladder_report",
    " UNION ALL ".join(
        f"""SELECT * FROM (WITH {_freq(n)}, {_SETTLED}, c1 AS ({_SINGLE}), cw AS ({_WIDE}), cp AS ({_PARTS}), cl AS ({_cells('light', 'part')}), cs AS ({_signed()})
      SELECT '{n}' AS stream, method, CAST(v AS BIGINT) AS f2, {_EXACT2} AS exact FROM (SELECT 'single' AS method, {_plus('c1')} AS v UNION ALL SELECT 'wide', {_plus('cw')} UNION ALL SELECT 'part_cm', {_plus('cp')}
        UNION ALL SELECT 'part_slots', {_plus('cl')} + (SELECT sum(f * f) FROM h) UNION ALL SELECT 'agms', {_median('cs')} UNION ALL SELECT 'minus', {_MINUS}))"""
        for n in ("S7", "S8")
    ),
)
def ladder_report(spark, d):
    out = None
    for n in ("S7", "S8"):
        row = ladder.report(STREAMS[n](spark, d), T).select(F.lit(n).alias("stream"), "method", "f2", "exact")
        out = row if out is None else out.unionByName(row)
    return _long(out, "f2", "exact")


@register("w9_weighted", SQL["ladder_report"].split(" UNION ALL SELECT * FROM (WITH")[0].replace("SELECT 'S7' AS stream, method", "SELECT method").replace(sql_stream("S7"), sql_stream("S4")))
def w9_weighted(spark, d):
    """All order-free methods on weighted updates."""
    return _long(weighted(spark, d), "f2", "exact")


# ------------------------------------------------------------------ buffers and the composite, static slots

_CHUNKS = f"""s AS (SELECT seq, k, {sql_fold("k")} AS x FROM ({sql_stream('S1')})),
o AS (SELECT seq, x, CAST(seq % {P} AS INT) AS producer, {sql_owner("x", T)} AS owner FROM s),
r AS (SELECT *, row_number() OVER (PARTITION BY producer, owner ORDER BY seq, x) AS rank, count(*) OVER (PARTITION BY producer, owner) AS n FROM o),
k AS (SELECT seq, x, producer, owner, (rank - 1) // {B} AS chunk, ((rank - 1) // {B} + 1) * {B} <= n AS handed,
  CASE WHEN ((rank - 1) // {B} + 1) * {B} <= n THEN max(seq) OVER (PARTITION BY producer, owner, (rank - 1) // {B}) END AS flush_seq FROM r)"""


def _state_sql(until: str | None = None) -> str:
    rows = "k" if until is None else f"(SELECT seq, x, producer, owner, chunk, flush_seq, handed AND flush_seq <= {until} AS handed FROM k WHERE seq <= {until})"
    return f"""kk AS (SELECT * FROM {rows}),
hf AS (SELECT x, owner AS part, count(*) AS f FROM kk WHERE handed GROUP BY ALL),
h AS (SELECT x, part, f FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY f DESC, x) AS r FROM hf) WHERE r <= {C}),
light AS (SELECT * FROM hf WHERE x NOT IN (SELECT x FROM h)),
c AS ({_cells('light', 'part')}),
buf AS (SELECT x, count(*) AS buf FROM kk WHERE NOT handed GROUP BY x),
fl AS (SELECT x, flush_seq, producer, count(*) AS v FROM kk WHERE handed AND x IN (SELECT x FROM h) GROUP BY ALL),
av AS (SELECT x, list_reduce(list(v::DOUBLE ORDER BY flush_seq, producer), lambda a, v: {T.w} * v + (1 - {T.w}) * a) AS avg FROM fl GROUP BY x),
hs AS (SELECT h.*, coalesce(buf, 0) AS buf, avg FROM h LEFT JOIN buf USING (x) JOIN av USING (x))"""


_STATE = f"{_CHUNKS}, {_state_sql()}"


def _state(spark, d) -> static_state.State:
    return static_state.build(STREAMS["S1"](spark, d), T)


@register("buffer_chunks", f"WITH {_CHUNKS} SELECT seq, x AS key, producer, CAST(owner AS INT) AS owner, chunk, handed, flush_seq FROM k")
def buffer_chunks(spark, d):
    return buffers.chunks(STREAMS["S1"](spark, d), T)


@register("buffer_residual", f"WITH {_CHUNKS} SELECT producer, CAST(owner AS INT) AS owner, x AS key, count(*) AS cnt FROM k WHERE NOT handed GROUP BY ALL")
def buffer_residual(spark, d):
    return buffers.residual(buffers.chunks(STREAMS["S1"](spark, d), T))


@register("buffer_bound", f"WITH {_CHUNKS} SELECT CAST(owner AS INT) AS owner, count(*) FILTER (WHERE NOT handed) AS n, {P * B}::BIGINT AS bound, count(*) FILTER (WHERE NOT handed) <= {P * B} AS ok FROM k GROUP BY owner")
def buffer_bound(spark, d):
    return buffers.buffered(buffers.chunks(STREAMS["S1"](spark, d), T), T)


@register("composite_point", f"WITH {_STATE}, raw AS (SELECT k, any_value(x) AS x, count(*) AS n FROM s GROUP BY k), q AS (SELECT DISTINCT x FROM raw), e AS ({_estimates('c', sql_owner('x', T))}) SELECT k AS key, CAST(coalesce(h.f, est) + coalesce(buf, 0) AS BIGINT) AS est, n AS exact FROM raw JOIN e USING (x) LEFT JOIN h USING (x) LEFT JOIN buf USING (x)")
def composite_point(spark, d):
    s = STREAMS["S1"](spark, d)
    return _beside_truth(static_state.point(_state(spark, d), s.select("key")), s)


@register("f1_counters", "SELECT count(*) AS f1 FROM events WHERE user_id IS NOT NULL")
def f1_counters(spark, d):
    return static_state.f1(STREAMS["S1"](spark, d), T)


def _f2_of(name: str, fn, heavy: str):
    @register(name, f"WITH {_STATE} SELECT CAST({_plus('c')} + (SELECT sum({heavy}) FROM hs) AS BIGINT) AS f2, (SELECT CAST(sum(n * n) AS BIGINT) FROM (SELECT count(*) AS n FROM s GROUP BY k)) AS exact")
    def run(spark, d):
        truth = exact.moments(STREAMS["S1"](spark, d)).select(F.col("f2").alias("exact"))
        return _long(fn(_state(spark, d)).crossJoin(truth), "f2", "exact")


_f2_of("f2_buffers_exact", static_state.f2_exact_buffers, "(f + buf) * (f + buf)")
_f2_of("f2_buffers_ignored", static_state.f2_ignore_buffers, "f * f")


@register("f2_projected", f"WITH {_STATE} SELECT round(CAST({_plus('c')} AS DOUBLE) + (SELECT sum((f + {P / 2} * avg) ** 2) FROM hs), 3) AS f2")
def f2_projected(spark, d):
    return static_state.f2_projected(_state(spark, d)).select(F.round("f2", 3).alias("f2"))


@register("slot_ewma", f"WITH {_STATE} SELECT CAST(part AS INT) AS part, x AS key, f AS cnt, round(avg, 6) AS avg FROM hs")
def slot_ewma(spark, d):
    return _state(spark, d).slots.select("part", "key", "cnt", F.round("avg", 6).alias("avg"))


@register("topk_slots", f"WITH {_STATE} SELECT x AS key, CAST(f + buf AS BIGINT) AS est FROM hs ORDER BY est DESC, key LIMIT 10")
def topk_slots(spark, d):
    return static_state.topk(_state(spark, d), 10)


# ------------------------------------------------------------------ policies


@register("exclusive_f1", f"WITH {_STATE} SELECT CAST((SELECT sum(cnt) FROM c WHERE row = 0) + (SELECT sum(f) FROM h) + (SELECT sum(buf) FROM buf) AS BIGINT) AS f1")
def exclusive_f1(spark, d):
    return static_state.exclusive_f1(_state(spark, d))


@register("exclusive_f2", f"WITH {_freq('S1')}, cp AS ({_PARTS}), c1 AS ({_SINGLE}) SELECT 'partitioned' AS merge, CAST({_plus('cp')} AS BIGINT) AS f2 UNION ALL SELECT 'elementwise', CAST({_plus('c1')} AS BIGINT)")
def exclusive_f2(spark, d):
    state = _state(spark, d)
    rows = [static_state.exclusive_f2(state, m).select(F.lit(m).alias("merge"), "f2") for m in ("partitioned", "elementwise")]
    return _long(rows[0].unionByName(rows[1]), "f2")


SCANS = 4  # scans of the whole stream: at each quarter of it, the last after its end


def _scan(s: DataFrame, i: int) -> tuple[int, int, int, int]:
    """(t0, step, delta, width) of the i-th scan, i in 1..SCANS, as shares of the last seq of the stream."""
    last = s.agg(F.max("seq")).first()[0] or 0
    return last * i // SCANS, max(1, last // 100), max(1, last // 60), max(1, last // 750)


_LAST = f"(SELECT coalesce(max(seq), 0)::BIGINT FROM ({sql_stream('S1')}))"


def _scan_sql(i: int) -> tuple[str, str, str, str]:
    return f"({_LAST} * {i} // {SCANS})", f"greatest(1, {_LAST} // 100)", f"greatest(1, {_LAST} // 60)", f"greatest(1, {_LAST} // 750)"


def _every_scan(sql) -> str:
    return " UNION ALL ".join(f"SELECT {i} AS scan, * FROM ({sql(*_scan_sql(i))})" for i in range(1, SCANS + 1))


def _each_scan(s: DataFrame, run) -> DataFrame:
    out = None
    for i in range(1, SCANS + 1):
        row = run(*_scan(s, i)).select(F.lit(i).alias("scan"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _unsynced_sql(order: str):
    def sql(t0, step, delta, width=None) -> str:
        looks = ("t", f"t + {delta}") if order == "sketch_first" else (f"t + {delta}", "t")
        return f"""WITH {_CHUNKS}, w AS (SELECT owner, seq, coalesce(flush_seq, {1 << 62}) AS gone, {t0} + owner * {step} AS t FROM k),
        l AS (SELECT owner, t, seq <= t AS here, gone <= {looks[0]} AS a, seq <= {looks[1]} AND gone > {looks[1]} AS b FROM w)
        SELECT CAST(owner AS INT) AS part, CAST(t AS BIGINT) AS t, count(*) FILTER (WHERE here) AS arrived, count(*) FILTER (WHERE a) AS in_sketch, count(*) FILTER (WHERE b) AS in_buffer,
          count(*) FILTER (WHERE here AND NOT a AND NOT b) AS missed, count(*) FILTER (WHERE a AND b) AS doubled FROM l GROUP BY owner, t"""

    return sql


def _unsynced(name: str, order: str):
    @register(f"{name}_whole", _every_scan(_unsynced_sql(order)))
    def run(spark, d):
        s = STREAMS["S1"](spark, d)
        return _each_scan(s, lambda t0, step, delta, _: interleave.unsynced(s, T, t0, step, delta, order))


_unsynced("unsynced_missed", "sketch_first")
_unsynced("unsynced_double", "buffers_first")


def _unsynced_f2_sql(t0, step, delta, width=None) -> str:
    return " UNION ALL ".join(
        f"""SELECT * FROM (WITH {_CHUNKS}, a AS (SELECT x, owner AS part, count(*) FILTER (WHERE coalesce(flush_seq, {1 << 62}) <= {t0} + owner * {step} + {ds}) AS f,
      count(*) FILTER (WHERE seq <= {t0} + owner * {step} + {db} AND coalesce(flush_seq, {1 << 62}) > {t0} + owner * {step} + {db}) AS b FROM k GROUP BY ALL),
      h AS (SELECT x FROM a WHERE f > 0 QUALIFY row_number() OVER (PARTITION BY part ORDER BY f DESC, x) <= {C}),
      lt AS (SELECT x, part, f FROM a WHERE x NOT IN (SELECT x FROM h) AND f > 0), cl AS ({_cells('lt', 'part')}),
      lp AS (SELECT part, min(sq) AS v FROM (SELECT part, row, sum(cnt * cnt) AS sq FROM cl GROUP BY ALL) GROUP BY part), hp AS (SELECT part, sum((f + b) * (f + b)) AS w FROM a WHERE x IN (SELECT x FROM h) GROUP BY part)
      SELECT '{o}' AS read_order, CAST(part AS INT) AS part, CAST(coalesce(v, 0) + coalesce(w, 0) AS BIGINT) AS f2 FROM (SELECT range AS part FROM range({P})) LEFT JOIN lp USING (part) LEFT JOIN hp USING (part))"""
        for o, ds, db in (("sketch_first", 0, delta), ("buffers_first", delta, 0))
    )


def _unsynced_f2(s, t0, step, delta, width=None) -> DataFrame:
    rows = [interleave.unsynced_f2(s, T, t0, step, delta, o).select(F.lit(o).alias("read_order"), "part", "f2") for o in ("sketch_first", "buffers_first")]
    return _long(rows[0].unionByName(rows[1]), "f2")


@register("unsynced_f2_whole", _every_scan(_unsynced_f2_sql))
def unsynced_f2_whole(spark, d):
    s = STREAMS["S1"](spark, d)
    return _each_scan(s, lambda *at: _unsynced_f2(s, *at))


def _versioned_sql(t0, step, delta, width) -> str:
    return f"""WITH {_CHUNKS}, e AS (SELECT DISTINCT owner AS part, producer, flush_seq, {t0} + owner * {step} AS t FROM k WHERE handed),
ag AS (SELECT part, min(flush_seq) AS again FROM e WHERE flush_seq > t AND flush_seq <= t + {width} GROUP BY part),
pt AS (SELECT range AS part, {t0} + range * {step} AS t, again FROM range({P}) LEFT JOIN ag ON part = range),
sn AS (SELECT k.*, pt.part FROM k JOIN pt ON k.owner = pt.part WHERE flush_seq <= coalesce(again, t)),
vf AS (SELECT x, part, count(*) AS f FROM sn GROUP BY ALL),
h AS (SELECT x FROM vf QUALIFY row_number() OVER (PARTITION BY part ORDER BY f DESC, x) <= {C}), vl AS (SELECT * FROM vf WHERE x NOT IN (SELECT x FROM h)), cv AS ({_cells('vl', 'part')}),
lp AS (SELECT part, min(sq) AS v FROM (SELECT part, row, sum(cnt * cnt) AS sq FROM cv GROUP BY ALL) GROUP BY part),
va AS (SELECT x, list_reduce(list(n::DOUBLE ORDER BY flush_seq, producer), lambda a, v: {T.w} * v + (1 - {T.w}) * a) AS avg FROM (SELECT x, flush_seq, producer, count(*) AS n FROM sn WHERE x IN (SELECT x FROM h) GROUP BY ALL) GROUP BY x),
hp AS (SELECT part, sum((f + {P / 2} * avg) ** 2) AS w FROM vf JOIN va USING (x) GROUP BY part),
ve AS (SELECT part, count(*) AS v_end FROM e JOIN pt USING (part) WHERE flush_seq <= coalesce(again, pt.t) GROUP BY part)
SELECT CAST(pt.part AS INT) AS part, CAST(pt.t AS BIGINT) AS t, coalesce(v_end, 0) AS v_end, CAST(again IS NOT NULL AS INT) AS retries, round(coalesce(v, 0)::DOUBLE + coalesce(w, 0), 3) AS f2
FROM pt LEFT JOIN ve USING (part) LEFT JOIN lp USING (part) LEFT JOIN hp USING (part)"""


@register("versioned_f2_whole", _every_scan(_versioned_sql))
def versioned_f2_whole(spark, d):
    s = STREAMS["S1"](spark, d)
    return _each_scan(s, lambda t0, step, _, width: interleave.versioned(s, T, t0, step, width)).withColumn("f2", F.round("f2", 3))


def _concurrent_sql(t0, step, delta=None, width=None) -> str:
    seen = f"raw AS (SELECT 1), f AS (SELECT x, CAST(count(*) AS BIGINT) AS f, {sql_owner('x', T)} AS part FROM (SELECT seq, {sql_fold('k')} AS x FROM ({sql_stream('S1')})) WHERE seq <= {t0} + {sql_owner('x', T)} * {step} GROUP BY x)"
    return f"WITH {seen}, {_SETTLED}, cw AS ({_WIDE}), cp AS ({_PARTS}), cl AS ({_cells('light', 'part')}) SELECT 'wide' AS kind, CAST({_plus('cw')} AS BIGINT) AS f2 UNION ALL SELECT 'part_cm', CAST({_plus('cp')} AS BIGINT) UNION ALL SELECT 'part_slots', CAST({_plus('cl')} + (SELECT sum(f * f) FROM h) AS BIGINT)"


def _concurrent(s, t0, step, delta=None, width=None) -> DataFrame:
    out = None
    for kind in ("wide", "part_cm", "part_slots"):
        row = ladder.concurrent(s, T, kind, t0, step).select(F.lit(kind).alias("kind"), "f2")
        out = row if out is None else out.unionByName(row)
    return _long(out, "f2")


@register("concurrent_f2_whole", _every_scan(_concurrent_sql))
def concurrent_f2_whole(spark, d):
    """The rungs without buffers, read part after part while rows arrive, at each quarter of the stream; by the last scan all of it has arrived."""
    s = STREAMS["S1"](spark, d)
    return _each_scan(s, lambda *at: _concurrent(s, *at))


# ------------------------------------------------------------------ consistency

_GRAIN = "g AS (SELECT greatest(1, coalesce(max(event_id), 0) // 200) AS g FROM events)"
_ASK = f"""iv AS (SELECT t_start, t_start + {P} AS t_end FROM (SELECT unnest(range(0, greatest((SELECT max(ceil(seq / g)) FROM s, g) - {P}, 0)::BIGINT + 1, 4)) AS t_start))"""


def _grain(s: DataFrame) -> int:
    from .operators import prefix

    return prefix.grain_of(s)


def _interval_sql(value: str, kind: str) -> str:
    return f"""SELECT t_start, t_end, CAST(sum(lo) AS {kind}) AS lo, CAST(sum(val) AS {kind}) AS val, CAST(sum(hi) AS {kind}) AS hi, sum(lo) <= sum(val) AND sum(val) <= sum(hi) AS inside
  FROM (SELECT t_start, t_end, {value.format(t='t_start')} AS lo, {value.format(t='t_start + i.range')} AS val, {value.format(t='t_end')} AS hi FROM iv, range({P}) i) GROUP BY ALL"""


@register("ivl_f1", f"WITH s AS (SELECT seq FROM ({sql_stream('S1')})), {_GRAIN}, {_ASK} " + _interval_sql(f"(SELECT count(*) FROM s, g WHERE seq <= ({{t}}) * g AND seq % {P} = i.range)", "BIGINT"))
def ivl_f1(spark, d):
    s = STREAMS["S1"](spark, d)
    return consistency.ivl_f1(s, T, _grain(s))


_F2_AT = f"""s AS (SELECT seq, {sql_fold("k")} AS x FROM ({sql_stream('S1')})), {_GRAIN}, {_ASK},
tt AS (SELECT DISTINCT t FROM (SELECT t_start + unnest(range(0, {P + 1})) AS t FROM iv)),
pf AS (SELECT t, x, {sql_owner("x", T)} AS part, count(*) AS f FROM tt, g, s WHERE seq <= t * g GROUP BY ALL),
pc AS ({" UNION ALL ".join(f"SELECT t, part, {j} AS row, {sql_row('x', T, j)} AS col, sum(f) AS cnt FROM pf GROUP BY ALL" for j in range(H))}),
p2 AS (SELECT t, part, min(sq) AS v FROM (SELECT t, part, row, sum(cnt * cnt) AS sq FROM pc GROUP BY ALL) GROUP BY ALL)"""


@register("ivl_f2", f"WITH {_F2_AT} " + _interval_sql("coalesce((SELECT v FROM p2 WHERE p2.part = i.range AND p2.t = {t}), 0)", "BIGINT"))
def ivl_f2(spark, d):
    s = STREAMS["S1"](spark, d)
    return _long(consistency.ivl_f2(s, T, _grain(s)), "lo", "val", "hi")


@register(
    "relaxed_bound",
    f"""WITH {_CHUNKS}, {_GRAIN}, ev AS (SELECT owner AS part, ceil(seq / g)::BIGINT AS bucket, 1 AS n, 0 AS h FROM k, g UNION ALL SELECT owner, ceil(flush_seq / g)::BIGINT, 0, 1 FROM k, g WHERE handed),
    b AS (SELECT part, bucket, sum(n) AS n, sum(h) AS h FROM ev GROUP BY ALL), c AS (SELECT part, bucket, sum(n) OVER w AS total, sum(h) OVER w AS seen FROM b WINDOW w AS (PARTITION BY part ORDER BY bucket))
    SELECT CAST(part AS INT) AS part, bucket, CAST(total AS BIGINT) AS total, CAST(seen AS BIGINT) AS seen, {P * B}::BIGINT AS bound, total - seen <= {P * B} AS ok FROM c""",
)
def relaxed_bound(spark, d):
    s = STREAMS["S1"](spark, d)
    return consistency.relaxed_bound(s, T, _grain(s))


@register("visibility", f"WITH {_CHUNKS} SELECT seq, x AS key, 3 * seq AS t_point, 3 * seq + 1 AS t_f1, 3 * flush_seq + 2 AS t_f2 FROM k")
def visibility(spark, d):
    return consistency.visibility(STREAMS["S1"](spark, d), T)


_PAIR = {("point", "f1"): P, ("point", "f2"): P * B, ("f1", "f2"): P * P * B}
_MONO = " UNION ALL ".join(
    f"SELECT '{a}' AS q1, '{b}' AS q2, CAST(coalesce(max(n), 0) AS BIGINT) AS worst, {_PAIR.get((a, b), 0)}::BIGINT AS bound FROM (SELECT t, count(*) FILTER (WHERE t_{a} <= t AND (t_{b} IS NULL OR t_{b} > t)) AS n FROM v, tp GROUP BY t{', owner' if a == 'point' else ''})"
    for a in consistency.QUERIES
    for b in consistency.QUERIES
)


@register("monotone_matrix", f"WITH {_CHUNKS}, {_GRAIN}, v AS (SELECT owner, 3 * seq AS t_point, 3 * seq + 1 AS t_f1, 3 * flush_seq + 2 AS t_f2 FROM k), tp AS (SELECT unnest(range(0, (SELECT max(t_f1) FROM v) // (3 * g) + 2)) * 3 * g AS t FROM g), m AS ({_MONO}) SELECT *, worst <= bound AS ok FROM m")
def monotone_matrix(spark, d):
    s = STREAMS["S1"](spark, d)
    return consistency.monotone_matrix(s, T, _grain(s))


# ------------------------------------------------------------------ measures

ZS, SALTS = (1.0, 1.5, 2.0), 3


def _salted(spark, d) -> DataFrame:
    rows = zipf_rows(spark, d)
    out = None
    for z in ZS:
        for salt in range(SALTS):
            s = streams.s8_zipf(spark, d, z, str(salt), rows).select(F.lit(z).alias("z"), F.lit(salt).alias("salt"), "k", "key", "weight")
            out = s if out is None else out.unionByName(s)
    return out


def _salted_sql() -> str:
    parts = []
    for z in ZS:
        cuts = streams.zipf_thresholds(z)
        for salt in range(SALTS):
            parts.append(
                f"""SELECT {z}::DOUBLE AS z, {salt} AS salt, CAST(rank AS VARCHAR) AS k FROM (SELECT ('0x' || substr(md5('{salt}:' || range), 1, 7))::BIGINT AS u FROM (SELECT unnest(range(greatest(20000, (SELECT count(*) FROM lineitem) // 3)::BIGINT)) AS range))
        JOIN (SELECT i AS rank, CASE WHEN i = 1 THEN 0 ELSE c[i - 1] END AS lo, c[i] AS hi FROM (SELECT {cuts} AS c), range(1, {len(cuts) + 1}) t(i)) ON u >= lo AND u < hi"""
            )
    return " UNION ALL ".join(parts)


def _grouped(part: str, shift: str = "0") -> str:
    cells = " UNION ALL ".join(f"SELECT z, salt, {part} AS part, {j} AS row, {sql_row('x', T, j)} + {shift} AS col, sum(f) AS cnt FROM f GROUP BY ALL" for j in range(H))
    return f"SELECT z, salt, sum(v) AS f2 FROM (SELECT z, salt, part, min(sq) AS v FROM (SELECT z, salt, part, row, sum(cnt * cnt) AS sq FROM ({cells}) GROUP BY ALL) GROUP BY ALL) GROUP BY ALL"


@register(
    "f2_mape",
    f"""WITH s AS (SELECT z, salt, k, {sql_fold('k')} AS x FROM ({_salted_sql()})), f AS (SELECT z, salt, x, {sql_owner('x', T)} AS part, count(*) AS f FROM s GROUP BY ALL),
e AS (SELECT 'single' AS method, * FROM ({_grouped('0')}) UNION ALL SELECT 'wide', * FROM ({_grouped('0', f'part * {K}')}) UNION ALL SELECT 'part_cm', * FROM ({_grouped('part')})),
t AS (SELECT z, salt, sum(n * n) AS exact FROM (SELECT z, salt, count(*) AS n FROM s GROUP BY z, salt, k) GROUP BY ALL)
SELECT z, method, round(avg(abs(f2::DOUBLE - exact::DOUBLE) / exact::DOUBLE), 6) AS mape FROM e JOIN t USING (z, salt) GROUP BY z, method""",
)
def f2_mape(spark, d):
    report = measures.grouped_report(_salted(spark, d), T, ["z", "salt"])
    return measures.mape(report, ["z", "method"]).withColumn("mape", F.round("mape", 6))


@register(
    "point_error_all",
    f"""WITH {_freq('S3')}, {_ASKED}, c1 AS ({_SINGLE}), e AS ({_estimates('c1')}), b AS (SELECT est, coalesce(f, 0) AS f FROM e LEFT JOIN raw USING (x))
SELECT CASE WHEN f = 0 THEN 'absent' WHEN f >= 30 THEN 'heavy' ELSE 'light' END AS kind, count(*) AS n, round(avg(abs(est - f)::DOUBLE), 6) AS avg_error, CAST(max(abs(est - f)) AS BIGINT) AS max_error, round(avg((est = f)::INT::DOUBLE), 6) AS exact_share FROM b GROUP BY kind""",
)
def point_error_all(spark, d):
    s = STREAMS["S3"](spark, d)
    out = measures.point_error(cm.point(cm.build(s, T), _asked(spark, d), T), exact.counts(s), 30)
    return out.withColumns({c: F.round(c, 6) for c in ("avg_error", "exact_share")})


_PS = [1, 2, 4, 8, 16, 32, 64, 128]


@register(
    "memory_report",
    f"""WITH ex AS (SELECT count(DISTINCT k) AS n FROM ({sql_stream('S10')})), p AS (SELECT unnest({_PS}) AS P), k AS (SELECT P, unnest([{{'layout': 'plain', 'extra': 0}}, {{'layout': 'slots', 'extra': 16 * 16}}, {{'layout': 'composite', 'extra': 16 * 16 + P * (16 * 8 + 8)}}], recursive := true) FROM p)
SELECT r.*, 16 * n AS exact_bytes, total_bytes < 16 * n AS smaller FROM ex, (SELECT P, layout, CAST((4 * 8 * 1024 - extra) // (4 * 8) AS INT) AS k, CAST(4 * 8 * ((4 * 8 * 1024 - extra) // (4 * 8)) + extra AS BIGINT) AS part_bytes, CAST(P * (4 * 8 * ((4 * 8 * 1024 - extra) // (4 * 8)) + extra) AS BIGINT) AS total_bytes FROM k
UNION ALL SELECT P, layout, 8192, part_bytes, P * part_bytes FROM p, (SELECT 'separate' AS layout, (6 * 8192 * 4) * 2 AS part_bytes UNION ALL SELECT 'separate_f0', (6 * 8192 * 4) * 2 + (1 << 12))) r""",
)
def memory_report(spark, d):
    from .spec import PAPER

    return measures.memory_report(STREAMS["S10"](spark, d), PAPER, _PS)


@register(
    "reads_report",
    f"""WITH ex AS (SELECT count(DISTINCT k) AS n FROM ({sql_stream('S10')})), p AS (SELECT unnest({_PS})::BIGINT AS P) SELECT r.*, n AS exact_reads, reads < n AS fewer FROM ex, (SELECT CAST(P AS INT) AS P, 'exact_buffers' AS method, P * 8 * 1024 + P * P * 16 + 2 * P * 16 AS reads FROM p UNION ALL SELECT P, 'ignore_buffers', P * (8 + 2 * 16) FROM p
UNION ALL SELECT P, 'projected', P * (8 + 3 * 16) FROM p UNION ALL SELECT P, 'part_cm', P * 8 * 1024 FROM p) r""",
)
def reads_report(spark, d):
    from .spec import PAPER

    return measures.reads_report(STREAMS["S10"](spark, d), PAPER, _PS)


# ------------------------------------------------------------------ baselines and built-ins


@register("separate_sketches", f"WITH {_freq('S1')}, c AS ({_signed()}) SELECT CAST((SELECT sum(f) FROM f) AS BIGINT) AS f1, CAST({_median('c')} AS BIGINT) AS f2, true AS f0_close")
def separate_sketches(spark, d):
    s = STREAMS["S1"](spark, d)
    got = baselines.separate(s, T)
    f0 = got["f0"].crossJoin(s.agg(F.count_distinct("key").alias("n"))).select((F.abs(F.col("f0") - F.col("n")) <= 0.05 * F.col("n") + 2).alias("f0_close"))
    return _long(got["f1"].crossJoin(got["f2"]).crossJoin(f0), "f2")


@register("builtin_moments", f"WITH {_freq('S7')} SELECT count(*) AS f0, CAST(sum(f) AS BIGINT) AS f1, CAST(sum(f * f) AS BIGINT) AS f2, true AS f0_close FROM raw")
def builtin_moments(spark, d):
    out = baselines.builtin(STREAMS["S7"](spark, d))
    return _long(out.select("f0", "f1", "f2", (F.abs(F.col("f0_approx") - F.col("f0")) <= 0.1 * F.col("f0")).alias("f0_close")), "f2")


# ------------------------------------------------------------------ replays: order-dependent, checked by conservation


def _replayed(spark, d, stream: str = "S1", spec: SketchSpec = T, s: DataFrame | None = None):
    work = Workspace(spark, "replay")
    handoffs = work.save(buffers.replay(STREAMS[stream](spark, d) if s is None else s, spec), "handoffs")
    return work.save(composite.drain(handoffs, spec), "state"), handoffs


@register("replay_conserved", f"WITH {_freq('S1')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def replay_conserved(spark, d):
    state, handoffs = _replayed(spark, d)
    return composite.conserved_cells(state, handoffs, T)


def _split(spark, d, stream: str):
    work = Workspace(spark, "split")
    handoffs = work.save(buffers.combine(STREAMS[stream](spark, d), T), "handoffs")
    cells, slots_ = composite.drain_split(handoffs, T)
    return work.save(cells, "cells"), work.save(slots_, "slots"), handoffs


@register("split_conserved", f"WITH {_freq('S7')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def split_conserved(spark, d):
    """The form for many cores: map-side buffers, several writers a part; cells, gains and buffers add up to all rows."""
    cells, slots_, handoffs = _split(spark, d, "S7")
    rest = slots_.select("key", (F.col("cnt") - F.col("old")).alias("f")).unionByName(handoffs.filter("NOT handed").select("key", F.col("cnt").alias("f"))).filter("f > 0")
    return cm.merge(cells, cm.from_frequencies(rest.groupBy("key").agg(F.sum("f").alias("f")), T, "parts"))


@register("split_f2")
def split_f2(spark, d):
    cells, slots_, _ = _split(spark, d, "S7")
    return composite.merged_f2(cells, slots_, T).crossJoin(exact.moments(STREAMS["S7"](spark, d)).select(F.col("f2").cast("bigint").alias("exact")))


@register("slots_conserved", f"WITH {_freq('S12')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def slots_conserved(spark, d):
    return composite.conserved_cells(composite.replay_slots(STREAMS["S12"](spark, d), T), None, T)


@register("weighted_slots_conserved", f"WITH {_freq('S4')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def weighted_slots_conserved(spark, d):
    """Weighted updates through the ordered slots: cells and gains add up to all weights."""
    return composite.conserved_cells(composite.replay_slots(STREAMS["S4"](spark, d).withColumn("seq", F.coalesce("seq", F.monotonically_increasing_id())), T), None, T)


@register("slots_replay_f2")
def slots_replay_f2(spark, d):
    s = Workspace(spark, "slots").save(STREAMS["S7"](spark, d), "stream")  # read twice
    f2 = composite.f2_ignore_buffers(composite.replay_slots(s, T)).agg(F.sum("f2").alias("f2"))
    return f2.crossJoin(exact.moments(s).select(F.col("f2").cast("bigint").alias("exact")))


@register("composite_replay_f2")
def composite_replay_f2(spark, d):
    out = None
    for n in ("S1", "S7", "S8"):
        work = Workspace(spark, "moments")
        s = work.save(STREAMS[n](spark, d), "stream")
        state, handoffs = _replayed(spark, d, s=s)
        truth = work.save(exact.moments(s).select(F.col("f2").cast("bigint").alias("exact")), "truth")  # one row, read by every method
        for name, df in (("buffers_ignored", composite.f2_ignore_buffers(state)), ("buffers_exact", composite.f2_exact_buffers(state, handoffs)), ("projected", composite.f2_projected(state, T))):
            row = df.agg(F.sum("f2").alias("f2")).crossJoin(truth).select(F.lit(n).alias("stream"), F.lit(name).alias("method"), "f2", "exact")
            out = row if out is None else out.unionByName(row)
    return out


@register("composite_replay_point")
def composite_replay_point(spark, d):
    state, handoffs = _replayed(spark, d)
    s = STREAMS["S1"](spark, d)
    return composite.point(state, handoffs, s.select("key"), T).join(exact.counts(s).select("k", "key", F.col("f").cast("bigint").alias("exact")), "key").select(F.col("k").alias("key"), "est", "exact")


@register("replay_metrics")
def replay_metrics(spark, d):
    return composite.metrics(*_replayed(spark, d))


@register("buffers_only_point")
def buffers_only_point(spark, d):
    s = STREAMS["S1"](spark, d)
    return baselines.buffers_only(s, s.select("key"), T).join(exact.counts(s).select("k", "key", F.col("f").cast("bigint").alias("exact")), "key").select(F.col("k").alias("key"), "est", "exact")


@register("combine_f1", "SELECT count(*) AS f1 FROM events WHERE user_id IS NOT NULL")
def combine_f1(spark, d):
    """What the map-side buffers emit adds up to the stream."""
    return buffers.combine(STREAMS["S1"](spark, d), T).agg(F.sum("cnt").cast("bigint").alias("f1"))


# ------------------------------------------------------------------ streams and relational operators

_GROUPS = "SELECT event_type, CAST(sum(f * f) AS BIGINT) AS exact FROM (SELECT event_type, user_id, count(*) AS f FROM events GROUP BY ALL) GROUP BY event_type"


@register(
    "per_group_f2",
    f"""WITH f AS (SELECT event_type, {sql_fold('CAST(user_id AS VARCHAR)')} AS x, count(*) AS f FROM events GROUP BY ALL), c AS ({" UNION ALL ".join(f"SELECT event_type, {j} AS row, {sql_row('x', T, j)} AS col, sum(f) AS cnt FROM f GROUP BY ALL" for j in range(H))})
SELECT event_type, CAST(f2 AS BIGINT) AS f2, exact FROM (SELECT event_type, min(sq) AS f2 FROM (SELECT event_type, row, sum(cnt * cnt) AS sq FROM c GROUP BY ALL) GROUP BY event_type) JOIN ({_GROUPS}) USING (event_type)""",
)
def per_group_f2(spark, d):
    events = streams.load(spark, d, "events", ["event_id", "event_type", "user_id"])
    s = events.select("event_type", "user_id", canon_key(F.col("user_id")).alias("key"), F.lit(1).alias("weight"))
    truth = s.groupBy("event_type", "user_id").agg(F.sum("weight").alias("f")).groupBy("event_type").agg(F.sum(F.col("f") * F.col("f")).cast("bigint").alias("exact"))
    return _long(cm.f2_plus(cm.build(s, T, by=["event_type"]), ["event_type"]).select("event_type", "f2").join(truth, "event_type"), "f2")


@register("zipf_stream", f"SELECT seq, CAST(k AS INT) AS rank FROM ({sql_stream('S8')})")
def zipf_stream(spark, d):
    return streams.s8_zipf(spark, d).select("seq", F.col("k").cast("int").alias("rank"))


@register("tokens", f"SELECT k AS word, count(*) AS n FROM ({sql_stream('S7')}) GROUP BY k")
def tokens(spark, d):
    return STREAMS["S7"](spark, d).groupBy(F.col("k").alias("word")).agg(F.count("*").alias("n"))


@register("hosts", f"SELECT k AS host, count(*) AS n FROM ({sql_stream('S9')}) GROUP BY k")
def hosts(spark, d):
    return STREAMS["S9"](spark, d).groupBy(F.col("k").alias("host")).agg(F.count("*").alias("n"))


# ------------------------------------------------------------------ streams that arrive


def _arriving(spark: SparkSession, d: str) -> DataFrame:
    return live.keyed(spark.readStream.schema(streams.SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").parquet(d))


def _run_stream(spark: SparkSession, d: str, make, mode: str) -> DataFrame:
    """Run a streaming query over the events file until it is read, and return its result table."""
    work = Workspace(spark, "stream")
    return live.run_available(make(_arriving(spark, d)), f"mixedsketch_{uuid.uuid4().hex}", work.path("checkpoint"), mode)


@register("stream_window_f1", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS f1 FROM events GROUP BY 1")
def stream_window_f1(spark, d):
    out = _run_stream(spark, d, live.window_f1, "complete")
    return out.select(F.to_date("start").cast("string").alias("day"), F.col("f1").cast("bigint").alias("f1"))


@register(
    "stream_sliding_f1",
    """SELECT strftime(day + INTERVAL (i) DAY, '%Y-%m-%d') AS first_day, CAST(sum(n) AS BIGINT) AS f1 FROM (SELECT CAST(ts AS DATE) AS day, count(*) AS n FROM events WHERE user_id IS NOT NULL GROUP BY 1), (SELECT unnest([0, -1, -2]) AS i) GROUP BY 1""",
)
def stream_sliding_f1(spark, d):
    """Windows of three days, one a day."""
    out = _run_stream(spark, d, lambda e: live.window_f1(e, "3 days", "1 day"), "complete")
    return out.select(F.to_date("start").cast("string").alias("first_day"), F.col("f1").cast("bigint").alias("f1"))


@register(
    "stream_cm_window",
    f"""WITH f AS (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, {sql_fold('CAST(user_id AS VARCHAR)')} AS x, count(*) AS f FROM events GROUP BY ALL)
    SELECT day, row, CAST(col AS INT) AS col, CAST(sum(f) AS BIGINT) AS cnt FROM ({" UNION ALL ".join(f"SELECT day, {j} AS row, {sql_row('x', T, j)} AS col, f FROM f" for j in range(H))}) GROUP BY ALL""",
)
def stream_cm_window(spark, d):
    out = _run_stream(spark, d, lambda e: live.window_cells(e, T), "complete")
    return out.select(F.to_date("start").cast("string").alias("day"), "row", "col", F.col("cnt").cast("bigint").alias("cnt"))


@register("stream_panes", SQL["stream_cm_window"])
def stream_panes(spark, d):
    """The matrices of all days, written batch by batch without any state and added up when read."""
    work = Workspace(spark, "panes")
    live.panes_to_store(_arriving(spark, d), work.path("store"), T, work.path("checkpoint")).awaitTermination()
    out = store.load(spark, work.path("store"), T, by=("start",))
    return out.select(F.to_date("start").cast("string").alias("day"), "row", "col", F.col("cnt").cast("bigint").alias("cnt"))


@register(
    "stream_sliding_f2",
    f"""WITH f AS (SELECT strftime(CAST(ts AS DATE) + INTERVAL (i) DAY, '%Y-%m-%d') AS first_day, {sql_fold('CAST(user_id AS VARCHAR)')} AS x, count(*) AS f FROM events, (SELECT unnest([0, -1, -2]) AS i) WHERE user_id IS NOT NULL GROUP BY ALL)
    SELECT first_day, CAST(min(sq) AS BIGINT) AS f2 FROM (SELECT first_day, row, sum(cnt * cnt) AS sq FROM ({" UNION ALL ".join(f"SELECT first_day, {j} AS row, {sql_row('x', T, j)} AS col, sum(f) AS cnt FROM f GROUP BY ALL" for j in range(H))}) GROUP BY ALL) GROUP BY first_day""",
)
def stream_sliding_f2(spark, d):
    """F2 of windows of three days, one a day, from the matrices of days."""
    panes = _run_stream(spark, d, lambda e: live.window_cells(e, T), "complete")
    out = live.window_f2(live.sliding_cells(panes, 1, 3))
    return out.select(F.to_date("start").cast("string").alias("first_day"), F.col("f2").cast("bigint").alias("f2"))


@register("stream_composite_conserved", f"WITH {_freq('S1')}, c AS ({_PARTS}) SELECT CAST(part AS INT) AS part, row, col, CAST(cnt AS BIGINT) AS cnt FROM c")
def stream_composite_conserved(spark, d):
    """Matrices, gains of slots and open buffers of the live sketch, read from its checkpoint, add up to all updates."""
    work = Workspace(spark, "stream")
    live.run_available(live.live_composite(_arriving(spark, d), T), f"mixedsketch_{uuid.uuid4().hex}", work.path("checkpoint"), "update")
    state, open_ = live.stored_live_state(spark, work.path("checkpoint"))
    return composite.conserved_cells(state, open_, T)


@register("stored_state_conserved", SQL["replay_conserved"])
def stored_state_conserved(spark, d):
    """The same of a replay whose matrices, slots, versions and buffers were stored and read again."""
    work = Workspace(spark, "stored")
    store.save_state(*_replayed(spark, d), work.path("store"), T, 0)
    return composite.conserved_cells(*store.load_state(spark, work.path("store"), T, 0), T)


@register("shuffle_report")
def shuffle_report(spark, d):
    """(method, bytes_per_row): what the hand-over of the token stream writes to shuffles, by method."""
    s = Workspace(spark, "shuffles").save(STREAMS["S7"](spark, d).select("seq", "key", "weight"), "stream")  # the words are cut once, outside of what is measured
    n = max(1, s.count())
    forms = {"cells": cm.build(s, T, "parts"), "ordered_buffers": buffers.replay(s, T), "combined_buffers": buffers.combine(s, T).filter("handed").repartition("owner"), "slots_of_each_update": composite.replay_slots(s, T)}
    return spark.createDataFrame([(name, round(measures.shuffled_bytes(spark, df) / n, 3)) for name, df in forms.items()], "method string, bytes_per_row double")


@register("stream_composite", "SELECT count(*) AS f1, true AS settled FROM events WHERE user_id IS NOT NULL")
def stream_composite(spark, d):
    """The newest snapshots of a live composite sketch: all updates counted, all versions matched."""
    rows = _run_stream(spark, d, lambda e: live.live_composite(e, T), "update")
    newest = composite.latest(rows)
    return newest.agg(F.sum("f1").cast("bigint").alias("f1"), F.every(F.col("v_begin") == F.col("v_end")).alias("settled"))


for _name, (_fn, _sql) in RELATIONAL.items():
    QUERIES[_name] = _fn
    SQL[_name] = _sql
QUERIES.update(WORKLOADS)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """The estimator ladder of two skewed streams beside the truth."""
    return ladder_report(spark, d)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)

