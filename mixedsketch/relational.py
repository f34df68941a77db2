"""Relational operators around the sketches, each with its DuckDB twin.

They prepare streams, join estimates with truth, and summarise; all are plain
DataFrame plans that Spark is free to broadcast or shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources.streams import load

RELATIONAL: dict[str, tuple] = {}


def register(name: str, sql: str):
    def put(f):
        RELATIONAL[name] = (f, sql)
        return f

    return put


@register("scalar_strings", "SELECT event_id, upper(event_type) AS up, substr(event_type, 1, 2) AS head, length(event_type) AS n, md5(event_type) AS digest, concat_ws(':', event_type, user_id) AS pair, event_type LIKE 'c%' AS c, regexp_matches(event_type, '^[a-m]') AS early FROM events")
def scalar_strings(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events", ["event_id", "event_type", "user_id"])
    t = F.col("event_type")
    return e.select("event_id", F.upper(t).alias("up"), F.substring(t, 1, 2).alias("head"), F.length(t).cast("bigint").alias("n"), F.md5(t).alias("digest"), F.concat_ws(":", t, F.col("user_id").cast("string")).alias("pair"), t.like("c%").alias("c"), t.rlike("^[a-m]").alias("early"))


@register("scalar_dates", "SELECT event_id, CAST(CAST(ts AS DATE) AS VARCHAR) AS day, CAST(year(ts) AS INT) AS y, CAST(month(ts) AS INT) AS m, CAST(date_trunc('hour', ts) AS VARCHAR) AS hour, CAST(date_diff('day', DATE '2020-01-01', CAST(ts AS DATE)) AS INT) AS age, epoch_us(ts) AS us FROM events")
def scalar_dates(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events", ["event_id", "ts"])
    us = F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts")) if hasattr(F, "timestamp_diff") else F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")
    return e.select("event_id", F.to_date("ts").cast("string").alias("day"), F.year("ts").alias("y"), F.month("ts").alias("m"), F.date_trunc("hour", F.col("ts")).cast("string").alias("hour"), F.datediff(F.to_date("ts"), F.lit("2020-01-01").cast("date")).alias("age"), us.cast("bigint").alias("us"))


@register("scalar_math", "SELECT event_id, abs(value - 50) AS a, CAST(floor(value) AS BIGINT) AS lo, CAST(ceil(value) AS BIGINT) AS hi, round(ln(value + 1), 6) AS l, round(sqrt(value), 6) AS r, user_id % 7 AS md, greatest(value, 10) AS g, CASE WHEN value BETWEEN 10 AND 20 THEN 'mid' WHEN value IN (0, 1) THEN 'end' ELSE coalesce(nullif(event_type, 'view'), 'none') END AS kind FROM events")
def scalar_math(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events", ["event_id", "value", "user_id", "event_type"])
    v = F.col("value")
    kind = F.when(v.between(10, 20), "mid").when(v.isin(0, 1), "end").otherwise(F.coalesce(F.nullif("event_type", F.lit("view")), F.lit("none")))
    return e.select("event_id", F.abs(v - 50).alias("a"), F.floor(v).alias("lo"), F.ceil(v).alias("hi"), F.round(F.ln(v + 1), 6).alias("l"), F.round(F.sqrt(v), 6).alias("r"), F.pmod("user_id", F.lit(7)).cast("bigint").alias("md"), F.greatest(v, F.lit(10.0)).alias("g"), kind.alias("kind"))


@register("scalar_json", "SELECT k, count(*) AS n FROM (SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events) GROUP BY k")
def scalar_json(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events", ["props"])
    return e.select(F.from_json("props", "k INT").alias("j")).groupBy("j.k").agg(F.count("*").alias("n"))


@register("scalar_arrays", "SELECT doc_id, len(w) AS n, array_to_string(list_sort(list_transform(w[1:5], lambda x: length(x))), ',') AS lens, list_contains(w, 'the') AS has_the, len(list_filter(w, lambda x: length(x) > 6)) AS longs FROM (SELECT doc_id, string_split(lang || ' ' || source || ' the end', ' ') AS w FROM documents)")
def scalar_arrays(spark: SparkSession, d: str) -> DataFrame:
    w = load(spark, d, "documents", ["doc_id", "lang", "source"]).select("doc_id", F.split(F.concat_ws(" ", "lang", "source", F.lit("the end")), " ").alias("w"))
    return w.select("doc_id", F.size("w").cast("bigint").alias("n"), F.array_join(F.transform(F.array_sort(F.transform(F.slice("w", 1, 5), F.length)), lambda n: n.cast("string")), ",").alias("lens"), F.array_contains("w", "the").alias("has_the"), F.size(F.filter("w", lambda x: F.length(x) > 6)).cast("bigint").alias("longs"))


@register("join_inner", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def join_inner(spark: SparkSession, d: str) -> DataFrame:
    o, c = load(spark, d, "orders", ["o_custkey"]), load(spark, d, "customer", ["c_custkey", "c_mktsegment"])
    return o.groupBy("o_custkey").count().join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.sum("count").cast("bigint").alias("n"))


@register("join_semi_anti", "SELECT 'ordered' AS kind, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) UNION ALL SELECT 'never', count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def join_semi_anti(spark: SparkSession, d: str) -> DataFrame:
    c, o = load(spark, d, "customer", ["c_custkey"]), load(spark, d, "orders", ["o_custkey"]).withColumnRenamed("o_custkey", "c_custkey")
    rows = [c.join(o, "c_custkey", how).agg(F.count("*").alias("n")).select(F.lit(name).alias("kind"), "n") for name, how in (("ordered", "left_semi"), ("never", "left_anti"))]
    return rows[0].unionByName(rows[1])


@register("join_full", "SELECT coalesce(a.user_id, b.o_custkey) AS key, coalesce(a.n, 0) AS events, coalesce(b.n, 0) AS orders FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1) a FULL JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) b ON a.user_id = b.o_custkey")
def join_full(spark: SparkSession, d: str) -> DataFrame:
    a = load(spark, d, "events", ["user_id"]).groupBy(F.col("user_id").alias("key")).agg(F.count("*").alias("events"))
    b = load(spark, d, "orders", ["o_custkey"]).groupBy(F.col("o_custkey").alias("key")).agg(F.count("*").alias("orders"))
    return a.join(b, "key", "full").select("key", F.coalesce("events", F.lit(0)).alias("events"), F.coalesce("orders", F.lit(0)).alias("orders"))


@register("join_asof", "SELECT e.event_id, p.event_id AS snapshot FROM events e ASOF JOIN (SELECT event_id, user_id, ts FROM events WHERE event_id % 10 = 0) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof(spark: SparkSession, d: str) -> DataFrame:
    """The newest snapshot of a key at or before each row: one pass over both sides in time order, per key and day with the last of earlier days carried in."""
    e = load(spark, d, "events", ["event_id", "user_id", "ts"])
    snap = e.filter("event_id % 10 = 0").select("user_id", "ts", F.lit(0).alias("side"), F.col("event_id").alias("snapshot"), F.lit(None).cast("bigint").alias("event_id"))
    both = e.select("user_id", "ts", F.lit(1).alias("side"), F.lit(None).cast("bigint").alias("snapshot"), "event_id").unionByName(snap).withColumn("day", F.to_date("ts"))
    last = both.filter("side = 0").groupBy("user_id", "day").agg(F.max_by("snapshot", F.struct("ts", "snapshot")).alias("of_day"))
    days = both.select("user_id", "day").distinct().join(last, ["user_id", "day"], "left")
    carried = days.select("user_id", "day", F.last("of_day", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("day").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    order = Window.partitionBy("user_id", "day").orderBy("ts", "side", "snapshot")
    found = both.withColumn("now", F.last("snapshot", ignorenulls=True).over(order)).filter("side = 1").join(carried, ["user_id", "day"])
    return found.select("event_id", F.coalesce("now", "before").alias("snapshot")).filter("snapshot IS NOT NULL")


@register("join_interval_whole", "WITH m AS (SELECT coalesce(max(event_id), 0) // 20 + 1 AS w FROM events) SELECT i.range AS slot, count(*) AS n FROM range(20) i JOIN m ON true JOIN events ON event_id BETWEEN i.range * w AND i.range * w + w * 3 // 2 GROUP BY i.range")
def join_interval_whole(spark: SparkSession, d: str) -> DataFrame:
    """Rows inside twenty overlapping intervals that cover every event number: intervals are cut into blocks, so rows meet candidates by equality."""
    e = load(spark, d, "events", ["event_id"])
    w = (e.agg(F.max("event_id")).first()[0] or 0) // 20 + 1
    slots = spark.range(20).select(F.col("id").alias("slot"), (F.col("id") * w).alias("lo"), (F.col("id") * w + w * 3 // 2).alias("hi"))
    blocks = slots.withColumn("block", F.explode(F.sequence(F.floor(F.col("lo") / w), F.floor(F.col("hi") / w))))
    return e.withColumn("block", F.floor(F.col("event_id") / w)).join(F.broadcast(blocks), "block").filter("event_id BETWEEN lo AND hi").groupBy("slot").agg(F.count("*").alias("n"))


@register("join_brand_f2", "SELECT p_brand, CAST(sum(f * f) AS BIGINT) AS f2 FROM (SELECT l_partkey, count(*) AS f FROM lineitem GROUP BY 1) JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def join_brand_f2(spark: SparkSession, d: str) -> DataFrame:
    f = load(spark, d, "lineitem", ["l_partkey"]).groupBy("l_partkey").agg(F.count("*").alias("f"))
    p = load(spark, d, "part", ["p_partkey", "p_brand"])
    return f.join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.sum(F.col("f") * F.col("f")).cast("bigint").alias("f2"))


@register("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem", ["l_returnflag", "l_linestatus"]).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@register("agg_rollup", "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ROLLUP (c_nationkey, c_mktsegment)")
def agg_rollup(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "customer", ["c_nationkey", "c_mktsegment"]).rollup("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


@register("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    flag, status = F.col("l_returnflag"), F.col("l_linestatus")
    return load(spark, d, "lineitem", ["l_returnflag", "l_linestatus"]).groupingSets([[flag], [status], []], flag, status).agg(F.count("*").alias("n")).select("l_returnflag", "l_linestatus", "n")


@register("agg_conditional", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS big, count(DISTINCT user_id) AS users, arg_max(event_id, value * 1000000 + event_id) AS top, round(median(value), 6) AS med, round(stddev_samp(value), 6) AS sd FROM events GROUP BY event_type")
def agg_conditional(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events", ["event_id", "event_type", "user_id", "value"])
    return e.groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("big"), F.count_distinct("user_id").alias("users"), F.max_by("event_id", F.col("value") * 1000000 + F.col("event_id")).alias("top"), F.round(F.median("value"), 6).alias("med"), F.round(F.stddev_samp("value"), 6).alias("sd"))


@register("agg_day_skew", "SELECT CAST(day AS VARCHAR) AS day, CAST(sum(f) AS BIGINT) AS f1, CAST(sum(f * f) AS BIGINT) AS f2, round(sum(f * f)::DOUBLE / (sum(f) * sum(f)), 9) AS alarm FROM (SELECT CAST(ts AS DATE) AS day, user_id, count(*) AS f FROM events GROUP BY ALL) GROUP BY day")
def agg_day_skew(spark: SparkSession, d: str) -> DataFrame:
    f = load(spark, d, "events", ["ts", "user_id"]).groupBy(F.to_date("ts").cast("string").alias("day"), "user_id").agg(F.count("*").alias("f"))
    out = f.groupBy("day").agg(F.sum("f").cast("bigint").alias("f1"), F.sum(F.col("f") * F.col("f")).cast("bigint").alias("f2"))
    return out.withColumn("alarm", F.round(F.col("f2").cast("double") / (F.col("f1") * F.col("f1")), 9))


@register("win_ranks", "SELECT user_id, n, CAST(rank() OVER w AS INT) AS r, CAST(dense_rank() OVER w AS INT) AS dr, CAST(ntile(4) OVER (ORDER BY n DESC, user_id) AS INT) AS q FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1) WINDOW w AS (ORDER BY n DESC)")
def win_ranks(spark: SparkSession, d: str) -> DataFrame:
    n = load(spark, d, "events", ["user_id"]).groupBy("user_id").agg(F.count("*").alias("n"))
    w = Window.orderBy(F.desc("n"))  # a row a user, after aggregation
    return n.select("user_id", "n", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.orderBy(F.desc("n"), "user_id")).alias("q"))


@register("win_frames", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS seen, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS near FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_frames(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = load(spark, d, "events", ["event_id", "user_id"])
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("seen"), F.count("*").over(w.rangeBetween(-1000, 0)).alias("near"))


@register("set_ops", "SELECT 'both' AS kind, count(*) AS n FROM (SELECT user_id FROM events INTERSECT SELECT o_custkey FROM orders) UNION ALL SELECT 'events only', count(*) FROM (SELECT user_id FROM events EXCEPT SELECT o_custkey FROM orders) UNION ALL SELECT 'either', count(*) FROM (SELECT user_id FROM events UNION SELECT o_custkey FROM orders) UNION ALL SELECT 'except all', count(*) FROM (SELECT o_custkey FROM orders EXCEPT ALL SELECT user_id FROM events)")
def set_ops(spark: SparkSession, d: str) -> DataFrame:
    a = load(spark, d, "events", ["user_id"]).toDF("k")
    b = load(spark, d, "orders", ["o_custkey"]).toDF("k")
    rows = {"both": a.intersect(b), "events only": a.subtract(b), "either": a.union(b).distinct(), "except all": b.exceptAll(a)}
    out = None
    for name, df in rows.items():
        row = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("kind"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@register("topk_global", "SELECT l_partkey AS key, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, key LIMIT 20")
def topk_global(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem", ["l_partkey"]).groupBy(F.col("l_partkey").alias("key")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "key").limit(20)


@register("topk_group", "SELECT event_type, user_id, n FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY n DESC, user_id) AS r FROM (SELECT event_type, user_id, count(*) AS n FROM events GROUP BY ALL)) WHERE r <= 5")
def topk_group(spark: SparkSession, d: str) -> DataFrame:
    n = load(spark, d, "events", ["event_type", "user_id"]).groupBy("event_type", "user_id").agg(F.count("*").alias("n"))
    r = F.row_number().over(Window.partitionBy("event_type").orderBy(F.desc("n"), "user_id"))
    return n.withColumn("r", r).filter("r <= 5").drop("r")
