"""Streams of (seq, key, weight) from the given tables, and readers for other formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import canon_key, check_key_type

#: Declared schemas of the tables that streams are made of.
SCHEMAS = {
    "events": "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP_NTZ",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP_NTZ, o_orderpriority STRING",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "part": "p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "pages": "page_id BIGINT, url STRING, html STRING",
}


def load(spark: SparkSession, folder: str, table: str, columns: list[str] | None = None) -> DataFrame:
    """A table by its declared schema (by its own where none is declared), cut to ``columns``."""
    reader = spark.read.schema(SCHEMAS[table]) if table in SCHEMAS else spark.read
    df = reader.parquet(f"{folder}/{table}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet with a declared schema."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write(df: DataFrame, path: str, fmt: str, mode: str = "errorifexists", partition_by: list[str] | None = None, **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def stream(spark: SparkSession, folder: str, table: str, max_files: int = 1) -> DataFrame:
    """A streaming read of a folder of Parquet files, in the order the files were written."""
    return spark.readStream.schema(SCHEMAS[table]).option("maxFilesPerTrigger", max_files).parquet(folder)


def normalise(df: DataFrame, key: Column, weight: Column | None = None, seq: Column | None = None, on_bad_weight: str = "fail", family: str = "md5") -> DataFrame:
    """(seq, key, weight, k): key folded, k its original as text.

    Null keys are dropped.  Null, zero or negative weights raise at run time, or
    are dropped with ``on_bad_weight="drop"``.  Without ``seq`` the stream has
    no order and only order-free methods apply (seq is null).
    """
    if on_bad_weight not in ("fail", "drop"):
        raise ValueError("on_bad_weight is fail or drop")
    check_key_type(df.select(key.alias("k")).schema["k"].dataType)
    weight = F.lit(1).cast("bigint") if weight is None else weight.cast("bigint")
    out = df.select((F.lit(None) if seq is None else seq).cast("bigint").alias("seq"), key.cast("string").alias("k"), weight.alias("weight")).filter("k IS NOT NULL")
    good = F.col("weight").isNotNull() & (F.col("weight") > 0)
    if on_bad_weight == "drop":
        out = out.filter(good)
    elif weight is not None:
        out = out.withColumn("weight", F.when(good, F.col("weight")).otherwise(F.raise_error(F.lit("weights must be positive")).cast("bigint")))
    return out.select("seq", canon_key(F.col("k"), family).alias("key"), "weight", "k")


# --- the streams of the workloads


def s1_users(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "events", ["event_id", "user_id"]), F.col("user_id"), seq=F.col("event_id"))


def s2_types(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "events", ["event_id", "event_type"]), F.col("event_type"), seq=F.col("event_id"))


def s3_parts(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "lineitem", ["l_partkey"]), F.col("l_partkey"))


def s4_weighted(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "lineitem", ["l_partkey", "l_quantity"]), F.col("l_partkey"), F.col("l_quantity"))


def s5_suppliers(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "lineitem", ["l_suppkey"]), F.col("l_suppkey"))


def s6_customers(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "orders", ["o_orderkey", "o_custkey"]), F.col("o_custkey"))


def s7_tokens(spark: SparkSession, d: str) -> DataFrame:
    docs = load(spark, d, "documents", ["doc_id", "text"])
    cores = spark.sparkContext.defaultParallelism
    if docs.rdd.getNumPartitions() < cores:  # few row groups of long texts: words are cut and folded by all cores
        docs = docs.repartition(cores, F.xxhash64("doc_id", "text"))
    words = docs.select("doc_id", F.posexplode(F.split(F.lower("text"), "[^a-z0-9]+")).alias("pos", "word"))
    return normalise(words.filter("word <> ''"), F.col("word"), seq=F.col("doc_id") * (1 << 24) + F.col("pos"))


ZIPF_DOMAIN = 1000


def zipf_thresholds(z: float, n: int = ZIPF_DOMAIN) -> list[int]:
    """Cumulative thresholds below 2^28 of the ranks 1..n."""
    mass = [q**-z for q in range(1, n + 1)]
    total, acc, out = sum(mass), 0.0, []
    for m in mass:
        acc += m
        out.append(int(2**28 * acc / total))
    out[-1] = 2**28
    return out


def s8_zipf(spark: SparkSession, d: str, z: float = 1.5, salt: str | None = None, rows: int | None = None, n: int = ZIPF_DOMAIN) -> DataFrame:
    """A Zipf(z) stream by range join of a hashed sequence with the thresholds, of ``rows`` or as many as lineitem has.

    Buckets of the hash value make the range join an equi join; the threshold
    table has n rows, whatever the length of the stream.
    """
    rows = load(spark, d, "lineitem", ["l_partkey"]).count() if rows is None else rows
    cuts = zipf_thresholds(z, n)
    lo = [0, *cuts[:-1]]
    shift = 18
    table = [(r + 1, a, b, bucket) for r, (a, b) in enumerate(zip(lo, cuts, strict=True)) if b > a for bucket in range(a >> shift, ((b - 1) >> shift) + 1)]
    ranks = spark.createDataFrame(table, "rank int, lo bigint, hi bigint, bucket bigint").withColumn("k", F.col("rank").cast("string"))
    ranks = ranks.withColumn("key", canon_key(F.col("k")))  # folded once a rank, not once a row
    text = F.col("seq").cast("string") if salt is None else F.concat(F.lit(f"{salt}:"), F.col("seq").cast("string"))
    u = spark.range(rows).select(F.col("id").alias("seq")).withColumn("u", F.conv(F.substring(F.md5(text), 1, 7), 16, 10).cast("bigint"))
    hit = u.withColumn("bucket", F.shiftright("u", shift)).join(F.broadcast(ranks), "bucket").filter("u >= lo AND u < hi")
    return hit.select("seq", "key", F.lit(1).cast("bigint").alias("weight"), "k")


def s9_hosts(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "pages", ["page_id", "url"]), F.regexp_extract("url", "://([^/?#]*)", 1), seq=F.col("page_id"))


def s10_pairs(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "lineitem", ["l_partkey", "l_suppkey"]), F.concat_ws(":", "l_partkey", "l_suppkey"))


def s11_dates(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "lineitem", ["l_shipdate"]), F.to_date("l_shipdate"))


def s12_langs(spark: SparkSession, d: str) -> DataFrame:
    return normalise(load(spark, d, "documents", ["doc_id", "lang"]), F.col("lang"), seq=F.col("doc_id"))


STREAMS = {"S1": s1_users, "S2": s2_types, "S3": s3_parts, "S4": s4_weighted, "S5": s5_suppliers, "S6": s6_customers, "S7": s7_tokens, "S8": s8_zipf, "S9": s9_hosts, "S10": s10_pairs, "S11": s11_dates, "S12": s12_langs}


def sql_stream(name: str, z: float = 1.5) -> str:
    """The DuckDB twin of a stream: (seq, k, weight)."""
    simple = {
        "S1": "SELECT event_id AS seq, CAST(user_id AS VARCHAR) AS k, 1::BIGINT AS weight FROM events",
        "S2": "SELECT event_id AS seq, event_type AS k, 1::BIGINT AS weight FROM events",
        "S3": "SELECT NULL::BIGINT AS seq, CAST(l_partkey AS VARCHAR) AS k, 1::BIGINT AS weight FROM lineitem",
        "S4": "SELECT NULL::BIGINT AS seq, CAST(l_partkey AS VARCHAR) AS k, CAST(l_quantity AS BIGINT) AS weight FROM lineitem",
        "S5": "SELECT NULL::BIGINT AS seq, CAST(l_suppkey AS VARCHAR) AS k, 1::BIGINT AS weight FROM lineitem",
        "S6": "SELECT NULL::BIGINT AS seq, CAST(o_custkey AS VARCHAR) AS k, 1::BIGINT AS weight FROM orders",
        "S7": "SELECT doc_id * 16777216 + pos - 1 AS seq, w[pos] AS k, 1::BIGINT AS weight FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS pos FROM (SELECT doc_id, string_split_regex(lower(text), '[^a-z0-9]+') AS w FROM documents)) WHERE w[pos] <> ''",
        "S9": "SELECT page_id AS seq, regexp_extract(url, '://([^/?#]*)', 1) AS k, 1::BIGINT AS weight FROM pages",
        "S10": "SELECT NULL::BIGINT AS seq, CAST(l_partkey AS VARCHAR) || ':' || CAST(l_suppkey AS VARCHAR) AS k, 1::BIGINT AS weight FROM lineitem",
        "S11": "SELECT NULL::BIGINT AS seq, CAST(CAST(l_shipdate AS DATE) AS VARCHAR) AS k, 1::BIGINT AS weight FROM lineitem",
        "S12": "SELECT doc_id AS seq, lang AS k, 1::BIGINT AS weight FROM documents",
    }
    if name != "S8":
        return simple[name]
    cuts = zipf_thresholds(z)
    return f"""SELECT seq, CAST(rank AS VARCHAR) AS k, 1::BIGINT AS weight
      FROM (SELECT range AS seq, ('0x' || substr(md5(CAST(range AS VARCHAR)), 1, 7))::BIGINT AS u FROM (SELECT unnest(range((SELECT count(*) FROM lineitem)::BIGINT)) AS range))
      JOIN (SELECT i AS rank, CASE WHEN i = 1 THEN 0 ELSE c[i - 1] END AS lo, c[i] AS hi FROM (SELECT {cuts} AS c), range(1, {len(cuts) + 1}) t(i)) ON u >= lo AND u < hi"""
