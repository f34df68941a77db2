"""The corpus pipeline: five stages over ``documents``, each on all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mixedsketch.llm.jaccard_join import jaccard_components
from mixedsketch.llm.length_buckets import pack_documents
from mixedsketch.llm.pii_pseudonyms import pseudonymise, session_key
from mixedsketch.llm.positional_index import contamination
from mixedsketch.llm.quality_classifier import scored
from mixedsketch.llm.workspace import Workspace

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
BROADCAST_IDS = 1_000_000


def numbered(docs: DataFrame, work: Workspace) -> DataFrame:
    """``docs`` with a number ``row`` for each row: the id where all ids differ, else one that is written with the rows."""
    docs = docs.select(*COLUMNS)
    if docs.groupBy("doc_id").count().filter("count > 1 OR doc_id IS NULL").isEmpty():
        return docs.withColumn("row", F.col("doc_id"))
    return work.save(docs.withColumn("row", F.monotonically_increasing_id()), "rows")


def without(docs: DataFrame, rows: DataFrame, work: Workspace) -> DataFrame:
    """Documents whose ``row`` is not among ``rows``; few of them are broadcast, many meet the documents in a shuffle."""
    rows = work.save(rows.select("row").distinct(), "dropped")
    few = rows.count() <= BROADCAST_IDS
    return docs.join(F.broadcast(rows) if few else rows, "row", "left_anti").select(*COLUMNS)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the positive-unlabelled classifier scores 0.5 or more; all of them where no model can be fitted."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return scored(docs, labels, keep=COLUMNS, untrained=1.0).filter("score >= 0.5").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of five-word shingle sets at Jaccard 0.8: the one with the smallest id.

    Where rows share an id or have none, each row is a document: of a component
    the row with an id before one without, then the smallest id, then the
    smallest hash of the text stays.  Texts without words link nothing; rows of
    one id that have no words are one document.
    """
    work = Workspace(spark, "near-duplicates")
    rows = numbered(docs, work)
    found = work.save(jaccard_components(rows, "row", size=5, percent=80).withColumnRenamed("doc_id", "row"), "components")
    facts = rows.select("row", "doc_id", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("hash"))
    same_id = (F.col("n_shingles") == 0) & F.col("doc_id").isNotNull()
    found = found.join(facts, "row").select("row", same_id.alias("bare"), F.when(same_id, F.col("doc_id")).otherwise(F.col("component_id")).alias("part"), F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "hash", "row").alias("rank"))
    kept = found.groupBy("bare", "part").agg(F.min("rank")["row"].alias("row"))
    return without(rows, found.join(kept, "row", "left_anti"), work)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a ten-word window of a benchmark item; rows are judged one by one, whatever their ids."""
    work = Workspace(spark, "decontamination")
    rows = numbered(docs, work)
    hit = contamination(rows, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), "row").filter("contaminated")
    return without(rows, hit.withColumnRenamed("doc_id", "row"), work)


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced by pseudonyms of the same format."""
    return pseudonymise(docs.select(*COLUMNS), session_key(spark)).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bucket, batch and slot of every document."""
    return pack_documents(docs)


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("pii", pii), ("packing", packing)]

#: A learnt classifier has no SQL; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply all stages to ``documents``; what each returns is written and read again."""
    work = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = work.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
