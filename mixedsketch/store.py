"""Sketches kept as tables: one folder a batch, under the spec they were built with."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import buffers, cm, composite
from .spec import SketchSpec


def save(cells: DataFrame, root: str, spec: SketchSpec, batch_id: int) -> None:
    """Write one batch's cells (with more columns, such as a pane's start, as they come); writing it again replaces it, so a retried batch counts once."""
    path = f"{root}/spec={spec.key}/batch_id={batch_id}"
    cells.repartition("part").sortWithinPartitions("part", "row", "col").write.mode("overwrite").parquet(path)


def load(spark: SparkSession, root: str, spec: SketchSpec, since: int | None = None, until: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Cells of all stored batches (or batches since..until), added up.

    Only folders of this spec are read, so sketches of different specs never
    mix; the batch filter prunes folders.
    """
    df = spark.read.option("basePath", f"{root}/spec={spec.key}").parquet(f"{root}/spec={spec.key}")
    if since is not None:
        df = df.filter(F.col("batch_id") >= since)
    if until is not None:
        df = df.filter(F.col("batch_id") <= until)
    if by:
        return df.groupBy(*by, "part", "row", "col").agg(F.sum("cnt").alias("cnt"))
    return cm.merge(df.select("part", "row", "col", "cnt"))


def save_state(state: DataFrame, handoffs: DataFrame, root: str, spec: SketchSpec, batch_id: int) -> None:
    """Write the owners' matrices, slots, partial sums and versions, and what is still in buffers, as of one batch."""
    state.write.mode("overwrite").parquet(f"{root}/states/spec={spec.key}/batch_id={batch_id}")
    handoffs.filter("NOT handed").repartition("owner").write.mode("overwrite").parquet(f"{root}/buffers/spec={spec.key}/batch_id={batch_id}")


def load_state(spark: SparkSession, root: str, spec: SketchSpec, batch_id: int) -> tuple[DataFrame, DataFrame]:
    """(state, buffered rows) as ``save_state`` wrote them; rows whose two versions differ are of a scan that was cut off and refused."""
    state = spark.read.schema(composite.STATE).parquet(f"{root}/states/spec={spec.key}/batch_id={batch_id}")
    if not state.filter("v_begin <> v_end").isEmpty():
        raise ValueError(f"batch {batch_id} has parts that were being written")
    return state, spark.read.schema(buffers.HANDOFF).parquet(f"{root}/buffers/spec={spec.key}/batch_id={batch_id}")


def merge_checked(a: tuple[SketchSpec, DataFrame], b: tuple[SketchSpec, DataFrame]) -> DataFrame:
    """Merge two sketches, or refuse if their specs differ."""
    if a[0].key != b[0].key:
        raise ValueError(f"specs differ: {a[0].key}, {b[0].key}")
    return cm.merge(a[1], b[1])


def read_state(spark: SparkSession, checkpoint: str, variable: str | None = None) -> DataFrame:
    """The state table of a stateful stream, by its checkpoint folder; ``variable`` for operators with several."""
    reader = spark.read.format("statestore")
    return (reader.option("stateVarName", variable) if variable else reader).load(checkpoint)
