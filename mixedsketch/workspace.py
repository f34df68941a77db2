"""Intermediate tables in the folder that all executors share.

Cutting lineage by a written table survives the loss of any executor: what is
read back lies in ``spark.checkpoint.dir``, never in a machine's own folder.
"""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; a folder of our own is set only where none is and all runs on one machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="mixedsketch-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


#: Rows in a batch between the JVM and Python.  A row may be a long text, and both sides hold batches outside
#: any limit that Spark watches, so the default of 10,000 is lowered; another setting of the user's is left alone.
BATCH_ROWS = "1000"


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once a context, so that they need no path of the driver's, and keep batches small."""
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    sc = spark.sparkContext
    if getattr(sc, "_mixedsketch_sent", False):
        return
    top = os.path.dirname(os.path.abspath(__file__))
    blob = io.BytesIO()
    with zipfile.ZipFile(blob, "w") as z:
        for folder, _, names in os.walk(top):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(top)))
    path = os.path.join(tempfile.mkdtemp(prefix="mixedsketch-zip-"), "mixedsketch_code.zip")  # stays: Spark serves it
    with open(path, "wb") as f:
        f.write(blob.getvalue())
    sc.addPyFile(path)
    sc._mixedsketch_sent = True


class Workspace:
    """Written tables of one query run, under one fresh folder."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.folder = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"

    def save(self, df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
        """Write ``df`` and return it read back."""
        writer = df.write.mode("overwrite")
        if partition_by:
            writer = writer.partitionBy(*partition_by)
        writer.parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def path(self, name: str) -> str:
        return f"{self.folder}/{name}"

    def drop(self, *names: str) -> None:
        """Delete tables that nothing reads any more (all of them, without names)."""
        jvm = self.spark.sparkContext._jvm
        conf = self.spark.sparkContext._jsc.hadoopConfiguration()
        for name in names or ("",):
            path = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}".rstrip("/"))
            path.getFileSystem(conf).delete(path, True)
