"""Order-dependent loops as compiled classes on the executors.

A lane or an owner is one sequential writer, so what a row costs is what the
whole stream costs.  ``Kernels.java`` is compiled once a context by the compiler
that Spark brings for its own generated code, and sent to the executors as a jar.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from importlib.resources import files

from pyspark.sql import DataFrame


def kernels(spark):
    """The object that makes the functions; compiled and sent at the first call of a context."""
    sc = spark.sparkContext
    made = getattr(sc, "_mixedsketch_kernels", None)
    if made is None:
        compiler = sc._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(sc._jvm.java.lang.Thread.currentThread().getContextClassLoader())
        compiler.cook(files(__package__).joinpath("Kernels.java").read_text())
        path = os.path.join(tempfile.mkdtemp(prefix="mixedsketch-jar-"), "mixedsketch_kernels.jar")  # stays: Spark serves it
        with zipfile.ZipFile(path, "w") as z:
            for entry in compiler.getBytecodes().items():
                z.writestr(entry[0].replace(".", "/") + ".class", bytes(entry[1]))
        sc._jsc.sc().addJar(path)
        made = sc._mixedsketch_kernels = compiler.getClassLoader().loadClass("mixedsketch.Kernels").getDeclaredConstructor(sc._gateway.new_array(sc._jvm.java.lang.Class, 0)).newInstance(sc._gateway.new_array(sc._jvm.java.lang.Object, 0))
    return made


def map_partitions(df: DataFrame, function, schema: str) -> DataFrame:
    """``df`` through a function of ``kernels``, partition by partition, as rows of ``schema``."""
    jvm = df.sparkSession.sparkContext._jvm
    encoder = jvm.org.apache.spark.sql.Encoders.row(jvm.org.apache.spark.sql.types.StructType.fromDDL(schema))
    return DataFrame(df._jdf.mapPartitions(function, encoder), df.sparkSession)
