"""Connected components of a link table, by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workspace import Workspace


def _toward_smallest(edges: DataFrame, work: Workspace, name: str) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    big = both.join(least, "u").filter("v > u AND v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
    big = work.save(big, f"{name}-big")
    low = big.groupBy("u").agg(F.min("v").alias("m"))
    hung = big.join(low, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return work.save(hung.union(low.select("u", F.col("m").alias("v"))).distinct(), f"{name}-small")


def components(edges: DataFrame, work: Workspace, name: str = "components", rounds: int = 60) -> DataFrame:
    """(node, component) for every node of ``edges(u, v)``; component is its smallest node.

    Each round joins every node's neighbours to the smallest of them and then
    keeps one downward link per node; link tables are written, so a lost
    executor costs one round at most.  Null ends, self links and repeated links
    are harmless.  Nothing but a count and a checksum reaches the driver.
    """
    now = edges.filter("u IS NOT NULL AND v IS NOT NULL AND u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now = work.save(now, f"{name}-0")
    seen = None
    for i in range(rounds):
        mark = now.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if mark == seen or mark[0] == 0:
            break
        seen = mark
        now = _toward_smallest(now, work, f"{name}-{i + 1}")
        work.drop(f"{name}-{i + 1}-big", f"{name}-{i}-small" if i else f"{name}-0")
    else:
        raise RuntimeError("star contraction did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
