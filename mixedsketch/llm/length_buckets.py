"""Packing by optimal length buckets.

Token counts of all documents form one histogram; dynamic programming over it
places the bucket boundaries that waste the fewest padding tokens, and every
bucket is cut into batches whose padded size stays within a token budget.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernel
from .token_cache import token_cache
from .workspace import Workspace, ship

BUCKETS = 16
TOKEN_BUDGET = 65_536
CHUNK_ROWS, CHUNK_BATCHES = 4096, 16  # a chunk of a bucket has about as many rows, or rows for as many full batches


def optimal_boundaries(lengths: list[int], counts: list[int], buckets: int) -> tuple[list[int], int]:
    """(ascending boundaries, padding): each length is padded to the least boundary that holds it.

    ``lengths`` are distinct.  With k buckets over m lengths the recurrence
    best[j][b] = min over a < b of best[j-1][a] + pad(a, b) has pad(a, b) =
    L_b (C_b - C_a) - (S_b - S_a), a line in L_b for each a, so a monotone hull
    answers each layer in O(m); O(k m) in all.
    """
    order = np.argsort(lengths)
    length = [int(lengths[i]) for i in order]
    count = [int(counts[i]) for i in order]
    m = len(length)
    if m == 0:
        return [], 0
    cum, weight = [0], [0]
    for v, c in zip(length, count, strict=True):
        cum.append(cum[-1] + c)
        weight.append(weight[-1] + c * v)
    best: list[int | None] = [0] + [None] * m
    back: list[list[int]] = []
    for _ in range(min(buckets, m)):
        now: list[int | None] = [0] + [None] * m
        came = [0] * (m + 1)
        hull: list[tuple[int, int, int]] = []  # slope, intercept, a
        at = 0
        for b in range(1, m + 1):
            a = b - 1
            if best[a] is not None:
                line = (-cum[a], best[a] + weight[a], a)
                while len(hull) - at >= 2 and _needless(hull[-2], hull[-1], line):
                    hull.pop()
                hull.append(line)
                at = min(at, len(hull) - 1)
            x = length[b - 1]
            while at + 1 < len(hull) and hull[at + 1][0] * x + hull[at + 1][1] <= hull[at][0] * x + hull[at][1]:
                at += 1
            if hull:
                s, c, a = hull[at]
                now[b] = s * x + c + x * cum[b] - weight[b]
                came[b] = a
        back.append(came)
        best = now
    bounds, b = [], m
    for came in reversed(back):
        if b == 0:
            break
        bounds.append(length[b - 1])
        b = came[b]
    return bounds[::-1], int(best[m])


def _needless(p: tuple, q: tuple, r: tuple) -> bool:
    """Whether line q is nowhere below both p and r (slopes fall from p to r)."""
    return (r[1] - p[1]) * (p[0] - q[0]) <= (q[1] - p[1]) * (p[0] - r[0])


def _lengths(vocabulary: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = token_cache(vocabulary)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("rid"), batch.column("doc_id"), pa.array(cache.counts(batch.column("text")))], names=["rid", "doc_id", "n_tokens"])

    return run


def pack_documents(docs: DataFrame, buckets: int = BUCKETS, token_budget: int = TOKEN_BUDGET, vocabulary: str = "word_bpe_49k.json", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: (doc_id, n_tokens, bucket, bucket_length, batch, slot).

    A batch holds ``max(1, token_budget // bucket_length)`` rows, or fewer at
    the end of a chunk; a text longer than the budget is a batch of its own,
    never cut.  Null and empty texts have no tokens; null and repeated ids keep
    their rows; other columns are ignored; an empty table gives no rows.

    Only the histogram, a row for each distinct length, reaches the driver.
    Rows of a bucket are dealt to chunks of about ``CHUNK_ROWS``, or of sixteen
    full batches where those are more, by the known bucket size, so no task ranks
    a whole bucket.
    """
    spark = docs.sparkSession
    ship(spark)
    work = Workspace(spark, "buckets")
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = work.save(rows.mapInArrow(kernel.tidy(_lengths(vocabulary)), "rid long, doc_id long, n_tokens long"), "lengths")
    hist = rows.groupBy("n_tokens").count().collect()
    lengths, counts = [r[0] for r in hist], [r[1] for r in hist]
    bounds, _ = optimal_boundaries(lengths, counts, buckets)
    held = np.zeros(len(bounds), dtype=np.int64)
    if bounds:
        np.add.at(held, np.searchsorted(bounds, lengths), counts)
    per = [max(1, token_budget // max(1, int(b))) for b in bounds]
    plan = [(i, int(b), per[i], int(-(-held[i] // max(CHUNK_ROWS, CHUNK_BATCHES * per[i])))) for i, b in enumerate(bounds)]
    table = F.array(*[F.struct(F.lit(i).alias("bucket"), F.lit(b).cast("long").alias("len"), F.lit(p).alias("per"), F.lit(c).alias("chunks")) for i, b, p, c in plan]) if plan else None
    if table is None:
        return rows.select("doc_id", "n_tokens", F.lit(0).alias("bucket"), F.lit(0).cast("long").alias("bucket_length"), F.lit("").alias("batch"), F.lit(0).alias("slot"))
    placed = rows.withColumn("b", F.element_at(F.filter(table, lambda x: x["len"] >= F.col("n_tokens")), 1))
    placed = placed.select("rid", "doc_id", "n_tokens", "b.*").withColumn("chunk", F.pmod(F.xxhash64("rid"), F.col("chunks")).cast("int"))
    rank = F.row_number().over(Window.partitionBy("bucket", "chunk").orderBy("rid")) - 1
    out = placed.withColumn("rank", rank).withColumn("batch", F.format_string("%d-%d-%d", "bucket", "chunk", F.floor(F.col("rank") / F.col("per"))))
    return out.select("doc_id", "n_tokens", "bucket", F.col("len").alias("bucket_length"), "batch", F.pmod("rank", "per").cast("int").alias("slot"))


def op2_length_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` in sixteen buckets and batches of 65,536 padded tokens."""
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
