"""Quality scores by positive-unlabelled learning.

Trusted positives are training rows labelled 1; everything else the learner
sees is unlabelled web text.  A small network minimises the non-negative
unbiased risk

    prior * E_P[loss(+)] + max(0, E_U[loss(-)] - prior * E_P[loss(-)])

where the class prior comes from labelled training rows (their smoothed share
of ones) or, if all labels are ones, from the scores of a first classifier.
Label zeros are used for the prior alone, never as negatives.

Features are counts of the text itself: byte classes, shapes of words, how
often words and lines come back.  Ids, language, source and labels are no
inputs.  Fitting uses a bounded sample, chosen by hash and therefore the same
on any cluster; scoring covers every row.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .workspace import ship

SAMPLE_POSITIVE = 12_000
SAMPLE_UNLABELLED = 24_000
HIDDEN = 24
STEPS = 1_500
BATCH = 1_024

#: Bytes that count one by one; other bytes count by class.
_SINGLE = b"\n!#$%&*|.,?-_/:;\"'()<>[]{}@=~+^`\\"
_UPPER, _LOWER, _DIGIT, _BLANK, _LEAD, _TAIL, _REST = range(7)
_CLASS = np.full(256, _REST, dtype=np.int64)
_CLASS[65:91], _CLASS[97:123], _CLASS[48:58] = _UPPER, _LOWER, _DIGIT
_CLASS[list(kernel.WHITE)] = _BLANK
_CLASS[0x80:0xC0], _CLASS[0xC0:] = _TAIL, _LEAD
for _i, _b in enumerate(_SINGLE):
    _CLASS[_b] = 7 + _i
_CLASSES = 7 + len(_SINGLE)
_LETTER = np.isin(_CLASS, [_UPPER, _LOWER, _LEAD, _TAIL])


def _per(owner: np.ndarray, rows: int, weights=None) -> np.ndarray:
    return np.bincount(owner, weights=weights, minlength=rows).astype(np.float64)


def _coming_back(keys: np.ndarray, owner: np.ndarray, rows: int) -> np.ndarray:
    """Per text, how many of its keys it has had before."""
    tagged = np.sort(kernel.mix64(keys ^ kernel.mix64(owner.astype(np.uint64) + np.uint64(1))) & ~np.uint64(0xFFFFF) | owner.astype(np.uint64))
    again = tagged[1:][tagged[1:] == tagged[:-1]]
    return _per((again & np.uint64(0xFFFFF)).astype(np.int64), rows)


def features(texts: pa.Array) -> np.ndarray:
    """One row a text; null counts as empty, and an empty text has zeros throughout."""
    out = []
    for lo, hi in kernel.slices(texts):
        for at in range(lo, hi, 1 << 19):
            out.append(_features(texts.slice(at, min(hi - at, 1 << 19))))
    return np.concatenate(out) if out else np.zeros((0, N_FEATURES))


def _features(texts: pa.Array) -> np.ndarray:
    rows = len(texts)
    buf, offsets = kernel.flatten(texts)
    kind = _CLASS[buf]
    of_byte = np.repeat(np.arange(rows), np.diff(offsets))
    counts = np.bincount(of_byte * _CLASSES + kind, minlength=rows * _CLASSES).reshape(rows, _CLASSES).astype(np.float64)
    counts[:, _BLANK] -= 1  # the blank that flatten() puts after each text
    size = np.maximum(counts.sum(axis=1), 1.0)
    starts, ends, owner = kernel.words(buf, offsets)
    n = _per(owner, rows)
    some = np.maximum(n, 1.0)
    hashes = kernel.word_hashes(buf, starts, ends)
    length = (ends - starts).astype(np.float64)
    letters = np.concatenate(([0], np.cumsum(_LETTER[buf])))
    uppers = np.concatenate(([0], np.cumsum(kind == _UPPER)))
    has = letters[ends] - letters[starts]
    caps = uppers[ends] - uppers[starts]
    mean = _per(owner, rows, length) / some
    same = np.zeros(len(hashes), dtype=bool)
    same[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
    tri, tri_owner = kernel.shingles(hashes, owner, 3, rows)
    odd_end = ~_LETTER[buf[ends - 1]] & (kind[ends - 1] != _CLASS[ord(".")]) & (kind[ends - 1] != _CLASS[ord(",")])
    line = np.where(buf == 10)[0]
    line_cut = np.concatenate(([0], line + 1))
    lines_of = np.maximum(np.searchsorted(offsets, line_cut, side="right") - 1, 0)
    stop = np.minimum(np.append(line, len(buf)), offsets[np.minimum(lines_of + 1, rows)] if rows else 0)
    filled = stop > line_cut
    line_hash = kernel.word_hashes(buf, line_cut[filled], stop[filled]) if len(buf) else np.zeros(0, dtype=np.uint64)
    n_lines = np.maximum(_per(lines_of[filled], rows), 1.0)
    columns = [
        np.sqrt(counts / size[:, None]),
        np.stack(
            [
                mean,
                np.sqrt(np.maximum(_per(owner, rows, length**2) / some - mean**2, 0)),
                _per(owner, rows, caps > 0) / some,
                _per(owner, rows, (caps == has) & (has > 1)) / some,
                _per(owner, rows, has == 0) / some,
                _per(owner, rows, odd_end) / some,
                np.sqrt(_per(owner, rows, same) / some),
                _coming_back(hashes, owner, rows) / some / np.log2(some + 2),
                np.sqrt(_coming_back(tri, tri_owner, rows) / some),
                _coming_back(line_hash, lines_of[filled], rows) / n_lines,
                np.log1p(n),
                np.log1p(n_lines),
                (n == 0).astype(np.float64),
            ],
            axis=1,
        ),
    ]
    return np.concatenate(columns, axis=1)


N_FEATURES = _CLASSES + 13


@dataclass
class Model:
    """Standardisation and a network with one hidden layer."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    prior: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.tanh(z @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.logits(x), -40, 40)))


def fit(positive: np.ndarray, unlabelled: np.ndarray, prior: float, seed: int = 7, steps: int = STEPS) -> Model:
    """Minimise the non-negative risk with the logistic loss by Adam.

    Where the estimated negative part of a batch falls below zero, the step goes
    the other way along that part's gradient, which keeps the risk from being
    driven negative by memorising the positives.
    """
    rng = np.random.default_rng(seed)
    both = np.concatenate([positive, unlabelled])
    mean, scale = both.mean(axis=0), np.maximum(both.std(axis=0), 1e-3)
    w = {"w1": rng.normal(0, 1 / np.sqrt(both.shape[1]), (both.shape[1], HIDDEN)), "b1": np.zeros(HIDDEN), "w2": rng.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN), "b2": np.zeros(1)}
    p, u = (np.clip((x - mean) / scale, -8, 8) for x in (positive, unlabelled))
    first, second = {k: np.zeros_like(v) for k, v in w.items()}, {k: np.zeros_like(v) for k, v in w.items()}
    for t in range(1, steps + 1):
        xp, xu = p[rng.integers(0, len(p), BATCH)], u[rng.integers(0, len(u), BATCH)]
        x = np.concatenate([xp, xu])
        h = np.tanh(x @ w["w1"] + w["b1"])
        g = h @ w["w2"] + w["b2"]
        s = 1 / (1 + np.exp(-np.clip(g, -40, 40)))
        sp, su = s[:BATCH], s[BATCH:]
        negative = np.mean(-np.log1p(-np.minimum(su, 1 - 1e-12))) - prior * np.mean(-np.log1p(-np.minimum(sp, 1 - 1e-12)))
        if negative >= 0:
            d = np.concatenate([prior * (sp - 1) - prior * sp, su]) / BATCH
        else:
            d = np.concatenate([prior * sp, -su]) / BATCH
        dh = np.outer(d, w["w2"]) * (1 - h**2)
        grad = {"w2": h.T @ d + 1e-4 * w["w2"], "b2": np.array([d.sum()]), "w1": x.T @ dh + 1e-4 * w["w1"], "b1": dh.sum(axis=0)}
        rate = 0.01 * min(1.0, 3 * (1 - t / (steps + 1)))
        for k in w:
            first[k] = 0.9 * first[k] + 0.1 * grad[k]
            second[k] = 0.999 * second[k] + 0.001 * grad[k] ** 2
            w[k] = w[k] - rate * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.999**t)) + 1e-8)
    return Model(mean, scale, w["w1"], w["b1"], w["w2"], float(w["b2"][0]), prior)


def estimate_prior(ones: int, zeros: int, positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """Share of positives among unlabelled text.

    Labelled training rows give it directly; without a labelled zero, a first
    classifier of positives against unlabelled text does: the unlabelled mean of
    its score over the mean on positives, at most one.
    """
    if zeros > 0:
        return (ones + 1) / (ones + zeros + 2)
    rough = fit(positive, unlabelled, 0.5, steps=400)
    return float(np.clip(rough.score(unlabelled).mean() / max(rough.score(positive).mean(), 1e-6), 0.05, 0.98))


def held_out(id_col) -> F.Column:
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(3)) == 1


def _feature_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        flat = features(batch.column("text")).astype(np.float32)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([row.tobytes() for row in flat], pa.binary())], names=["doc_id", "x"])


def train(docs: DataFrame, labels: DataFrame, positives: int = SAMPLE_POSITIVE, unlabelled: int = SAMPLE_UNLABELLED) -> Model | None:
    """Fit on at most ``positives`` + ``unlabelled`` texts of the training folds (the bound of the sample).

    ``labels`` has doc_id and quality; conflicting labels of a document count as
    zero, and of rows that share an id one is learnt from.  Without a trusted positive there is no model.
    """
    known = labels.filter("doc_id IS NOT NULL AND quality IS NOT NULL").filter(~held_out("doc_id")).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    ones, zeros = known.agg(F.coalesce(F.sum((F.col("quality") == 1).cast("long")), F.lit(0)), F.coalesce(F.sum((F.col("quality") != 1).cast("long")), F.lit(0))).first()
    order = F.xxhash64("doc_id"), F.col("doc_id")
    trusted = known.filter("quality = 1").select("doc_id").orderBy(*order).limit(positives).withColumn("trusted", F.lit(True))
    open_text = docs.filter("doc_id IS NOT NULL").select("doc_id").filter(~held_out("doc_id")).distinct().orderBy(*order).limit(unlabelled).withColumn("open", F.lit(True))
    chosen = trusted.join(open_text, "doc_id", "full")
    # at most positives + unlabelled ids, and one text of each: rows that share an id count once, with the smallest text
    rows = docs.join(F.broadcast(chosen.select("doc_id")), "doc_id").groupBy("doc_id").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))
    flags = chosen.collect()
    got = rows.select("doc_id", "text").mapInArrow(kernel.tidy(_feature_rows), "doc_id long, x binary").toPandas()
    if not len(got):
        return None
    got = got.assign(x=[bytes(v) for v in got["x"]]).sort_values("doc_id")  # any order of arrival gives one model
    x = np.frombuffer(b"".join(got["x"]), dtype=np.float32).reshape(len(got), N_FEATURES).astype(np.float64)
    ids = got["doc_id"].to_numpy()
    p = x[np.isin(ids, [r["doc_id"] for r in flags if r["trusted"]])]
    u = x[np.isin(ids, [r["doc_id"] for r in flags if r["open"]])]
    if not len(p) or not len(u):
        return None
    return fit(p, u, estimate_prior(ones, zeros, p, u))


def _score_rows(model, untrained: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(model.value.score(features(batch.column("text"))) if model.value else np.full(batch.num_rows, untrained))], names=[*batch.schema.names, "score"])

    return run


def scored(docs: DataFrame, labels: DataFrame, keep: list[str] | None = None, id_col: str = "doc_id", text_col: str = "text", untrained: float = 0.0) -> DataFrame:
    """All rows with their score; ``keep`` names further columns to carry along.

    Null texts score as empty ones; null ids are scored but never learnt from;
    repeated rows are kept; without any trusted positive every score is ``untrained``.
    """
    spark = docs.sparkSession
    ship(spark)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    model = spark.sparkContext.broadcast(train(texts, labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))))
    carried = texts if keep is None else docs.select(*keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in carried.schema.fields)
    return carried.mapInArrow(kernel.tidy(_score_rows(model, untrained)), f"{schema}, score double")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` scored; ``labels`` of the held-out third are never seen."""
    out = scored(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return out.select("doc_id", F.coalesce(held_out("doc_id"), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
