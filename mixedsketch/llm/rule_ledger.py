"""Quality rules as a ledger of failure bits.

Every rule is evaluated once per document; the ledger keeps the measurements
and one failure bit a rule.  A policy is a version and a set of rules, so
applying one, comparing versions, or asking what a rule alone rejects are
bitwise operations on the ledger and never touch a text again.  The ledger of a
table is written once for a version of the rules, and found again by both.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .workspace import Workspace, shared_folder, ship

WINDOW = 8
#: Characters that count as symbols.
SYMBOLS = b"#*$%&|<>"

MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_adjacent"]

#: Rule bits by place; a rule fails a document when its condition holds.  New rules go to the end.
RULES = {
    "few_words": "n_words < 20",
    "repeated_windows": "100 * n_repeat_words > 30 * n_words",
    "symbols": "100 * n_symbols > 20 * n_words",
    "duplicate_lines": "n_lines >= 4 AND 100 * n_dup_lines > 50 * n_lines",
    "word_length": "word_chars < 2 * n_words OR word_chars > 25 * n_words",
    "capitals": "100 * n_upper > 35 * word_chars",
    "doubled_words": "100 * n_adjacent > 15 * n_words",
}


@dataclass(frozen=True)
class Policy:
    """A named, versioned set of rules."""

    name: str
    version: int
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        return sum(1 << list(RULES).index(r) for r in self.rules)


BASE = Policy("base", 1, ("few_words", "repeated_windows"))
STRICT = Policy("strict", 1, tuple(RULES))
LENIENT = Policy("lenient", 1, ("few_words", "repeated_windows", "symbols"))

_IS_SYMBOL = np.zeros(256, dtype=bool)
_IS_SYMBOL[list(SYMBOLS)] = True


def measure(texts: pa.Array) -> np.ndarray:
    """MEASURES of every text, one row each; nulls are empty."""
    out = [np.zeros((0, len(MEASURES)), dtype=np.int64)]
    for lo, hi in kernel.slices(texts):
        out.append(_measure(texts.slice(lo, hi - lo)))
    return np.concatenate(out)


def _again(keys: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For keys within a text: whether the key comes more than once, and whether it came before."""
    if not len(keys):
        return np.zeros(0, dtype=bool), np.zeros(0, dtype=bool)
    tagged = kernel.mix64(keys ^ kernel.mix64(owner.astype(np.uint64) + np.uint64(1)))
    order = np.argsort(tagged, kind="stable")
    same = tagged[order][1:] == tagged[order][:-1]
    before = np.zeros(len(keys), dtype=bool)
    more = np.zeros(len(keys), dtype=bool)
    before[order[1:]] = same
    more[order[1:]] |= same
    more[order[:-1]] |= same
    return more, before


def _measure(texts: pa.Array) -> np.ndarray:
    rows = len(texts)
    buf, offsets = kernel.flatten(texts)
    starts, ends, owner = kernel.words(buf, offsets)
    count = lambda at, w=None: np.bincount(at, weights=w, minlength=rows).astype(np.int64)
    total = lambda flags: np.add.reduceat(flags, offsets[:-1], dtype=np.int64) if rows else np.zeros(0, dtype=np.int64)
    hashes = kernel.word_hashes(buf, starts, ends)
    points = np.concatenate(([0], np.cumsum((buf & 0xC0) != 0x80)))
    covered = np.zeros(len(starts) + 1, dtype=np.int64)
    if len(hashes) >= WINDOW:
        inside = np.flatnonzero(owner[: len(owner) - WINDOW + 1] == owner[WINDOW - 1 :])
        windows, at = kernel.shingles(hashes, owner, WINDOW, rows)
        full = np.bincount(owner, minlength=rows)[at] >= WINDOW  # shorter texts have no window
        more, _ = _again(windows[full], at[full])
        first = inside[more]
        covered[: len(starts) + 1] += np.bincount(first, minlength=len(starts) + 1) - np.bincount(first + WINDOW, minlength=len(starts) + 1)
    repeat = np.cumsum(covered)[:-1] > 0
    cut = np.flatnonzero(buf == 10)
    line_start = np.sort(np.concatenate([offsets[:-1], cut + 1]))
    line_text = np.searchsorted(offsets, line_start, side="right") - 1
    line_end = np.minimum(np.append(line_start[1:], len(buf)) - 1, offsets[line_text + 1] - 1)
    worded = np.searchsorted(starts, line_end, side="left") > np.searchsorted(starts, line_start, side="left")
    _, dup = _again(kernel.word_hashes(buf, line_start[worded], line_end[worded]), line_text[worded])
    same = np.zeros(len(hashes), dtype=bool)
    same[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
    return np.stack(
        [
            count(owner),
            count(owner, points[ends] - points[starts]),
            total(_IS_SYMBOL[buf]),
            count(line_text[worded][dup]),
            count(owner[repeat]),
            count(line_text[worded]),
            total((buf >= 65) & (buf <= 90)),
            count(owner[same]),
        ],
        axis=1,
    )


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        got = measure(batch.column("text"))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id")] + [pa.array(got[:, i]) for i in range(len(MEASURES))], names=["doc_id", *MEASURES])


def ledger(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, the measurements, and ``fail_bits`` with one bit a rule.

    Words are runs without ASCII white space.  Null and empty texts measure 0
    throughout; null and repeated ids keep their rows; other columns are
    ignored; an empty table gives an empty ledger.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    measured = rows.mapInArrow(kernel.tidy(_rows), ", ".join([f"doc_id {kind}"] + [f"{m} long" for m in MEASURES]))
    bits = sum((F.when(F.expr(c), F.lit(1 << i)).otherwise(F.lit(0)) for i, c in enumerate(RULES.values())), F.lit(0))
    return measured.withColumn("fail_bits", bits.cast("long"))


def rules_version() -> str:
    """Changes whenever a rule or a measurement does."""
    return hashlib.sha256(repr((MEASURES, RULES, WINDOW, SYMBOLS)).encode()).hexdigest()[:16]


def stored_ledger(spark: SparkSession, table: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The ledger of a Parquet table, in the shared folder: read if these rules have judged these files before, else written.

    Files are told by name, length and time of change.  A ledger appears under its
    name only when it is complete; of two writers at once, the first one stays.
    """
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(table)
    files = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    seen = sorted((s.getPath().toString(), s.getLen(), s.getModificationTime()) for s in files.listStatus(at))
    name = hashlib.sha256(repr((seen, id_col, text_col)).encode()).hexdigest()[:24]
    folder = jvm.org.apache.hadoop.fs.Path(f"{shared_folder(spark)}/ledgers/{name}-{rules_version()}")
    store = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not store.exists(folder):
        work = Workspace(spark, "ledger")
        work.save(ledger(spark.read.parquet(table), id_col, text_col), "book")
        store.mkdirs(folder.getParent())
        if not store.exists(folder):
            store.rename(jvm.org.apache.hadoop.fs.Path(work.path("book")), folder)
        work.drop()
    return spark.read.parquet(folder.toString())


def apply_policy(book: DataFrame, policy: Policy) -> DataFrame:
    """The ledger with ``kept``: no bit of the policy is set."""
    return book.withColumn("kept", F.col("fail_bits").bitwiseAND(F.lit(policy.mask)) == 0)


def ablations(book: DataFrame, policies: list[Policy]) -> DataFrame:
    """Per policy and rule: documents the rule fails, those it alone rejects, and those kept with and without it.

    Documents are counted by distinct bit pattern first, so at most 2^rules rows are shuffled a task.
    """
    patterns = book.groupBy("fail_bits").agg(F.count("*").alias("docs"))
    rows = [(p.name, p.version, p.mask, r, 1 << list(RULES).index(r)) for p in policies for r in p.rules]
    asked = F.array(*[F.struct(F.lit(a).alias("policy"), F.lit(b).alias("version"), F.lit(c).cast("long").alias("mask"), F.lit(d).alias("rule"), F.lit(e).cast("long").alias("bit")) for a, b, c, d, e in rows])
    x = patterns.select("fail_bits", "docs", F.explode(asked).alias("a")).select("fail_bits", "docs", "a.*")
    hit = F.col("fail_bits").bitwiseAND(F.col("mask"))
    n = lambda cond: F.sum(F.when(cond, F.col("docs")).otherwise(0)).cast("long")
    return x.groupBy("policy", "version", "rule").agg(
        n(F.col("fail_bits").bitwiseAND(F.col("bit")) != 0).alias("n_failed"),
        n(hit == F.col("bit")).alias("n_only"),
        n(hit == 0).alias("n_kept"),
        n(hit.bitwiseAND(F.bitwise_not(F.col("bit"))) == 0).alias("n_kept_without"),
    )


def op8_rule_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` under the strict policy."""
    book = apply_policy(stored_ledger(spark, f"{sf_dir}/documents.parquet"), STRICT)
    failed = F.col("fail_bits").bitwiseAND(F.lit(BASE.mask)) != 0
    return book.select("doc_id", *MEASURES[:5], failed.alias("base_failed"), "kept", "fail_bits", *MEASURES[5:])


def op8_policy_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each rule of each policy does to ``documents``."""
    return ablations(stored_ledger(spark, f"{sf_dir}/documents.parquet"), [BASE, LENIENT, STRICT])


_WORD = r"[^\x20\x09-\x0D]+"
_LEDGER = rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS w FROM documents),
win AS (SELECT rid, i, array_to_string(w[i : i + {WINDOW - 1}], ' ') AS k FROM (SELECT rid, w, unnest(range(1, len(w) - {WINDOW - 2})) AS i FROM d)),
rep AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest(range(i, i + {WINDOW})) AS p FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, k) AS c FROM win) WHERE c > 1) GROUP BY rid),
ln AS (SELECT rid, l FROM (SELECT rid, unnest(string_split(t, chr(10))) AS l FROM d) WHERE regexp_matches(l, '{_WORD}')),
dup AS (SELECT rid, count(*) AS lines, count(*) - count(DISTINCT l) AS n FROM ln GROUP BY rid),
m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
        CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
        CAST(coalesce(dup.n, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words, CAST(coalesce(dup.lines, 0) AS BIGINT) AS n_lines,
        CAST(length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS BIGINT) AS n_upper,
        CAST(len(list_filter(range(2, len(w) + 1), lambda i: w[i] = w[i - 1])) AS BIGINT) AS n_adjacent
      FROM d LEFT JOIN rep USING (rid) LEFT JOIN dup USING (rid)),
book AS (SELECT *, CAST({" + ".join(f"CASE WHEN {c} THEN {1 << i} ELSE 0 END" for i, c in enumerate(RULES.values()))} AS BIGINT) AS fail_bits FROM m)
"""
OP8_SQL = _LEDGER + f"SELECT doc_id, {', '.join(MEASURES)}, fail_bits, fail_bits & {BASE.mask} <> 0 AS base_failed, fail_bits & {STRICT.mask} = 0 AS kept FROM book"
OP8_ABLATION_SQL = _LEDGER + " UNION ALL ".join(
    f"SELECT '{p.name}' AS policy, {p.version} AS version, '{r}' AS rule, count_if(fail_bits & {b} <> 0) AS n_failed, count_if(fail_bits & {p.mask} = {b}) AS n_only, count_if(fail_bits & {p.mask} = 0) AS n_kept, count_if(fail_bits & {p.mask & ~b} = 0) AS n_kept_without FROM book"
    for p in (BASE, LENIENT, STRICT)
    for r in p.rules
    for b in [1 << list(RULES).index(r)]
)
OP8_ABLATION_SQL = f"SELECT policy, version, rule, CAST(n_failed AS BIGINT) AS n_failed, CAST(n_only AS BIGINT) AS n_only, CAST(n_kept AS BIGINT) AS n_kept, CAST(n_kept_without AS BIGINT) AS n_kept_without FROM ({OP8_ABLATION_SQL})"
