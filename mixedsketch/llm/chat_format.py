"""Chat formatting with loss masks aligned by offsets.

A conversation is rendered as a whole and encoded once with offsets.  The spans
of its assistant texts are sorted and disjoint, and so are the starts of its
tokens, so a binary search finds the tokens a span meets; a token that goes over
the edge of a span is trimmed to it.  Control strings inside texts or roles are
broken up by an escape that decoding undoes exactly.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .workspace import ship

TURN, END = "<|turn|>", "<|end|>"
#: Strings that must not come out of a text as they are (our marks, and those of common chat templates).
CONTROL = [TURN, END, "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<|startoftext|>", "<<SYS>>", "<</SYS>>", "[INST]", "[/INST]", "<s>", "</s>"]
ESCAPE = "␛"
_FIND = re.compile("|".join(re.escape(c) for c in CONTROL))
_UNDO = re.compile(ESCAPE + "(.)")
_MEANT = {"e": ESCAPE, "c": "", "n": "\n"}


def escape(text: str) -> str:
    """No control string is left: each is broken after its first character, and the escape itself is doubled up."""
    return _FIND.sub(lambda m: f"{m.group()[0]}{ESCAPE}c{m.group()[1:]}", text.replace(ESCAPE, ESCAPE + "e"))


def unescape(text: str) -> str:
    return _UNDO.sub(lambda m: _MEANT[m.group(1)], text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The conversation as one string, and the spans of its escaped assistant texts."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        head = f"{TURN}{escape(role).replace(chr(10), ESCAPE + 'n')}\n"
        body = escape(text)
        if role == "assistant":
            spans.append((at + len(head), at + len(head) + len(body)))
        parts += [head, body, END, "\n"]
        at += len(head) + len(body) + len(END) + 1
    return "".join(parts), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a rendered conversation."""
    turns = []
    for piece in formatted.split(TURN)[1:]:
        role, _, rest = piece.partition("\n")
        turns.append((unescape(role), unescape(rest[: -len(END) - 1])))
    return turns


def mask_tokens(starts: np.ndarray, ends: np.ndarray, spans: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token, from, to) of every piece of a span that a token covers.

    Tokens come in text order; several may share a character, which counts for
    the first of them only.
    """
    reach = np.maximum.accumulate(ends) if len(ends) else ends
    token, lo, hi = [], [], []
    for a, b in spans:
        i, j = int(np.searchsorted(reach, a, side="right")), int(np.searchsorted(starts, b, side="left"))
        if j <= i:
            continue
        before = np.concatenate(([a], reach[i : j - 1]))
        x, y = np.maximum(np.maximum(starts[i:j], a), before), np.minimum(ends[i:j], b)
        keep = y > x
        token.append(np.arange(i, j)[keep])
        lo.append(x[keep])
        hi.append(y[keep])
    empty = np.zeros(0, dtype=np.int64)
    return tuple(np.concatenate(v) if v else empty for v in (token, lo, hi))


_tokenizers: dict = {}


def _tokenizer(name: str):
    if name not in _tokenizers:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import public_tokenizers
        from tokenizers import Tokenizer, processors

        t = Tokenizer.from_file(name if os.path.isabs(name) else public_tokenizers.path(name))
        t.encode_special_tokens = True  # strings of special tokens in a text are ordinary text
        t.post_processor = processors.ByteLevel(trim_offsets=False)  # blanks belong to their tokens
        _tokenizers[name] = t
    return _tokenizers[name]


FORMATTED = "conv_id long, formatted string, input_ids array<int>, loss_mask array<boolean>, loss_from array<int>, loss_to array<int>"


def _format(vocabulary: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _tokenizer(vocabulary)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                done = [render([(x["role"], x["text"]) for x in turns]) for turns in part.column("turns").to_pylist()]
                out = {"formatted": [d[0] for d in done], "input_ids": [], "loss_mask": [], "loss_from": [], "loss_to": []}
                for (_, spans), code in zip(done, t.encode_batch([d[0] for d in done], add_special_tokens=False), strict=True):
                    offsets = np.array(code.offsets, dtype=np.int64).reshape(-1, 2)
                    token, lo, hi = mask_tokens(offsets[:, 0], offsets[:, 1], spans)
                    mask = np.zeros(len(offsets), dtype=bool)
                    mask[token] = True
                    out["input_ids"].append(code.ids)
                    out["loss_mask"].append(mask)
                    out["loss_from"].append(lo)
                    out["loss_to"].append(hi)
                yield pa.RecordBatch.from_arrays(
                    [part.column("conv_id"), pa.array(out["formatted"], pa.string()), pa.array(out["input_ids"], pa.list_(pa.int32())), pa.array(out["loss_mask"], pa.list_(pa.bool_()))]
                    + [pa.array([v.astype(np.int32) for v in out[k]], pa.list_(pa.int32())) for k in ("loss_from", "loss_to")],
                    names=["conv_id", "formatted", "input_ids", "loss_mask", "loss_from", "loss_to"],
                )

    return run


def format_conversations(rows: DataFrame, vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """One row per conv_id: the rendered text, its ids, the mask of tokens that carry loss, and the character
    pieces under the mask (one per masked token, in order).

    ``rows`` has conv_id, turn, role, text; turns are ordered by turn, then role
    and text, so ties and repeated rows have one order and all stay.  Null
    roles and texts are empty; rows with a null conv_id belong to nothing known
    and are a conversation each; other columns are ignored; an empty table gives no rows.  A conversation is
    one output row and has to fit into a task.
    """
    ship(rows.sparkSession)
    turn = F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = rows.select(F.col("conv_id").cast("long").alias("conv_id"), turn.alias("one"), F.when(F.col("conv_id").isNull(), F.monotonically_increasing_id()).alias("alone"))
    grouped = rows.groupBy("conv_id", "alone").agg(F.sort_array(F.collect_list("one")).alias("turns")).drop("alone")
    return grouped.mapInArrow(kernel.tidy(_format(vocabulary)), FORMATTED)


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = {k: [] for k in ("n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars")}
        for text, lo, hi in zip(batch.column("formatted").to_pylist(), batch.column("loss_from").to_pylist(), batch.column("loss_to").to_pylist(), strict=True):
            turns = parse(text)
            loss = unescape("".join([text[a:b] for a, b in zip(lo, hi, strict=True)]))
            out["n_turns"].append(len(turns))
            out["turns_sha256"].append(hashlib.sha256("".join([f"{r}\n{t}\n" for r, t in turns]).encode()).hexdigest())
            out["loss_chars"].append(len(loss))
            out["loss_sha256"].append(hashlib.sha256(loss.encode()).hexdigest())
            out["formatted_chars"].append(len(text))
        yield pa.RecordBatch.from_arrays([batch.column("conv_id")] + [pa.array(v, pa.string() if k.endswith("sha256") else pa.int64()) for k, v in out.items()], names=["conv_id", *out])


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``conversations`` and one full of control strings, read back from the formatted output."""
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", probe), (-7, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    out = format_conversations(rows.unionByName(extra))
    return out.mapInArrow(kernel.tidy(_digest), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def _sql_escape(column: str) -> str:
    out = f"replace({column}, '{ESCAPE}', '{ESCAPE}e')"
    for c in CONTROL:
        out = f"replace({out}, '{c}', '{c[0]}{ESCAPE}c{c[1:]}')"
    return out


OP5_SQL = f"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, CASE WHEN conv_id IS NULL THEN row_number() OVER () END AS alone FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]', NULL UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]', NULL),
g AS (SELECT conv_id, count(*) AS n_turns,
  string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS turns,
  coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '') AS loss,
  sum(length({_sql_escape("role")}) + length(replace(role, chr(10), '__')) - length(role) + length({_sql_escape("text")}) + {len(TURN) + len(END) + 2}) AS formatted_chars
  FROM r GROUP BY conv_id, alone)
SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256, CAST(formatted_chars AS BIGINT) AS formatted_chars FROM g
"""
