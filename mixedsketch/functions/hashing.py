"""Key folding and the hash family, as column expressions and as numpy twins.

Family ``md5``: a key is mixed and folded below 2^31 - 1, then every hash is
linear arithmetic that stays below 2^62, so Spark, DuckDB and numpy agree to
the bit.  Family ``xxhash64``, for domains beyond some 10^5 keys: a key is its
64-bit hash, and rows, owners and signs are seeded 64-bit hashes of that.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..spec import PRIME, SketchSpec


OWNER_SEED, SIGN_SEED = 1_000_003, 2_000_003


def rekeyed(s, spec: SketchSpec):
    """The stream with its keys in the form of the spec's hash family; it must carry the given keys in ``k``."""
    return s.withColumn("key", canon_key(F.col("k"), spec.hash_family)) if spec.hash_family != "md5" else s


def canon_key(col: Column, family: str = "md5") -> Column:
    """Fold a key of any accepted type to a BIGINT, below 2^31 - 1 for ``md5``; null stays null.

    Structs fold by their JSON form.  Doubles are refused where the type is
    known (``check_key_type``): equal values may print differently.
    """
    text = col.cast("string")
    if family == "xxhash64":
        return F.when(text.isNotNull(), F.xxhash64(text))
    return F.pmod(F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint"), F.lit(PRIME))


def check_key_type(kind: T.DataType) -> None:
    if isinstance(kind, (T.DoubleType, T.FloatType, T.MapType, T.ArrayType)):
        raise TypeError(f"{kind.simpleString()} is no key type")


def linear(x: Column, a: int, b: int, modulus: int) -> Column:
    return F.pmod(F.pmod(x * F.lit(a).cast("bigint") + F.lit(b).cast("bigint"), F.lit(PRIME).cast("bigint")), F.lit(modulus).cast("bigint"))


def _seeded(x: Column, seed: int) -> Column:
    return F.xxhash64(x, F.lit(seed).cast("bigint"))


def row_hash(x: Column, spec: SketchSpec, j: int) -> Column:
    if spec.hash_family == "xxhash64":
        return F.pmod(_seeded(x, j), F.lit(spec.K).cast("bigint")).cast("int")
    return linear(x, *spec.row(j), spec.K).cast("int")


def owner(x: Column, spec: SketchSpec) -> Column:
    if spec.hash_family == "xxhash64":
        return F.pmod(_seeded(x, OWNER_SEED), F.lit(spec.P).cast("bigint")).cast("int")
    return linear(x, *spec.owner, spec.P).cast("int")


def sign(x: Column, spec: SketchSpec, j: int) -> Column:
    if spec.hash_family == "xxhash64":
        return F.when(_seeded(x, SIGN_SEED + j) < 0, F.lit(1)).otherwise(F.lit(-1)).cast("bigint")
    c = [F.lit(v).cast("bigint") for v in spec.sign(j)]
    acc = c[0]
    for v in c[1:]:
        acc = F.pmod(acc * x + v, F.lit(PRIME).cast("bigint"))
    return F.when(F.pmod(acc, F.lit(2)) == 1, F.lit(1)).otherwise(F.lit(-1)).cast("bigint")


def _linear_text(x: str, a: int, b: int, modulus: int) -> str:
    return f"pmod(pmod({x} * {a}L + {b}L, {PRIME}L), {modulus}L)"


def row_text(x: str, spec: SketchSpec, j: int) -> str:
    """``row_hash`` as text of one expression, which takes one call to Spark and not one for each term."""
    return f"CAST({f'pmod(xxhash64({x}, {j}L), {spec.K}L)' if spec.hash_family == 'xxhash64' else _linear_text(x, *spec.row(j), spec.K)} AS INT)"


def owner_text(x: str, spec: SketchSpec) -> str:
    """``owner`` as text."""
    return f"CAST({f'pmod(xxhash64({x}, {OWNER_SEED}L), {spec.P}L)' if spec.hash_family == 'xxhash64' else _linear_text(x, *spec.owner, spec.P)} AS INT)"


def sign_text(x: str, spec: SketchSpec, j: int) -> str:
    """``sign`` as text."""
    if spec.hash_family == "xxhash64":
        return f"CAST(CASE WHEN xxhash64({x}, {SIGN_SEED + j}L) < 0 THEN 1 ELSE -1 END AS BIGINT)"
    first, *more = spec.sign(j)
    acc = f"{first}L"
    for v in more:
        acc = f"pmod({acc} * {x} + {v}L, {PRIME}L)"
    return f"CAST(CASE WHEN pmod({acc}, 2) = 1 THEN 1 ELSE -1 END AS BIGINT)"


def row_and_sign(x: Column, row: Column, spec: SketchSpec) -> tuple[Column, Column]:
    """(column, sign) of the row number in ``row``: one expression for sketches of many rows."""
    if spec.hash_family == "xxhash64":
        seeded = lambda seed: F.xxhash64(x, row.cast("bigint") + F.lit(seed).cast("bigint"))
        return F.pmod(seeded(0), F.lit(spec.K).cast("bigint")).cast("int"), F.when(seeded(SIGN_SEED) < 0, F.lit(1)).otherwise(F.lit(-1)).cast("bigint")
    of = lambda values: F.get(F.array(*[F.lit(v).cast("bigint") for v in values]), row)
    p = F.lit(PRIME).cast("bigint")
    pairs = [spec.row(j) for j in range(spec.H)]
    col = F.pmod(F.pmod(x * of([a for a, _ in pairs]) + of([b for _, b in pairs]), p), F.lit(spec.K).cast("bigint")).cast("int")
    signs = [spec.sign(j) for j in range(spec.H)]
    acc = of([c[0] for c in signs])
    for t in range(1, 4):
        acc = F.pmod(acc * x + of([c[t] for c in signs]), p)
    return col, F.when(F.pmod(acc, F.lit(2)) == 1, F.lit(1)).otherwise(F.lit(-1)).cast("bigint")


def fold(key) -> int:
    """``canon_key`` of one Python value, for tests and drivers."""
    return int(hashlib.md5(str(key).encode()).hexdigest()[:15], 16) % PRIME


def row_hashes_np(x: np.ndarray, spec: SketchSpec) -> np.ndarray:
    """(len(x), H) columns."""
    if spec.hash_family == "xxhash64":
        return np.stack([xxhash64_np(x, j) % spec.K for j in range(spec.H)], axis=1)
    x = x.astype(np.int64)
    return np.stack([(a * x + b) % PRIME % spec.K for a, b in (spec.row(j) for j in range(spec.H))], axis=1)


#: The primes of the published 64-bit hash.
_X1, _X2, _X3, _X4, _X5 = (np.uint64(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _xx_long(x: np.ndarray, seed) -> np.ndarray:
    """The published hash of 8 bytes."""
    turn = lambda v, r: (v << np.uint64(r)) | (v >> np.uint64(64 - r))
    h = (seed + _X5 + np.uint64(8)) ^ (turn(x * _X2, 31) * _X1)
    h = turn(h, 27) * _X1 + _X4
    h = (h ^ (h >> np.uint64(33))) * _X2
    h = (h ^ (h >> np.uint64(29))) * _X3
    return h ^ (h >> np.uint64(32))


def xxhash64_np(x: np.ndarray, seed: int) -> np.ndarray:
    """What ``F.xxhash64(x, seed)`` gives for two BIGINTs: the first hash is the seed of the second."""
    first = _xx_long(np.asarray(x, dtype=np.int64).view(np.uint64), np.full(len(x), 42, dtype=np.uint64))
    return _xx_long(np.full(len(x), seed, dtype=np.uint64), first).view(np.int64)


def owner_np(x: np.ndarray, spec: SketchSpec) -> np.ndarray:
    if spec.hash_family == "xxhash64":
        return xxhash64_np(x, OWNER_SEED) % spec.P
    a, b = spec.owner
    return (a * x.astype(np.int64) + b) % PRIME % spec.P


# --- DuckDB spelling of the same arithmetic, for oracle queries


def sql_fold(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 15))::BIGINT % {PRIME})"


def sql_linear(x: str, a: int, b: int, modulus: int) -> str:
    return f"((({a}::BIGINT * {x} + {b}) % {PRIME}) % {modulus})"


def sql_row(x: str, spec: SketchSpec, j: int) -> str:
    return sql_linear(x, *spec.row(j), spec.K)


def sql_owner(x: str, spec: SketchSpec) -> str:
    return sql_linear(x, *spec.owner, spec.P)


def sql_sign(x: str, spec: SketchSpec, j: int) -> str:
    c = spec.sign(j)
    acc = str(c[0]) + "::BIGINT"
    for v in c[1:]:
        acc = f"(({acc} * {x} + {v}) % {PRIME})"
    return f"(CASE WHEN {acc} % 2 = 1 THEN 1 ELSE -1 END)"
