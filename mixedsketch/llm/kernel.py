"""Vectorised text kernels shared by the corpus operators.

A batch of texts is one UTF-8 byte buffer plus offsets; words, word hashes and
shingles of all texts come out of a handful of numpy passes, so the cost per
byte does not depend on how the bytes are spread over documents.  Nulls count
as empty texts everywhere in this module.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: ASCII white space, which separates words.
WHITE = b"\x20\x09\x0a\x0b\x0c\x0d"

def release() -> None:
    """Give freed memory back to the system: a Python worker that waits for its next task should hold little."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: it keeps what it keeps
        pass


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """``run`` for mapInArrow, releasing memory when its task ends."""

    @wraps(run)
    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_STEP = 0x9E3779B97F4A7C15
_ODD = 0xD1342543DE82EF95


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words (splitmix)."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x = x ^ (x >> np.uint64(27))
    x = x * _M2
    return x ^ (x >> np.uint64(31))


_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(_STEP))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_WHITE = np.zeros(256, dtype=bool)
_IS_WHITE[list(WHITE)] = True
#: Unrelated odd multipliers by place: small ones would give some rearranged shingles equal sums.
_PLACE = mix64(np.arange(1, 65, dtype=np.uint64) * np.uint64(_ODD)) | np.uint64(1)
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int, inverse: bool) -> np.ndarray:
    key = "inv" if inverse else "fwd"
    have = _powers.get(key)
    if have is None or len(have) < n:
        base = pow(_ODD, -1, 2**64) if inverse else _ODD
        steps = np.full(max(n, 1 << 16), base, dtype=np.uint64)
        steps[0] = 1
        have = _powers[key] = np.cumprod(steps, dtype=np.uint64)
    return have[:n]


def slices(texts: pa.Array, max_bytes: int = 1 << 19) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``max_bytes`` of text each (a longer text stands alone)."""
    sizes = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at, base = 0, 0
    while at < len(sizes):
        to = max(at + 1, int(np.searchsorted(sizes, base + max_bytes, side="right")))
        yield at, to
        at, base = to, int(sizes[to - 1])


def flatten(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """One byte buffer with a blank after each text, and len+1 offsets into it."""
    raw = [b"" if v is None else v for v in texts.cast(pa.large_binary()).to_pylist()]
    sizes = np.fromiter((len(v) + 1 for v in raw), dtype=np.int64, count=len(raw))
    offsets = np.concatenate(([0], np.cumsum(sizes)))
    return np.frombuffer(b" ".join(raw) + b" ", dtype=np.uint8), offsets


def lower(buf: np.ndarray) -> np.ndarray:
    """A-Z to a-z, all other bytes kept."""
    return _LOWER[buf]


def words(buf: np.ndarray, offsets: np.ndarray, white: np.ndarray = _IS_WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, text index) of every maximal run of bytes that are not ``white``."""
    inside = ~white[buf]
    edge = np.diff(inside.view(np.int8), prepend=np.int8(0))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte ranges, from prefix sums of a rolling polynomial."""
    n = len(buf)
    sums = np.empty(n + 1, dtype=np.uint64)
    sums[0] = 0
    np.cumsum(_BYTE[buf] * _power_table(n, False), dtype=np.uint64, out=sums[1:])
    return mix64((sums[ends] - sums[starts]) * _power_table(n, True)[starts])


def shingles(hashes: np.ndarray, owner: np.ndarray, size: int, n_texts: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of ``size`` (up to 64) words and their text; a text of fewer words, but not none, gives one."""
    k = len(hashes)
    per_text = np.bincount(owner, minlength=n_texts)
    if k >= size:
        total = np.zeros(k - size + 1, dtype=np.uint64)
        for j in range(size):
            total += hashes[j : k - size + 1 + j] * _PLACE[j]
        whole = owner[: k - size + 1] == owner[size - 1 :]
        out, at = mix64(total[whole]), owner[: k - size + 1][whole]
    else:
        out, at = np.empty(0, dtype=np.uint64), np.empty(0, dtype=owner.dtype)
    few = np.flatnonzero((per_text > 0) & (per_text < size))
    if len(few):
        first = np.concatenate(([0], np.cumsum(per_text)))
        extra = np.array([_short(hashes[first[i] : first[i + 1]]) for i in few], dtype=np.uint64)
        out, at = np.concatenate([out, extra]), np.concatenate([at, few.astype(at.dtype)])
        order = np.argsort(at, kind="stable")
        out, at = out[order], at[order]
    return out, at


def _short(hashes: np.ndarray) -> int:
    total = len(hashes) * _STEP
    for j, h in enumerate(hashes.tolist()):
        total += h * int(_PLACE[j % len(_PLACE)])
    return int(mix64(np.array([total % 2**64], dtype=np.uint64))[0])


def runs(owner: np.ndarray, n_texts: int) -> np.ndarray:
    """n_texts+1 offsets into an array ordered by text."""
    return np.concatenate(([0], np.cumsum(np.bincount(owner, minlength=n_texts))))


def shingle_sets(texts: pa.Array, size: int, fold_case: bool = True) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, values, cut): row lo+i has the sorted distinct hashes values[cut[i]:cut[i+1]]."""
    for lo, hi in slices(texts):
        buf, offsets = flatten(texts.slice(lo, hi - lo))
        if fold_case:
            buf = lower(buf)
        starts, ends, owner = words(buf, offsets)
        out, at = shingles(word_hashes(buf, starts, ends), owner, size, hi - lo)
        cut = runs(at, hi - lo)
        for i in range(hi - lo):
            out[cut[i] : cut[i + 1]].sort()
        keep = np.ones(len(out), dtype=bool)
        keep[1:] = (out[1:] != out[:-1]) | (at[1:] != at[:-1])
        yield lo, hi, out[keep], runs(at[keep], hi - lo)
