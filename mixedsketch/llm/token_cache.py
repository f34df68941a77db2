"""Exact token ids of whole texts at a fraction of the tokenizer's cost.

The tokenizer drops white space and never merges across it, so the ids of a
text are the ids of its words in turn; a word of plain letters and marks splits
further where these meet.  Units repeat; each distinct unit that is not in a
bounded, direct-mapped cache is encoded by the library, the rest is gathered
with numpy.  ``word_wise`` checks the property on the vocabulary file.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from . import kernel

SLOT_BITS = 20
POOL = 6 << 20
CHUNK = 400
SLICE_BYTES = 1 << 19  # numpy needs some thirty bytes for each byte of text in work

_WHITE, _LETTER, _MARK, _OTHER = 0, 1, 2, 3
#: ASCII letters and those of Latin-1 in UTF-8, and ASCII marks; digits, the apostrophe, the start of
#: special tokens and all other bytes leave a word whole.
_KIND = np.full(256, _OTHER, dtype=np.uint8)
_KIND[list(kernel.WHITE)] = _WHITE
_KIND[list(range(65, 91)) + list(range(97, 123)) + list(range(0x80, 0xC0)) + [0xC3]] = _LETTER
_KIND[list(b"!\"#$%&()*+,-./:;=>?@[\\]^_`{|}~")] = _MARK


class TokenCache:
    """Encodes Arrow string arrays; one instance a Python worker."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if not word_wise(spec):
            raise ValueError(f"{path}: its ids depend on white space between words")
        self.tokenizer = Tokenizer.from_file(path)
        self.vocabulary = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.ends_word = np.zeros(self.vocabulary, dtype=bool)
        suffix = spec["model"]["end_of_word_suffix"]
        self.ends_word[[i for t, i in self.tokenizer.get_vocab(with_added_tokens=False).items() if t.endswith(suffix)]] = True
        self._clear()

    def _clear(self) -> None:
        self.key = np.zeros(1 << SLOT_BITS, dtype=np.uint64)
        self.at = np.zeros(1 << SLOT_BITS, dtype=np.int32)
        self.size = np.full(1 << SLOT_BITS, -1, dtype=np.int32)
        self.pool = np.zeros(POOL, dtype=np.uint16 if self.vocabulary <= 1 << 16 else np.uint32)
        self.used = 0

    def _encode_units(self, units: list[str], whole: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all units, ids per unit).  Units that are one piece are joined by blanks, and a piece ends where an end-of-word token does."""
        sizes = np.zeros(len(units), dtype=np.int64)
        parts, order = [], []
        plain = np.flatnonzero(whole)
        texts = [" ".join([units[i] for i in plain[k : k + CHUNK]]) for k in range(0, len(plain), CHUNK)]
        for k, got in enumerate(self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)):
            block = plain[k * CHUNK : (k + 1) * CHUNK]
            ids = np.array(got.ids, dtype=np.int64)
            ends = np.flatnonzero(self.ends_word[ids])
            sizes[block] = np.diff(np.concatenate(([-1], ends)))
            parts.append(ids)
            order.append(block)
        for i in np.flatnonzero(~whole):
            ids = np.array(self.tokenizer.encode(units[i], add_special_tokens=False).ids, dtype=np.int64)
            sizes[i] = len(ids)
            parts.append(ids)
            order.append([i])
        flat = np.concatenate(parts) if parts else np.zeros(0, dtype=np.int64)
        if order:  # back to the order of the units
            order = np.concatenate(order)
            begin = np.zeros(len(units), dtype=np.int64)
            begin[order] = np.concatenate(([0], np.cumsum(sizes[order])))[:-1]
            flat = flat[ragged(begin, sizes)]
        return flat, sizes

    def _units(self, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(start, end, text, one piece?): words; plain ones are cut where letters meet punctuation."""
        kind = _KIND[buf]
        late = (buf[1:] == 0x97) | (buf[1:] == 0xB7)
        kind[1:][late & (buf[:-1] == 0xC3)] = _OTHER  # the two signs among the accented letters
        inside = kind != _WHITE
        edge = np.diff(inside.view(np.int8), prepend=np.int8(0))
        starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        odd = np.zeros(len(starts), dtype=bool)
        odd[np.searchsorted(starts, np.flatnonzero(kind == _OTHER), side="right") - 1] = True
        turn = np.flatnonzero((kind[1:] != kind[:-1]) & inside[1:] & inside[:-1]) + 1
        turn = turn[~odd[np.searchsorted(starts, turn, side="right") - 1]]
        more = np.sort(np.concatenate([starts, turn]))
        fewer = np.sort(np.concatenate([ends, turn]))
        one = ~odd[np.searchsorted(starts, more, side="right") - 1]
        return more, fewer, np.searchsorted(offsets, more, side="right") - 1, one

    def _spans(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pool offset, ids, text) of every unit."""
        buf, offsets = kernel.flatten(texts)
        if b"<|" not in buf.tobytes():  # special tokens must keep their case
            buf = kernel.lower(buf)
        starts, ends, owner, one = self._units(buf, offsets)
        hashes = kernel.word_hashes(buf, starts, ends)
        if self.used > POOL // 2:
            self._clear()
        slot = (hashes >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
        at, size = self.at[slot].astype(np.int64), self.size[slot].astype(np.int64)
        miss = np.flatnonzero((self.key[slot] != hashes) | (size < 0))
        if len(miss):
            new, first, back = np.unique(hashes[miss], return_index=True, return_inverse=True)
            raw = buf.tobytes()
            where = miss[first]
            flat, sizes = self._encode_units([raw[a:b].decode("utf-8", "replace") for a, b in zip(starts[where].tolist(), ends[where].tolist(), strict=True)], one[where])
            begin = self.used + np.concatenate(([0], np.cumsum(sizes)))[:-1]
            need = self.used + len(flat)
            if need > len(self.pool):  # only until the next call: a batch of unheard-of words
                self.pool = np.concatenate([self.pool, np.zeros(need - len(self.pool), dtype=self.pool.dtype)])
            self.pool[self.used : need] = flat
            self.used = need
            at[miss], size[miss] = begin[back], sizes[back]
            spot = (new >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
            self.key[spot], self.at[spot], self.size[spot] = new, begin, sizes
        return at, size, owner

    def counts(self, texts: pa.Array) -> np.ndarray:
        """Tokens per text."""
        out = [np.zeros(0, dtype=np.int64)]
        for lo, hi in kernel.slices(texts, SLICE_BYTES):
            _, size, owner = self._spans(texts.slice(lo, hi - lo))
            out.append(np.bincount(owner, weights=size, minlength=hi - lo).astype(np.int64))
        return np.concatenate(out)

    def encode(self, texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(first row, end row, ids of all these rows, ids per row)."""
        for lo, hi in kernel.slices(texts, SLICE_BYTES):
            at, size, owner = self._spans(texts.slice(lo, hi - lo))
            ids = self.pool[ragged(at, size)]
            yield lo, hi, ids, np.bincount(owner, weights=size, minlength=hi - lo).astype(np.int64)


def ragged(begin: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices begin[i], begin[i]+1, ... for sizes[i] places each, one after the other."""
    ends = np.cumsum(sizes)
    total = int(ends[-1]) if len(ends) else 0
    return np.repeat(begin - (ends - sizes), sizes) + np.arange(total)


def word_wise(spec: dict) -> bool:
    """Whether ids of a text are those of its words in turn, as its normalizer and splitter show."""
    pre = spec.get("pre_tokenizer") or {}
    steps = pre.get("pretokenizers", [pre])
    split = [s for s in steps if s.get("type") == "Split" and s.get("behavior") == "Removed" and s.get("invert")]
    prefix = any(s.get("add_prefix_space") for s in steps)
    flags = any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in spec.get("added_tokens", []))
    lower = any(n.get("type") == "Lowercase" for n in (spec.get("normalizer") or {}).get("normalizers", []))
    classes = r"[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
    return bool(split) and not prefix and not flags and lower and classes in str(split[0]["pattern"].get("Regex")) and bool(spec["model"].get("end_of_word_suffix"))


_cache: dict[str, TokenCache] = {}


def token_cache(name: str) -> TokenCache:
    """This worker's cache for a vocabulary file, given as a path or as a name of the public ones."""
    if name not in _cache:
        path = name
        if not os.path.isabs(name):
            import public_tokenizers

            path = public_tokenizers.path(name)
        _cache[name] = TokenCache(path)
    return _cache[name]
