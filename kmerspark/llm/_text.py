"""Vectorised word kernels shared by the text operators.

All kernels work on Arrow buffers: whole texts in, NumPy arrays out, no Python loop per word.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash

#: Text bytes that one kernel call holds at a time (a single longer text is held whole).
BLOCK_BYTES = 4 << 20

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


@lru_cache(maxsize=1)
def give_back() -> None:
    """Let this process return freed arrays to the system at once: workers live long, and share their machine."""
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        ctypes.CDLL(None).mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD of glibc; other libraries have no such call
    except (AttributeError, OSError):
        pass


def text_blocks(batch: pa.RecordBatch, column: str, limit: int = BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows whose text is about `limit` bytes; a longer text is a run of its own."""
    give_back()
    if not batch.num_rows:
        return
    text = batch.column(batch.schema.get_field_index(column)).cast(pa.large_string())
    sizes = np.diff(_offsets(text))
    run = np.cumsum(sizes) // limit
    cuts = [0, *(np.flatnonzero(np.diff(run)) + 1), batch.num_rows]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        if b > a:
            yield batch.slice(a, b - a)


def _offsets(text: pa.LargeStringArray) -> np.ndarray:
    offsets = np.frombuffer(text.buffers()[1], dtype=np.int64)[text.offset : text.offset + len(text) + 1]
    if text.null_count:  # the extent of a null is undefined
        valid = np.asarray(text.is_valid())
        lengths = np.where(valid, np.diff(offsets), 0)
        return np.concatenate([[0], np.cumsum(lengths)])
    return offsets


class Words:
    """The words `[^\\x20\\x09-\\x0D]+` of a block of texts.

    counts: words of each text; codes: for each word, its place in `distinct` (a binary Arrow array).
    A null text has no words.
    """

    def __init__(self, text: pa.Array, lower: bool = False, cuts: Callable[[np.ndarray], np.ndarray] | None = None):
        text = text.cast(pa.large_string())
        if text.null_count:
            text = text.fill_null("")
        offsets = _offsets(text)
        data = text.buffers()[2]
        raw = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
        offsets = offsets - offsets[0]
        if lower:
            raw = _LOWER[raw]
        inside = ~_SPACE[raw]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        starts = offsets[:-1][np.diff(offsets) > 0]
        first[starts] = inside[starts]
        if cuts is not None:  # bytes at which a word is cut in two
            first |= cuts(raw)
        at = np.flatnonzero(first)
        self.counts = np.diff(np.searchsorted(at, offsets))
        letters = np.concatenate([[0], np.cumsum(inside, dtype=np.int64 if len(raw) >> 31 else np.int32)])
        bounds = np.append(letters[at], letters[-1])
        packed = raw[inside]
        words = pa.Array.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(packed)])
        coded = words.dictionary_encode()
        self.codes = np.asarray(coded.indices)
        self.distinct = coded.dictionary
        self.words, self._packed, self.bounds = words, packed, bounds

    def ends(self) -> np.ndarray:
        """For each text, the place after its last word."""
        return np.cumsum(self.counts)

    def spaced(self) -> np.ndarray:
        """All words end to end, a space after each; word i begins at bounds[i] + i."""
        out = np.full(len(self._packed) + len(self.bounds) - 1, 0x20, np.uint8)
        letter = np.ones(len(out), bool)
        letter[self.bounds[1:].astype(np.int64) + np.arange(len(self.bounds) - 1)] = False
        out[letter] = self._packed
        return out

    def hashes(self) -> np.ndarray:
        """A 64-bit hash for each word."""
        own = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in self.distinct.to_pylist()), dtype=np.uint64, count=len(self.distinct))
        return own[self.codes] if len(own) else np.zeros(0, np.uint64)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers (multiply and shift rounds)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xA0761D6478BD642F)
    x ^= x >> np.uint64(32)
    return x


def gram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit hash of the n words from each place on; len(words) - n + 1 of them, across text borders too."""
    if len(words) < n:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(words) - n + 1, np.uint64)
    for i in range(n):
        out = mix64(out + np.uint64(0x9E3779B97F4A7C15)) if i else out
        out += words[i : len(words) - n + 1 + i]
    return mix64(out)


@lru_cache(maxsize=4)
def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


class Rolling:
    """Hashes of any runs of words, from sums over all words before: two steps a run, however long it is."""

    BASE = 0x9FB21C651E98DF25

    def __init__(self, words: np.ndarray, base: int = BASE):
        room = 1 << max(12, len(words).bit_length())  # the same powers serve texts of about the same length
        self.inverse = _powers(pow(base, -1, 2**64), room)
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.add.accumulate(words * _powers(base, room)[: len(words)])])

    def runs(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The hash of the words from each a to before b."""
        return mix64((self.sums[b] - self.sums[a]) * self.inverse[a] + (b - a).astype(np.uint64))

    def windows(self, n: int) -> np.ndarray:
        """The hash of the n words from each place on, across text borders too."""
        if len(self.sums) <= n:
            return np.zeros(0, np.uint64)
        return mix64((self.sums[n:] - self.sums[:-n]) * self.inverse[: len(self.sums) - n] + np.uint64(n))


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    """A column by name, the first if names clash."""
    return batch.column(batch.schema.get_field_index(name))
