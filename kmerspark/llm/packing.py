"""Harmonic packing of tokenised documents into fixed-length sequences.

Residual lengths fall into the reciprocal-capacity classes (C/(j+1), C/j]; a bin of class j takes exactly j pieces
of its class, so no worker needs to know another's bins. What a bin then lacks is filled with slices of the
documents below the last class, so sequences are full; the few ids left at the end of a block form sequences whose
length is a power of two, which need no padding.

There is no shuffle: each task packs its own blocks of rows in bounded memory, and a lost task is run again with
the same result.
"""

from __future__ import annotations

import os
import re
import zlib
from array import array
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from ._text import Words, column, text_blocks

CAPACITY = 2048
CLASSES = 8
END_ID = 1
#: Word encodings after which a worker drops those not met again since the last time; it holds two such sets.
CACHE_WORDS = 300_000
#: Bytes of text that are packed together.
BLOCK_BYTES = 8 << 20

SCHEMA = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"


def pack_lengths(lengths: np.ndarray, capacity: int = CAPACITY, classes: int = CLASSES) -> dict[str, np.ndarray]:
    """Pieces (doc, start, length, sequence, offset) that hold each unit of the documents exactly once.

    Every sequence is full, or its length is a power of two. Documents of length 0 get no piece.
    """
    lengths = np.asarray(lengths, dtype=np.int64)
    whole, rest = np.divmod(lengths, capacity)
    head = whole * capacity
    docs = np.repeat(np.arange(len(lengths)), whole)
    nth = np.arange(len(docs)) - np.repeat(np.cumsum(whole) - whole, whole)
    parts = [(docs, nth * capacity, np.full(len(docs), capacity), np.arange(len(docs)), np.zeros(len(docs), np.int64))]
    used = len(docs)

    live = np.flatnonzero(rest)
    kind = capacity // rest[live]
    filler, bins = [live[kind > classes]], []
    for j in range(1, classes + 1):
        own = live[kind == j]
        full = len(own) // j * j
        bins.append(own[:full].reshape(-1, j))
        filler.append(own[full:])
    gaps = [capacity - rest[b].sum(axis=1) for b in bins]
    every = np.concatenate(gaps)
    keep = np.ones(len(every), dtype=bool)
    short = int(every.sum()) - sum(int(rest[f].sum()) for f in filler)
    if short > 0:  # each bin given up lowers what is lacking by the capacity
        keep[np.argsort(-every, kind="stable")[: -(-short // capacity)]] = False
    kept = np.split(keep, np.cumsum([len(b) for b in bins])[:-1])

    open_at, open_size = [], []
    for b, gap, stays in zip(bins, gaps, kept, strict=True):
        filler.append(b[~stays].ravel())
        b, gap = b[stays], gap[stays]
        size = rest[b]
        sequence = used + np.arange(len(b))
        parts.append((b.ravel(), head[b.ravel()], size.ravel(), np.repeat(sequence, b.shape[1]), (np.cumsum(size, axis=1) - size).ravel()))
        open_at.append(sequence)
        open_size.append(gap)
        used += len(b)

    # One axis holds the filler documents end to end and, below them, the free slots end to end.
    filler = np.concatenate(filler)
    filler_end = np.cumsum(rest[filler])
    total = int(filler_end[-1]) if len(filler) else 0
    slot_at, slot_size = np.concatenate(open_at), np.concatenate(open_size)
    slot_base = capacity - slot_size
    left = total - int(slot_size.sum())
    new = [capacity] * (left // capacity) + [1 << bit for bit in range(capacity.bit_length(), -1, -1) if left % capacity >> bit & 1]
    slot_at = np.concatenate([slot_at, used + np.arange(len(new))])
    slot_size = np.concatenate([slot_size, np.array(new, np.int64)])
    slot_base = np.concatenate([slot_base, np.zeros(len(new), np.int64)])
    slot_end = np.cumsum(slot_size)
    ends = np.union1d(filler_end, slot_end)
    ends = ends[ends > 0]
    begins = np.concatenate([[0], ends[:-1]]).astype(np.int64)[: len(ends)]
    doc, slot = np.searchsorted(filler_end, begins, side="right"), np.searchsorted(slot_end, begins, side="right")
    if len(ends):
        d = filler[doc]
        parts.append((d, head[d] + begins - (filler_end[doc] - rest[d]), ends - begins, slot_at[slot], slot_base[slot] + begins - (slot_end[slot] - slot_size[slot])))
    names = ("doc", "start", "length", "sequence", "offset")
    return {n: np.concatenate([p[i] for p in parts]).astype(np.int64) for i, n in enumerate(names)}


@lru_cache(maxsize=2)
def _encoder(path: str) -> Callable[[pa.Array], tuple[np.ndarray, np.ndarray]]:
    """Ids of distinct words: one array of all ids, and the length of each word's run."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    known: dict[bytes, bytes] = {}
    older: dict[bytes, bytes] = {}

    def encode(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        nonlocal known, older
        words = words.to_pylist()
        if len(known) > CACHE_WORDS:  # what was not met again since the last turn goes
            known, older = {}, known
        fresh = []
        for w in words:
            if w not in known:
                if (run := older.get(w)) is None:
                    fresh.append(w)
                else:
                    known[w] = run
        for i in range(0, len(fresh), 20_000):
            part = fresh[i : i + 20_000]
            found = tokenizer.encode_batch_fast([w.decode() for w in part], add_special_tokens=False)
            known.update((w, array("I", e.ids).tobytes()) for w, e in zip(part, found, strict=True))
        runs = [known[w] for w in words]
        return np.frombuffer(b"".join(runs), dtype="<u4"), np.fromiter(map(len, runs), np.int64, len(runs)) // 4

    return encode


#: What the tokenizer reads with an eye to what stands around: its own marks, and the capital sigma.
MARK = re.compile(rb"<\|(start|end)oftext\|>|\xce\xa3", re.IGNORECASE)
#: 1: ASCII letter, 2: ASCII sign, 3: ASCII digit, 0: anything else.
_KIND = np.zeros(256, np.uint8)
_KIND[0x21:0x7F] = 2
_KIND[[*range(65, 91), *range(97, 123)]] = 1
_KIND[48:58] = 3
#: By the kinds of two neighbours: a letter ends before a sign or digit, and a digit is always alone.
_CUT = np.zeros(16, dtype=bool)
_CUT[[4 + 2, 4 + 3, 8 + 3, 12 + 1, 12 + 2]] = True


def _cuts(raw: np.ndarray) -> np.ndarray:
    """Where the tokenizer splits a word whatever stands around; in ASCII, so that no cut parts what its normaliser joins."""
    out = np.zeros(len(raw), dtype=bool)
    kind = _KIND[raw]
    out[1:] = _CUT[4 * kind[:-1] + kind[1:]]
    return out


def encode_block(text: pa.Array, path: str, end_id: int = END_ID) -> tuple[np.ndarray, np.ndarray]:
    """All ids of a block, each document's followed by `end_id`, and the number of ids of each document.

    The tokenizer drops white space and case, and no token spans white space or a cut, so a text's ids are those of
    its pieces in turn; each distinct piece is encoded once. A block with a MARK is not cut.
    """
    data = text.cast(pa.large_string()).buffers()[2]
    plain = data is None or not MARK.search(memoryview(data))
    words = Words(text, lower=plain, cuts=_cuts if plain else None)
    pool, sizes = _encoder(path)(words.distinct)
    begins = np.cumsum(sizes) - sizes
    per_word = sizes[words.codes]
    ends = np.cumsum(per_word)
    at = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(begins[words.codes] - (ends - per_word), per_word)
    flat = pool[at]
    doc_end = np.concatenate([[0], ends])[words.ends()] if len(ends) else np.zeros(len(text), np.int64)
    lengths = np.diff(doc_end, prepend=0) + 1
    ids = np.empty(len(flat) + len(text), dtype="<u4")
    last = np.zeros(len(ids), dtype=bool)
    last[np.cumsum(lengths) - 1] = True
    ids[last], ids[~last] = end_id, flat
    return ids, lengths


def _pack_partition(path: str, text_col: str, id_col: str, capacity: int, classes: int, end_id: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = TaskContext.get().partitionId() << 36
        for batch in batches:
            for block in text_blocks(batch, text_col, BLOCK_BYTES):
                ids, lengths = encode_block(column(block, text_col), path, end_id)
                p = pack_lengths(lengths, capacity, classes)
                first = np.cumsum(lengths) - lengths
                a = first[p["doc"]] + p["start"]
                raw = memoryview(ids).cast("B")
                crc = np.fromiter((zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(a.tolist(), (a + p["length"]).tolist(), strict=True)), np.int64, len(a))
                doc = pa.array(p["doc"])
                cols = [column(block, id_col).cast(pa.int64()).take(doc), p["start"], p["length"], crc, lengths[p["doc"]], base + p["sequence"], p["offset"]]
                base += int(p["sequence"].max()) + 1
                yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, pa.int64()) for c in cols], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return run


def harmonic_packing(docs: DataFrame, tokenizer: str, text_col: str = "text", id_col: str = "doc_id", capacity: int = CAPACITY, classes: int = CLASSES, end_id: int = END_ID) -> DataFrame:
    """Pack all documents into sequences of at most `capacity` ids; one row per piece.

    A null or empty text is the single id `end_id`. A null id stays null. Repeated rows are packed as often as they
    occur. A document longer than a sequence is cut. An empty table gives an empty result. Extra columns are ignored.
    """
    picked = docs.select(docs[id_col].cast("long").alias(id_col), docs[text_col].cast("string").alias(text_col))
    return picked.mapInArrow(_pack_partition(tokenizer, text_col, id_col, capacity, classes, end_id), SCHEMA)
