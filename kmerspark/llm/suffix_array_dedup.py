"""Repeated passages by sparse suffix arrays.

Only suffixes that begin at a content-selected anchor (a window's minimiser) are kept. The suffixes of a task's
anchors are sorted by the words that follow, and once more by the words before the anchor, read backwards. In each
order neighbours are compared. Two windows at the same distance from their anchors are equal just if no neighbours
between them part before the window's end on the right, nor before its start on the left: so the common lengths of
neighbours alone say which windows of the whole array are the same, and the ids of their holders are joined.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._blocks import read_payload
from ._repeats import NONE_LO, WINDOW, Block, covered, holders, repeated_windows
from ._text import column


def _common(a: list[bytes], b: list[bytes]) -> int:
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


def _order(parts: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray]:
    """The order of lists of words, and how many leading words each shares with the one before."""
    order = sorted(range(len(parts)), key=parts.__getitem__)
    common = [_common(parts[i], parts[j]) for i, j in zip(order[:-1], order[1:], strict=True)]
    return np.array(order), np.array([0, *common])


def search_suffixes(passages: list[list[bytes]], at: list[int], lo: list[int], hi: list[int], window: int, starts: list[int] | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """The least and largest id that hold each window of each passage."""
    m = len(passages)
    begin, size = np.array(at), np.array([len(p) for p in passages])
    ahead, right = _order([p[a:] for p, a in zip(passages, at, strict=True)])
    back, left = _order([p[:a][::-1] for p, a in zip(passages, at, strict=True)])
    far = np.arange(begin.max() + 1)  # words of a window before its anchor
    ends, starts = np.empty((m, len(far)), np.int64), np.empty((m, len(far)), np.int64)
    ends[ahead] = np.cumsum(right[:, None] < window - far[None, :], axis=0)  # windows of one class agree from the anchor on
    starts[back] = np.cumsum(left[:, None] < far[None, :], axis=0)  # and before it
    which, l = np.nonzero((begin[:, None] >= far) & (size[:, None] - begin[:, None] >= window - far))
    classes = (l * (m + 1) + ends[which, l]) * (m + 1) + starts[which, l]
    order = np.argsort(classes, kind="stable")
    edge = np.flatnonzero(np.concatenate([[True], np.diff(classes[order]) != 0]))
    own = np.repeat(np.arange(len(edge)), np.diff(np.append(edge, len(order))))
    low, high = np.empty(len(order), np.int64), np.empty(len(order), np.int64)
    low[order] = np.minimum.reduceat(np.array(lo)[which[order]], edge)[own]
    high[order] = np.maximum.reduceat(np.array(hi)[which[order]], edge)[own]
    place = np.lexsort((-l, which))  # by passage, and by start
    cuts = np.cumsum(size - window + 1)[:-1]
    return list(zip(np.split(low[place], cuts), np.split(high[place], cuts), strict=True))


def repeated_passages(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", window: int = WINDOW) -> DataFrame:
    """doc_id, start, length, first_doc, n_words: the maximal passages of at least `window` words whose every window
    another document holds too; start and length in words.

    first_doc is the least id that holds a window of the passage: the passage's original stands where it is the
    row's own id, all others are copies. A document without such a passage has no row; so do null and empty texts
    and rows without an id. Rows of equal id don't count against each other, but equal rows are each reported. An
    empty table gives an empty result.
    """

    def spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, hits in zip(column(batch, "payload"), column(batch, "hits"), strict=True):
                block = Block(read_payload(raw.as_buffer()), window)
                n = len(block.hashed)
                lo, hi = holders(hits, n)
                doc = np.repeat(np.arange(len(block.counts)), block.counts)
                own = np.asarray(block.ids.fill_null(0))[doc]
                marked = (lo < own) | (hi > own)
                inside = covered(marked, window)
                new = np.concatenate([[True], doc[1:] != doc[:-1]])
                first = np.flatnonzero(inside & (new | ~np.concatenate([[False], inside[:-1]])))
                last = np.flatnonzero(inside & (np.append(new[1:], True) | ~np.append(inside[1:], False)))
                least = np.minimum.reduceat(np.where(marked, lo, NONE_LO), np.stack([first, last + 1], axis=1).ravel()[: 2 * len(first) - 1 if len(last) and last[-1] + 1 == n else None])[::2] if len(first) else first
                d = doc[first]
                columns = (own[first], first - (block.ends - block.counts)[d], last + 1 - first, least, block.counts[d])
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc_id", "start", "length", "first_doc", "n_words"])

    slim = docs.select(docs[id_col].cast("long").alias("id"), F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text"))
    blocks, hits = repeated_windows(slim, search_suffixes, window)
    return blocks.with_rows(hits).mapInArrow(spans, "doc_id long, start long, length long, first_doc long, n_words long")
