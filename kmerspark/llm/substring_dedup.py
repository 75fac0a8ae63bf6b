"""Substring deduplication by suffix automata of reference shards.

The reference is the passages that repeat, each spelled once, in shards by the anchor that their windows share. A
shard's automaton knows for every substring the least id that holds it; passages stream through it for matching
statistics, and words under a match of the threshold's length that an earlier document holds are removed. Broadcast
automata of all documents would grow with the corpus; a shard is instead built where the passages of its anchor
meet, so no shard is sent anywhere and its size follows the distinct passages of one anchor.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._blocks import read_payload
from ._repeats import NONE_HI, NONE_LO, WINDOW, covered, holders, repeated_windows
from ._text import Words, column

#: Passages of one automaton; a search of more has several, and all its passages stream through each.
SHARD_PASSAGES = 16_384


class SuffixAutomaton:
    """Generalised suffix automaton over sequences of words; each state knows the least and largest id that hold it."""

    def __init__(self):
        self.next: list[dict[bytes, int]] = [{}]
        self.link, self.length = [-1], [0]
        self.lo, self.hi = [NONE_LO], [NONE_HI]

    def add(self, words: list[bytes], lows: list[int], highs: list[int]) -> None:
        """Take up a passage; for each word the least and largest id that hold what ends there."""
        moves, link, length, los, his = self.next, self.link, self.length, self.lo, self.hi
        last = 0
        for w, lo, hi in zip(words, lows, highs, strict=True):
            p, q = last, moves[last].get(w)
            if q is None:  # a new state for the words so far
                last = len(moves)
                moves.append({})
                length.append(length[p] + 1)
                link.append(0)
                los.append(lo)
                his.append(hi)
                while p >= 0 and (q := moves[p].setdefault(w, last)) == last:
                    p = link[p]
                if p < 0:
                    continue
                cur = last
            else:
                cur = None
            if length[p] + 1 < length[q]:  # q's shorter strings get a state of their own
                twin = len(moves)
                moves.append(moves[q].copy())
                length.append(length[p] + 1)
                link.append(link[q])
                los.append(NONE_LO)
                his.append(NONE_HI)
                link[q] = twin
                while p >= 0 and moves[p].get(w) == q:
                    moves[p][w] = twin
                    p = link[p]
                q = twin
            if cur is None:
                last = q
                if lo < los[q]:
                    los[q] = lo
                if hi > his[q]:
                    his[q] = hi
            else:
                link[cur] = q

    def close(self) -> SuffixAutomaton:
        """Hand ids on from longer strings to their suffixes."""
        link, los, his = self.link, self.lo, self.hi
        for v in np.argsort(-np.array(self.length), kind="stable").tolist():
            u = link[v]
            if u > 0:  # the empty string at the root holds nothing of use
                if los[v] < los[u]:
                    los[u] = los[v]
                if his[v] > his[u]:
                    his[u] = his[v]
        return self

    def statistics(self, words: list[bytes], window: int) -> list[tuple[int, int, int]]:
        """For each window of the passage that occurs: its start, and the least and largest id that hold it."""
        moves, link, length, los, his = self.next, self.link, self.length, self.lo, self.hi
        v, n, out = 0, 0, []
        for i, w in enumerate(words, 1):
            q = moves[v].get(w)
            while q is None and v > 0:
                v = link[v]
                n = length[v]
                q = moves[v].get(w)
            if q is not None:
                v, n = q, n + 1
            if n >= window:
                while length[u := link[v]] >= window:
                    v, n = u, length[u]
                out.append((i - window, los[v], his[v]))
        return out


def search_automata(passages: list[list[bytes]], at: list[int], lo: list[int], hi: list[int], window: int, starts: list[int] | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """The least and largest id that hold each window of each passage.

    Passages of one run of words (`starts`) that overlap are taken as one, each window with the ids of its passage.
    """
    sizes = [len(p) - window + 1 for p in passages]
    runs: list[tuple[list[bytes], list[int], list[int], list[tuple[int, int]]]] = []  # words, ids by word, (passage, its place)
    until = None
    for i, (p, x, y) in enumerate(zip(passages, lo, hi, strict=True)):
        own = sizes[i]
        if starts is not None and until is not None and until - window < starts[i] < until:
            words, lows, highs, held = runs[-1]
            shift = starts[i] - (until - len(words))
            words += p[until - starts[i] :]
            lows += [NONE_LO] * (len(words) - len(lows))
            highs += [NONE_HI] * (len(words) - len(highs))
        else:
            words, lows, highs, held, shift = list(p), [NONE_LO] * len(p), [NONE_HI] * len(p), [], 0
            runs.append((words, lows, highs, held))
        lows[shift + window - 1 : shift + window - 1 + own] = [x] * own
        highs[shift + window - 1 : shift + window - 1 + own] = [y] * own
        held.append((i, shift))
        until = starts[i] + len(p) if starts is not None else None
    found = [(np.full(len(r[0]), NONE_LO), np.full(len(r[0]), NONE_HI)) for r in runs]
    for a in range(0, len(runs), SHARD_PASSAGES):
        shard = SuffixAutomaton()
        for words, lows, highs, _ in runs[a : a + SHARD_PASSAGES]:
            shard.add(words, lows, highs)
        shard.close()
        for (words, *_), (los, his) in zip(runs, found, strict=True):
            if hits := shard.statistics(words, window):
                start, low, high = np.array(hits).T
                los[start], his[start] = np.minimum(los[start], low), np.maximum(his[start], high)
    out: list = [None] * len(passages)
    for (_, _, _, held), (los, his) in zip(runs, found, strict=True):
        for i, shift in held:
            out[i] = los[shift : shift + sizes[i]], his[shift : shift + sizes[i]]
    return out


def substring_dedup(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept_text and kept_sha256 of every row.

    Removed is each word under a window of `window` words that also starts in a document of smaller id; windows are
    judged on the input. Kept words are joined by one space. A null or empty text has no words. Rows of equal id
    don't count against each other; a row without an id keeps all its words and takes none from others. An empty
    table gives an empty result.
    """

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, hits in zip(column(batch, "payload"), column(batch, "hits"), strict=True):
                own = read_payload(raw.as_buffer())
                ids, words = column(own, "id"), Words(column(own, "text"))
                ends, counts = words.ends(), words.counts
                lo = holders(hits, len(words.codes))[0]
                gone = covered(lo < np.repeat(np.asarray(ids.fill_null(NONE_HI)), counts), window)
                sizes = np.diff(words.bounds.astype(np.int64)) + 1
                text = memoryview(words.spaced()[np.repeat(~gone, sizes)])
                until = np.concatenate([[0], np.cumsum(np.where(gone, 0, sizes))])
                n_gone = np.concatenate([[0], np.cumsum(gone)])
                kept = [bytes(text[a : max(a, b - 1)]) for a, b in zip(until[ends - counts].tolist(), until[ends].tolist(), strict=True)]
                digest = [hashlib.sha256(k).hexdigest() for k in kept]
                yield pa.RecordBatch.from_arrays([ids, pa.array(counts, pa.int64()), pa.array(n_gone[ends] - n_gone[ends - counts], pa.int64()), pa.array(kept, pa.binary()).cast(pa.string()), pa.array(digest, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_text", "kept_sha256"])

    slim = docs.select(docs[id_col].cast("long").alias("id"), F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text"))
    blocks, hits = repeated_windows(slim, search_automata, window)
    return blocks.with_rows(hits, "left").mapInArrow(apply, "doc_id long, n_words long, n_removed long, kept_text string, kept_sha256 string")
