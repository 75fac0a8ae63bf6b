"""Passages that stand word for word in several documents: the plan that the substring operators share.

1. All grams of GRAM words are counted by cell of a hash space that grows with the input (`_blocks`); each block
   learns which of its grams occur elsewhere.
2. A window (`window` words) can only repeat if all its grams do. The windows that pass are cut into runs with the
   same minimiser (least gram hash of the window), which is the same wherever the window stands. A run is a slice of
   words around its anchor; equal slices of a block are one.
3. Slices with the same anchor meet; an operator finds, for each window, the least and the largest id that hold it.
   An anchor with one distinct slice has nobody to meet, and is searched where its block is, beside its neighbours.
   An anchor with many distinct slices is not searched in one task: its windows are cut once more, by their second
   least gram hash, and so on; equal windows still meet.
4. What was found goes back to the blocks, where documents are read again.

Hot passages cost one slice a block, and their holders are reduced before each shuffle.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._blocks import Blocks, by_block, read_payload, repeated
from ._state import stored
from ._text import Rolling, Words, column, mix64

WINDOW = 50
#: Distinct slices of one anchor that are searched together, and how often a larger group is cut again.
HOT_SLICES, LEVELS = 2_048, 4
#: Slices that a task searches at a time, whole anchors.
CHUNK_SLICES = 4_096
NONE_LO, NONE_HI = np.iinfo(np.int64).max, np.iinfo(np.int64).min

#: For slices of whole anchors: words of each, place of the anchor in each, least and largest id of their holders,
#: the window's length, and where each begins if they are all from one run of words, in order; gives the least and
#: largest id that hold each window of each slice.
Search = Callable[[list[list[bytes]], list[int], list[int], list[int], int, list[int] | None], list[tuple[np.ndarray, np.ndarray]]]


class Block:
    """The words of a block's documents and the hashes of their grams of half a window."""

    def __init__(self, batch: pa.RecordBatch, window: int):
        self.ids = column(batch, "id")
        self.words = Words(column(batch, "text"))
        self.ends, self.counts = self.words.ends(), self.words.counts
        self.hashed = self.words.hashes()
        self.rolling = Rolling(self.hashed)
        self.gram = window // 2
        self.grams = self.rolling.windows(self.gram)
        self.left = np.repeat(self.ends, self.counts) - np.arange(len(self.hashed))  # words to the end of the text
        long = np.repeat(self.counts >= window, self.counts)
        self.at = np.flatnonzero((self.left >= self.gram) & long)

    def items(self) -> np.ndarray:
        return self.grams[self.at]


def first_least(values: np.ndarray, width: int) -> np.ndarray:
    """For each window of `width` values, the place of the first least one."""
    at = np.arange(len(values), dtype=np.int32)
    have = 1
    while have < width:
        step = min(have, width - have)
        later = values[step:] < values[:-step]
        values, at = np.where(later, values[step:], values[:-step]), np.where(later, at[step:], at[:-step])
        have += step
    return at


def runs_of(block: Block, hit: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last window of each run that may repeat, and the place of its anchor."""
    known = np.zeros(len(block.hashed) + 1, bool)
    known[block.at] = hit
    width = window - block.gram + 1
    bad = np.concatenate([[0], np.cumsum(~known[: len(block.grams)], dtype=np.int32)])
    good = bad[width:] == bad[:-width]
    owned = np.repeat(np.asarray(block.ids.is_valid()), block.counts)
    good &= (block.left[: len(good)] >= window) & owned[: len(good)]
    start = np.flatnonzero(good)
    if not len(start):
        return start, start, start
    anchor = first_least(block.grams, width)
    new = np.concatenate([[True], (np.diff(start) > 1) | (np.diff(anchor[start]) != 0)])
    first, last = start[new], start[np.append(np.flatnonzero(new)[1:], len(start)) - 1]
    return first, last, anchor[first].astype(np.int64)


FOUND = "k1 long, k2 long, block long, start int, n int, id long, anchor long, at int, lo long, hi long"


def _slices(window: int, space):
    """Two kinds of rows: where slices stand (key, block, start, n, id), and a block's distinct slices, each where it
    stands first (key, block, start, n, anchor, at, lo, hi)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, raw, parts in zip(column(batch, "block").to_pylist(), column(batch, "payload"), column(batch, "parts"), strict=True):
                block = Block(read_payload(raw.as_buffer()), window)
                first, last, anchor = runs_of(block, repeated(space, block.items(), parts.as_py()), window)
                if not len(first):
                    continue
                end = last + window
                k1, k2 = block.rolling.runs(first, end), Rolling(mix64(block.hashed ^ np.uint64(0x2545F4914F6CDD1D))).runs(first, end)
                own = np.asarray(block.ids.take(pa.array(np.searchsorted(block.ends, first, side="right"))))
                order = np.lexsort((own, k2, k1))
                new = np.concatenate([[True], (np.diff(k1[order]) != 0) | (np.diff(k2[order]) != 0)])
                head = order[new]  # of each distinct slice, the place with the least id
                tail = order[np.append(np.flatnonzero(new)[1:], len(order)) - 1]
                m, k = len(first), len(head)
                twice = lambda x, t: pa.array(np.concatenate([x, x[head]]), t)
                long, short = pa.int64(), pa.int32()
                yield pa.RecordBatch.from_arrays([
                    twice(k1.view(np.int64), long), twice(k2.view(np.int64), long), pa.array(np.full(m + k, name), long), twice(first, short), twice(last - first + 1, short),
                    pa.concat_arrays([pa.array(own, long), pa.nulls(k, long)]),
                    *(pa.concat_arrays([pa.nulls(m, t), pa.array(x, t)]) for x, t in ((block.grams[anchor[head]].view(np.int64), long), ((anchor - first)[head], short), (own[head], long), (own[tail], long))),
                ], names=[x.split()[0] for x in FOUND.split(", ")])

    return run


SLICES = "k1 long, k2 long, anchor long, at int, slice string, lo long, hi long"
FOUND_IDS = "k1 long, k2 long, los array<long>, his array<long>"


def _ids(k1: pa.Array, k2: pa.Array, found: list[tuple[np.ndarray, np.ndarray]]) -> list[pa.Array]:
    """The columns of FOUND_IDS; ids that are the same in all windows of a slice stand once."""
    kind = pa.list_(pa.int64())
    out = []
    for side in (0, 1):
        short = [x[:1] if (x == x[0]).all() else x for x in (f[side] for f in found)]
        sizes = np.concatenate([[0], np.cumsum([len(x) for x in short])]).astype(np.int32)
        out.append(pa.ListArray.from_arrays(sizes, pa.array(np.concatenate(short) if short else [], pa.int64())).cast(kind))
    return [k1, k2, *out]


def _spell(find: Search, window: int):
    """Two kinds of rows, of the slices that a block was chosen to give: slices that others meet, spelled out, and what
    was found of those that are alone with their anchor."""
    names = [x.split()[0] for x in f"{SLICES}, los, his".split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, wanted in zip(column(batch, "payload"), column(batch, "wanted"), strict=True):
                words = Words(column(read_payload(raw.as_buffer()), "text"))
                begin = words.bounds.astype(np.int64) + np.arange(len(words.bounds))
                rows = pa.RecordBatch.from_struct_array(wanted.values)
                rows = rows.take(pa.array(np.argsort(np.asarray(rows.column(rows.schema.get_field_index("start"))), kind="stable")))
                alone = column(rows, "n_slices").to_numpy() == 1
                spaced = words.spaced()
                met = rows.filter(pa.array(~alone))
                start, n = (np.asarray(column(met, c)) for c in ("start", "n"))
                a, b = begin[start], begin[start + n + window - 1] - 1
                sizes = b - a
                text = spaced[np.arange(sizes.sum()) + np.repeat(a - (np.cumsum(sizes) - sizes), sizes)]
                spelled = pa.Array.from_buffers(pa.string(), len(a), [None, pa.py_buffer(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.py_buffer(text)])
                none = pa.nulls(len(a), pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([*(spelled if c == "slice" else column(met, c) for c in names[:7]), none, none], names=names)
                own, whole = rows.filter(pa.array(alone)), memoryview(spaced)
                for at in range(0, own.num_rows, CHUNK_SLICES):
                    part = own.slice(at, CHUNK_SLICES)
                    start, n = (np.asarray(column(part, c)) for c in ("start", "n"))
                    passages = [bytes(whole[x:y]).split(b" ") for x, y in zip(begin[start].tolist(), (begin[start + n + window - 1] - 1).tolist(), strict=True)]
                    found = find(passages, *(column(part, c).to_pylist() for c in ("at", "lo", "hi")), window, start.tolist())
                    k1, k2, los, his = _ids(column(part, "k1"), column(part, "k2"), found)
                    yield pa.RecordBatch.from_arrays([k1, k2, *(pa.nulls(part.num_rows, t) for t in (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64())), los, his], names=names)

    return run


def _search(find: Search, window: int):
    """Rows are sorted by anchor; whole anchors are searched together, about CHUNK_SLICES slices at a time."""
    names = ("k1", "k2", "at", "slice", "lo", "hi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        anchor, held = None, []

        def flush() -> pa.RecordBatch:
            k1, k2, at, text, lo, hi = (list(x) for x in zip(*held, strict=True))
            found = find([t.encode().split(b" ") for t in text], at, lo, hi, window, None)
            return pa.RecordBatch.from_arrays(_ids(pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), found), names=["k1", "k2", "los", "his"])

        for batch in batches:
            for own, *row in zip(*(column(batch, c).to_pylist() for c in ("anchor", *names)), strict=True):
                if own != anchor and len(held) >= CHUNK_SLICES:
                    yield flush()
                    held = []
                anchor = own
                held.append(row)
        if held:
            yield flush()

    return run


PART = "k1 long, k2 long, offset int, n int, s1 long, s2 long, anchor long, at int, slice string, lo long, hi long"


def _refine(window: int, level: int):
    """Cut slices by the next least gram hash of their windows: where the parts stand (key, offset, n, part), and the parts."""
    n = window // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            places, parts = [], {}
            for k1, k2, anchor, at, text, lo, hi in zip(*(column(batch, c).to_pylist() for c in ("k1", "k2", "anchor", "at", "slice", "lo", "hi")), strict=True):
                spelled = text.split(" ")
                hashed = Words(pa.array([text])).hashes()
                grams = Rolling(hashed).windows(n)
                inside = np.lib.stride_tricks.sliding_window_view(grams, window - n + 1)
                where = np.argsort(inside, axis=1, kind="stable")[:, level] + np.arange(len(inside))
                edge = np.flatnonzero(np.concatenate([[True], np.diff(where) != 0, [True]]))
                first, last = edge[:-1], edge[1:] - 1
                runs = (Rolling(x).runs(first, last + window).view(np.int64).tolist() for x in (hashed, mix64(hashed ^ np.uint64(0x2545F4914F6CDD1D))))
                keys = mix64(grams[where[first]] ^ np.uint64(anchor % 2**64)).view(np.int64).tolist()
                for f, e, s1, s2, key in zip(first.tolist(), last.tolist(), *runs, keys, strict=True):
                    places.append((k1, k2, f, e - f + 1, s1, s2))
                    held = parts.setdefault((s1, s2, key), [at - f, " ".join(spelled[f : e + window]), lo, hi])
                    held[2], held[3] = min(held[2], lo), max(held[3], hi)
            rows = [(*p, None, None, None, None, None) for p in places] + [(None, None, None, None, *k, *v) for k, v in parts.items()]
            kinds = [{"long": pa.int64(), "int": pa.int32(), "string": pa.string()}[x.split()[1]] for x in PART.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=[x.split()[0] for x in PART.split(", ")])

    return run


def _found(slices: DataFrame, hot: DataFrame, find: Search, window: int, level: int = 1) -> DataFrame:
    """k1, k2, los, his of distinct slices (key, anchor, at, slice, lo, hi); `hot` has the anchors of too many."""
    some = level <= LEVELS and not hot.isEmpty()
    cold = slices.join(hot, "anchor", "left_anti") if some else slices
    searched = cold.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_search(find, window), FOUND_IDS)
    if not some:
        return searched
    cut = stored(slices.join(hot, "anchor", "left_semi").mapInArrow(_refine(window, level), PART))
    parts = cut.filter("slice IS NOT NULL").groupBy(F.col("s1").alias("k1"), F.col("s2").alias("k2"), "anchor").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.first("slice").alias("slice"), F.first("at").alias("at"))
    parts = stored(parts)
    more = stored(parts.groupBy("anchor").agg(F.count("*").alias("n")).filter(F.col("n") > HOT_SLICES).select("anchor"))
    own = _found(parts, more, find, window, level + 1).select(F.col("k1").alias("s1"), F.col("k2").alias("s2"), "los", "his")
    rows = cut.filter("slice IS NULL").select("k1", "k2", "offset", "n", "s1", "s2").join(own, ["s1", "s2"])
    rows = rows.groupBy("k1", "k2").agg(F.sort_array(F.collect_list(F.struct("offset", "n", "los", "his"))).alias("x"))
    whole = lambda c: F.flatten(F.transform("x", lambda x: F.when(F.size(x[c]) == 1, F.array_repeat(x[c][0], x["n"])).otherwise(x[c]))).alias(c)
    return searched.unionByName(rows.select("k1", "k2", whole("los"), whole("his")))


def repeated_windows(docs: DataFrame, find: Search, window: int = WINDOW) -> tuple[Blocks, DataFrame]:
    """The blocks of `docs` (id, text), and for each block with windows that another id holds too its hits.

    A hit (start, n, los, his) is a run of n windows from word `start` of the block on, with the least and the
    largest id that hold each; a single entry stands for all windows of the run.
    """
    blocks = Blocks(docs)
    answers = blocks.counted(lambda batch: Block(batch, window).items())
    found = stored(blocks.with_rows(by_block(answers)).mapInArrow(_slices(window, blocks.space), FOUND))
    key = ["k1", "k2"]
    held = found.filter("id IS NULL").groupBy(*key, "anchor").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.min(F.struct("block", "start", "n", "at")).alias("r"))
    held = stored(held.select(*key, "anchor", "lo", "hi", "r.block", "r.start", "r.n", "r.at"))
    several = stored(held.groupBy("anchor").agg(F.count("*").alias("n"), F.min("lo").alias("least"), F.max("hi").alias("most")).filter("least < most").select("anchor", F.col("n").alias("n_slices")))
    wanted = held.join(several, "anchor").groupBy("block").agg(F.collect_list(F.struct(*key, "anchor", "at", "lo", "hi", "start", "n", "n_slices")).alias("wanted"))
    spelled = stored(blocks.with_rows(wanted).mapInArrow(_spell(find, window), f"{SLICES}, los array<long>, his array<long>"))
    slices = spelled.filter("slice IS NOT NULL").drop("los", "his")
    alone = spelled.filter("slice IS NULL").select(*key, "los", "his")
    results = alone.unionByName(_found(slices, several.filter(F.col("n_slices") > HOT_SLICES).select("anchor"), find, window))
    places = found.filter("id IS NOT NULL").select(*key, "block", "id", "start", "n")
    hits = places.join(results, key).filter(F.exists("los", lambda x: x < F.col("id")) | F.exists("his", lambda x: x > F.col("id")))
    return blocks, hits.groupBy("block").agg(F.collect_list(F.struct("start", "n", "los", "his")).alias("hits"))


def holders(hits: pa.ListScalar, n_words: int) -> tuple[np.ndarray, np.ndarray]:
    """The least and the largest id that hold the window from each word of a block on; none where nothing was found."""
    lo, hi = np.full(n_words, NONE_LO), np.full(n_words, NONE_HI)
    if hits.values is not None and len(hits.values):
        start, n = (np.asarray(hits.values.field(c)).astype(np.int64) for c in ("start", "n"))
        at = np.arange(n.sum()) + np.repeat(start - (np.cumsum(n) - n), n)
        for out, name in ((lo, "los"), (hi, "his")):
            lists = hits.values.field(name)
            sizes = np.asarray(pc.list_value_length(lists))
            out[at] = np.repeat(np.asarray(lists.flatten()), np.repeat(np.where(sizes == n, 1, n), sizes))
    return lo, hi


def covered(marked: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Words that a marked window covers, given for each word whether its window is marked."""
    n = np.concatenate([[0], np.cumsum(marked)])
    return n[1:] > n[np.maximum(np.arange(len(marked)) + 1 - window, 0)]
