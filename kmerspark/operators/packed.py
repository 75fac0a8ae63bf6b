"""All words of reads with the counts of a sketch that no task can hold: words in parts, counters in ranges.

1. Words are mixed by a multiplication that can be undone, so that parts are even, and sent to their part as gaps of
   sorted numbers. A part is a row: its distinct words and their counts, in some two bytes a word. Bytes are squeezed, since most gaps and counts are small.
2. Table by table, a part sends the sorted cells of its words to the ranges of the table. A range adds them up and
   answers with the counter of each; the part makes its cells again, in the same order, and keeps the least.

Parts follow the input and ranges the tables, so no task holds more than one of either. Nothing is broadcast.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.dna import windows_of
from ..plans.sizing import size_for_fpr
from ..sources.simulate import draw
from .kmers import as_signed, read_blocks
from .sketch import BLOCK, SketchSpec
from .store import discard, shared_path, shuffles_released, stored

#: Bytes of input for each part, and parts at most.
PART_BYTES, MOST_PARTS = 1 << 20, 1 << 15
#: Beyond these bytes of input, words are dealt to their parts in so many passes over the reads, to hold less at a time.
ONE_PASS_BYTES, PASSES = 256 << 20, 3
#: Counters of a range.
RANGE = 1 << 22
FACTOR = 0x9E3779B97F4A7C15
UNDO = pow(FACTOR, -1, 2**64)


def mixed(codes: np.ndarray, bits: int, factor: int = FACTOR) -> np.ndarray:
    return codes * np.uint64(factor) & np.uint64(2**bits - 1)


def squeeze(raw: bytes) -> bytes:
    return len(raw).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True)


def expand(raw: bytes) -> bytes:
    return pa.decompress(raw[8:], int.from_bytes(raw[:8], "little"), "zstd", asbytes=True)


def encode_sorted(values: np.ndarray) -> bytes:
    """Ascending numbers as gaps, their bytes apart by rank."""
    gaps = np.diff(values, prepend=np.uint64(0))
    width = max(1, (int(gaps.max()).bit_length() + 7) // 8)
    return squeeze(bytes([width]) + b"".join((gaps >> np.uint64(8 * i)).astype(np.uint8).tobytes() for i in range(width)))


def decode_sorted(raw: bytes) -> np.ndarray:
    raw = expand(raw)
    planes = np.frombuffer(raw, np.uint8, offset=1).reshape(raw[0], -1)
    gaps = planes[0].astype(np.uint64)
    for i in range(1, raw[0]):
        gaps |= planes[i].astype(np.uint64) << np.uint64(8 * i)
    return np.cumsum(gaps, dtype=np.uint64)


def encode_counts(cnt: np.ndarray) -> bytes:
    """A byte a count, and eight more for those from 255 on."""
    size = cnt.astype(np.int64).view(np.uint64)  # counts with END may have run over
    return squeeze(np.minimum(size, np.uint64(255)).astype(np.uint8).tobytes() + cnt[size >= 255].astype("<i8").tobytes())


def decode_counts(raw: bytes, n: int) -> np.ndarray:
    raw = expand(raw)
    out = np.frombuffer(raw, np.uint8, n).astype(np.int64)
    out[out == 255] = np.frombuffer(raw, "<i8", offset=n)
    return out


ROWS = "part int, n int, words binary, counts binary"


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "tinyint": pa.int8()}
    columns = [c.split() for c in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[t]) for i, (_, t) in enumerate(columns)], names=[c for c, _ in columns])


def _cut(values: np.ndarray, size: int) -> Iterator[tuple[int, int, int]]:
    """(number, from, to) of the runs of ascending values within the same multiple of size."""
    if len(values):
        number = values // np.uint64(size)
        edge = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]])).tolist()
        yield from zip(number[edge].tolist(), edge, [*edge[1:], len(values)], strict=True)


def layout(reads: DataFrame, k: int) -> tuple[int, int, int]:
    """Bits of a word, bits that tell its part, and words of a part's range; parts follow the bytes that the engine expects."""
    plan = reads._jdf.queryExecution().optimizedPlan()
    leaves = plan.collectLeaves()
    sizes = [*(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())), int(str(plan.stats().sizeInBytes()))]
    known = [x for x in sizes if x < 2**56]  # beyond it is the engine's stand-in for a size that it can't tell
    partitions = int(reads.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n_bytes = max(sum(known[:-1]) if len(known) > 1 else 0, known[-1]) if len(known) == len(sizes) else 4 * partitions * PART_BYTES
    bits = 2 * k
    part_bits = min(bits, max(1, (min(MOST_PARTS, max(partitions, -(-n_bytes // PART_BYTES))) - 1).bit_length()))
    return bits, part_bits, 2 ** (bits - part_bits)


def packed_words(codes: np.ndarray, cnt: np.ndarray, size: int) -> Iterator[tuple]:
    """ROWS of distinct mixed words in ascending order, cut by part."""
    for p, a, b in _cut(codes, size):
        yield p, b - a, encode_sorted(codes[a:b] - np.uint64(p * size)), encode_counts(cnt[a:b])


def added(codes: np.ndarray, cnt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct words in ascending order and the sums of their counts."""
    if not len(codes):
        return codes, cnt
    order = np.argsort(codes)
    codes, cnt = codes[order], cnt[order]
    start = np.flatnonzero(np.concatenate([[True], codes[1:] != codes[:-1]]))
    return codes[start], np.add.reduceat(cnt, start)


def merged(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """The words of all rows of a part, without its offset, and their counts."""
    own = np.concatenate([decode_sorted(x) for x in table["words"].to_pylist()])
    return added(own, np.concatenate([decode_counts(x, i) for x, i in zip(table["counts"].to_pylist(), table["n"].to_pylist(), strict=True)]))


#: Words that a task puts in order at a time.
BLOCK_WORDS = 4 << 20


def sent(reads: DataFrame, k: int, stranded: bool, size: int, ends_too: bool = False, within: tuple[int, int] | None = None, weight: str | None = None) -> DataFrame:
    """ROWS of each block of reads, of all parts or of those from one number to another.

    With `ends_too`, a word at the end of its read counts END more. With `weight`, it counts as often as that column
    of its read says; words that count 0 are sent too.
    """
    bits = 2 * k

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        held, n = [], 0
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                read, pos, code = windows_of(raw, ends, k, stranded)
                last = (np.diff(ends, prepend=0) - k)[read] == pos if ends_too else np.zeros(0, bool)
                if weight:
                    last = np.asarray(rows.column(2))[read]
                code = mixed(code, bits)
                if within:
                    own = (code >= np.uint64(within[0] * size)) & (code <= np.uint64(within[1] * size - 1))
                    code, last = code[own], last[own] if ends_too or weight else last
                held.append((code, last))
                n += len(code)
                if n >= BLOCK_WORDS:
                    yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
                    held, n = [], 0
        if n:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for code, last in blocks(batches):
            if weight:
                own, cnt = added(code, last.astype(np.int64))
            else:
                own, cnt = added(code, 1 + END * last.astype(np.int64)) if ends_too else np.unique(code, return_counts=True)
            yield _batch(list(packed_words(own, cnt, size)), ROWS)

    return reads.select("read_id", "seq", *([weight] if weight else [])).mapInArrow(send, ROWS)


#: What a word's place at the end of a read adds to its count, where that is asked for.
END = 1 << 40


def packed_counts(rows: DataFrame, bits: int, size: int, least: int = 1) -> DataFrame:
    """(kmer, cnt) of ROWS: parts are sent as gaps, and added up where they meet. Words under `least` stay there."""

    def add(table: pa.Table) -> pa.Table:
        own, cnt = merged(table)
        if least > 1:
            own, cnt = own[cnt >= least], cnt[cnt >= least]
        return pa.table([as_signed(mixed(own + np.uint64(table["part"][0].as_py() * size), bits, UNDO)), pa.array(cnt)], names=["kmer", "cnt"])

    return rows.groupBy("part").applyInArrow(add, "kmer long, cnt long")


#: Words that a task puts in order at a time with their sources, which take as much memory again.
SOURCE_WORDS = 2 << 20
GROUPED = "part int, words binary, groups binary, names array<string>, totals array<long>"


def in_pairs(codes: np.ndarray, groups: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct pairs of a word and a whole number, in ascending order of both, and where each pair begins among all."""
    if not len(codes):
        return codes, groups, np.zeros(0, np.int64)
    wide = int(groups.max()).bit_length()
    if bits + wide > 64:
        order = np.lexsort((groups, codes))
        codes, groups = codes[order], groups[order]
    else:
        key = codes << np.uint64(wide)
        key |= groups.astype(np.uint64)
        key.sort()
        codes, groups = key >> np.uint64(wide), (key & np.uint64(2**wide - 1)).astype(np.int32)
    start = np.flatnonzero(np.concatenate([[True], (codes[1:] != codes[:-1]) | (groups[1:] != groups[:-1])]))
    return codes[start], groups[start], start


def sent_by_source(reads: DataFrame, k: int, stranded: bool, size: int, within: tuple[int, int] | None = None) -> DataFrame:
    """GROUPED: of each block of reads the distinct words of each source by part, and how many words these stand for."""
    bits = 2 * k

    def packed(held: list[tuple], names: list) -> pa.RecordBatch:
        n = sum(len(x[0]) for x in held)
        code, group = (np.concatenate(x) for x in zip(*held, strict=True))
        held.clear()
        code, group, start = in_pairs(code, group, bits)
        times, rows = np.diff(start, append=n), []
        for p, a, b in _cut(code, size):
            found, at = np.unique(group[a:b], return_inverse=True)
            width = 1 if len(found) <= 256 else 4
            totals = np.zeros(len(found), np.int64)
            np.add.at(totals, at, times[a:b])
            rows.append((p, encode_sorted(code[a:b] - np.uint64(p * size)), squeeze(at.astype(f"<u{width}").tobytes()), [names[i] for i in found.tolist()], totals.tolist()))
        kinds = (pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.string()), pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=[c.split()[0] for c in GROUPED.split(", ")])

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, known, n = [], {}, 0
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                read, _, code = windows_of(raw, ends, k, stranded)
                names = rows.column(2).dictionary_encode()
                place = np.array([known.setdefault(x, len(known)) for x in [*names.dictionary.to_pylist(), None]])
                group = place[names.indices.fill_null(len(names.dictionary)).to_numpy(zero_copy_only=False)].astype(np.int32)[read]
                code = mixed(code, bits)
                if within:
                    own = (code >= np.uint64(within[0] * size)) & (code <= np.uint64(within[1] * size - 1))
                    code, group = code[own], group[own]
                held.append((code, group))
                n += len(code)
                if n >= SOURCE_WORDS:
                    yield packed(held, list(known))
                    held, known, n = [], {}, 0
        if n:
            yield packed(held, list(known))

    return reads.select("read_id", "seq", "source").mapInArrow(send, GROUPED)


def rollup_by_source(reads: DataFrame, k: int, stranded: bool = False) -> DataFrame:
    """lang, source, n_words, n_distinct of reads whose source is 'lang/source': a rollup, with the words of all.

    A part tells how many of its words each group has, so only numbers leave it. Large inputs take several passes over
    the reads, so that only a share of the words is shuffled at a time.
    """
    bits, part_bits, size = layout(reads, k)
    names = ("level", "lang", "source", "n_words", "n_distinct")
    kinds = (pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64())

    def key(name: str | None) -> tuple[str | None, str | None]:
        return (None, None) if name is None else tuple([*name.split("/"), None][:2])

    def tell(table: pa.Table) -> pa.Table:
        own = [[key(x) for x in row] for row in table["names"].to_pylist()]
        keys = sorted({x for row in own for x in row}, key=lambda x: [(c is not None, c or "") for c in x])
        place, words, groups, totals = {x: i for i, x in enumerate(keys)}, [], [], np.zeros(len(keys), np.int64)
        for row, raw, group, n in zip(own, table["words"].to_pylist(), table["groups"].to_pylist(), table["totals"].to_pylist(), strict=True):
            at = np.array([place[x] for x in row])
            np.add.at(totals, at, n)
            words.append(decode_sorted(raw))
            groups.append(at.astype(np.int32)[np.frombuffer(expand(group), f"<u{1 if len(row) <= 256 else 4}")])
        code, group, _ = in_pairs(np.concatenate(words), np.concatenate(groups), bits)
        rows, fresh = [], np.concatenate([[True], code[1:] != code[:-1]])
        for level, of in ((0, keys), (1, [(x[0], None) for x in keys]), (2, [(None, None) for _ in keys])):
            labels = list(dict.fromkeys(of))  # in order, so equal ones stand together in a word's groups
            at = {x: i for i, x in enumerate(labels)}
            number = np.array([at[x] for x in of])
            label = number[group]
            first = fresh | np.concatenate([[True], label[1:] != label[:-1]])
            n_words = np.zeros(len(labels), np.int64)
            np.add.at(n_words, number, totals)
            rows += [(level, *x, w, d) for x, w, d in zip(labels, n_words.tolist(), np.bincount(label[first], minlength=len(labels)).tolist(), strict=True)]
        return pa.table({c: pa.array([r[i] for r in rows], t) for i, (c, t) in enumerate(zip(names, kinds, strict=True))})

    out, parts = None, 2**part_bits
    for within in spans(parts, PASSES if parts * PART_BYTES > ONE_PASS_BYTES else 1):
        found = sent_by_source(reads, k, stranded, size, within).groupBy("part").applyInArrow(tell, "level int, lang string, source string, n_words long, n_distinct long")
        found = stored(found.groupBy("level", "lang", "source").agg(F.sum("n_words").alias("n_words"), F.sum("n_distinct").alias("n_distinct")))
        out = found if out is None else out.unionByName(found)
    return out.groupBy("level", "lang", "source").agg(F.sum("n_words").alias("n_words"), F.sum("n_distinct").alias("n_distinct")).drop("level")


def spans(parts: int, passes: int) -> list[tuple[int, int] | None]:
    """The parts of each pass over the reads; one pass takes all."""
    passes = min(passes, parts)
    return [(parts * i // passes, parts * (i + 1) // passes) for i in range(passes)] if passes > 1 else [None]


def part_files(rows: Callable[[tuple[int, int] | None], DataFrame], parts: int, passes: int = 1) -> DataFrame:
    """Rows in files by their part: a table bucketed by it, so that what is asked of a part moves nothing.

    `rows` makes those of some parts; in several passes, only a share of the rows is shuffled at a time.
    """
    path, name = "", f"kmerspark_parts_{uuid.uuid4().hex}"
    for within in spans(parts, passes):
        own = rows(within)
        spark = own.sparkSession
        path = path or shared_path(spark)
        with shuffles_released(spark):
            own.repartition(parts, "part").write.mode("append").bucketBy(parts, "part").option("path", path).saveAsTable(name)
    out = spark.table(name)
    out._stored_at = path
    return out


def first_seen(blocks: Iterator[np.ndarray], n: int, lost: float) -> Iterator[np.ndarray]:
    """Of blocks of distinct words, those that a filter for n words in all has not seen."""
    size = math.ceil(size_for_fpr(1.2 * max(1, n), lost, 3, exact=True).memory) + 64
    bits = np.zeros(size, bool)
    for code in blocks:
        at = [(draw(code, 11, s + 1) % np.uint64(size)).astype(np.int64) for s in range(3)]
        known = bits[at[0]] & bits[at[1]] & bits[at[2]]
        for a in at:
            bits[a] = True
        yield code[~known]


class PackedWords:
    """The distinct words of reads and their counts, a row a part, in a table bucketed by part.

    With `lost`, a filter per part decides at which words' first sight a word is new; a share `lost` of them, at most,
    is taken for known and has no estimate. Counters have the counts of all.
    """

    def __init__(self, reads: DataFrame, k: int, stranded: bool = False, lost: float | None = None, ends_too: bool = False, weight: str | None = None):
        spark = reads.sparkSession
        self.bits, part_bits, self.size = layout(reads, k)
        size, rows = self.size, ROWS + (", first binary" if lost else "")

        def add(table: pa.Table) -> pa.Table:
            own, cnt = merged(table)
            out = (table["part"][0].as_py(), len(own), encode_sorted(own), encode_counts(cnt))
            if lost:
                passed = np.concatenate(list(first_seen((decode_sorted(x) for x in table["words"].to_pylist()), sum(table["n"].to_pylist()), lost)))
                out += (squeeze(np.packbits(np.isin(own, passed)).tobytes()),)
            return pa.Table.from_batches([_batch([out], rows)])

        name, partitions = f"kmerspark_words_{uuid.uuid4().hex}", int(spark.conf.get("spark.sql.shuffle.partitions"))
        path, parts = shared_path(spark), 2**part_bits
        for within in spans(parts, PASSES if parts * PART_BYTES > ONE_PASS_BYTES and parts > PASSES else 1):  # what is shuffled goes when a pass has been written
            found = sent(reads, k, stranded, size, ends_too, within, weight).groupBy("part").applyInArrow(add, rows)
            with shuffles_released(spark):
                found.write.mode("append").bucketBy(max(partitions, parts // 8), "part").option("path", path).saveAsTable(name)
        self.rows, self.name, self.parts = spark.table(name), name, parts
        self.rows._stored_at = path

    def counts(self, within: tuple[int, int] | None = None) -> DataFrame:
        """(kmer, cnt) as they lie, of all parts or of those from one number to another; nothing is shuffled."""
        bits, size = self.bits, self.size
        own = self.rows.filter((F.col("part") >= within[0]) & (F.col("part") < within[1])) if within else self.rows

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for part, n, raw, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    code = mixed(decode_sorted(raw) + np.uint64(part * size), bits, UNDO)
                    yield pa.RecordBatch.from_arrays([as_signed(code), pa.array(decode_counts(counts, n))], names=["kmer", "cnt"])

        return own.select("part", "n", "words", "counts").mapInArrow(run, "kmer long, cnt long")

    def sums(self, numbers: Callable[[np.ndarray, np.ndarray], tuple[int, ...]], n: int) -> tuple[int, ...]:
        """Sums over the parts of what `numbers` finds in a part's words and counts; n numbers a part leave the tasks."""
        bits, size, names = self.bits, self.size, [f"x{i}" for i in range(n)]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for part, m, raw, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    found = numbers(mixed(decode_sorted(raw) + np.uint64(part * size), bits, UNDO), decode_counts(counts, m))
                    yield pa.RecordBatch.from_arrays([pa.array([int(x)], pa.int64()) for x in found], names=names)

        rows = self.rows.select("part", "n", "words", "counts").mapInArrow(run, ", ".join(f"{x} long" for x in names))
        return tuple(int(x or 0) for x in rows.agg(*(F.sum(x) for x in names)).first())

    def discard(self) -> None:
        """Delete the table; what has been made of it must not be read again."""
        spark = self.rows.sparkSession
        discard(self.rows)
        spark.sql(f"DROP TABLE IF EXISTS {self.name}")

    def answered(self, spec: SketchSpec, tables_too: bool = False, answers: bool = True) -> list[DataFrame]:
        """By table, the stored answers (part, range, est) of its ranges to all parts.

        With `tables_too`, a range also gives its counters in use, block by block, as parts -1, -2 and so on.
        """
        if spec.layout != "primes" or 2 * spec.k != self.bits or spec.cap > 2**32 - 1:
            raise ValueError("packed words go to prime tables for their own k, of at most 32 bits a counter")
        bits, size, cap = self.bits, self.size, spec.cap
        width = next(w for w in (1, 2, 4) if cap < 256**w)

        def sender(prime: int):
            def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    for part, n, raw, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                        code = mixed(decode_sorted(raw) + np.uint64(part * size), bits, UNDO)
                        cell, cnt = code % np.uint64(prime), decode_counts(counts, n)
                        order = np.argsort(cell)  # words of one cell get one answer, so their order is free
                        cell, cnt = cell[order], cnt[order]
                        yield _batch([(r, part, b - a, encode_sorted(cell[a:b] - np.uint64(r * RANGE)), encode_counts(cnt[a:b])) for r, a, b in _cut(cell, RANGE)], "range int, part int, n int, cells binary, counts binary")

            return send

        def answer(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, total = [], np.zeros(RANGE, np.int64)
            for batch in batches:
                for part, n, raw, counts in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("part", "n", "cells", "counts")), strict=True):
                    np.add.at(total, decode_sorted(raw).view(np.int64), decode_counts(counts, n))
                    if answers:
                        held.append((part, raw))
            total = np.minimum(total, cap).astype(f"<u{width}")
            for a in range(0, len(held), 1000):
                yield _batch([(p, key[0].as_py(), squeeze(total[decode_sorted(raw).view(np.int64)].tobytes())) for p, raw in held[a : a + 1000]], "part int, range int, est binary")
            if tables_too:
                blocks = ((b, total[b * BLOCK : (b + 1) * BLOCK]) for b in range(RANGE // BLOCK))
                yield _batch([(-1 - b, key[0].as_py(), squeeze(own.tobytes())) for b, own in blocks if own.any()], "part int, range int, est binary")

        found = []
        for prime in spec.primes:
            cells = self.rows.select("part", "n", "words", "counts").mapInArrow(sender(prime), "range int, part int, n int, cells binary, counts binary")
            found.append(stored(cells.groupBy("range").applyInArrow(answer, "part int, range int, est binary")))
        return found

    def estimates(self, spec: SketchSpec, keep: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None, found: list[DataFrame] | None = None) -> DataFrame:
        """kmer, cnt, est: every word, its count, and its count in a sketch of that spec of all words.

        `keep` tells by counts and estimates which words are given. `found` has the answers, if they are there already.
        """

        def rows(code: np.ndarray, cnt: np.ndarray, est: np.ndarray) -> pa.RecordBatch:
            if keep:
                own = keep(cnt, est)
                code, cnt, est = code[own], cnt[own], est[own]
            return pa.RecordBatch.from_arrays([as_signed(code), pa.array(cnt), pa.array(est)], names=["kmer", "cnt", "est"])

        return self._least(spec, rows, "kmer long, cnt long, est long", found)

    def histogram(self, spec: SketchSpec, found: list[DataFrame] | None = None) -> DataFrame:
        """abundance, n_kmers of a sketch of that spec of all words; a part sends its own histogram."""

        def rows(_code: np.ndarray, _cnt: np.ndarray, est: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in np.unique(est, return_counts=True)], names=["abundance", "n"])

        own = self._least(spec, rows, "abundance long, n long", found)
        return own.groupBy("abundance").agg(F.sum("n").alias("n_kmers"))

    def _least(self, spec: SketchSpec, rows: Callable, schema: str, found: list[DataFrame] | None) -> DataFrame:
        """What `rows` makes of each part's words, their counts and the least answer to each."""
        bits, size, cap, primes = self.bits, self.size, spec.cap, spec.primes
        width, filtered = next(w for w in (1, 2, 4) if cap < 256**w), "first" in self.rows.columns

        def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                first = batch.column(batch.schema.get_field_index("first")).to_pylist() if filtered else []
                for part, n, raw, counts, answers in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("part", "n", "words", "counts", "answers")), strict=True):
                    code, est = mixed(decode_sorted(raw) + np.uint64(part * size), bits, UNDO), np.full(n, cap, np.int64)
                    for i, prime in enumerate(primes):
                        own = b"".join(expand(x["est"]) for x in answers if x["table_id"] == i)  # by table and range
                        order = np.argsort(code % np.uint64(prime))
                        est[order] = np.minimum(est[order], np.frombuffer(own, f"<u{width}"))
                    cnt = decode_counts(counts, n)
                    if filtered:
                        keep = np.unpackbits(np.frombuffer(expand(first.pop(0)), np.uint8), count=n).astype(bool)
                        code, cnt, est = code[keep], cnt[keep], est[keep]
                    yield rows(code, cnt, est)

        own, out = found or self.answered(spec), None
        for i, table in enumerate(own):
            row = table.filter("part >= 0").select(F.lit(i).cast("tinyint").alias("table_id"), "*")
            out = row if out is None else out.unionByName(row)
        answers = stored(out.groupBy("part").agg(F.sort_array(F.collect_list(F.struct("table_id", "range", "est"))).alias("answers")))
        if not found:
            discard(*own)
        return self.rows.join(answers.hint("shuffle_hash"), "part").mapInArrow(least, schema)


def tables_of(found: list[DataFrame]) -> DataFrame:
    """table_id, block, counters of the tables that `answered` gave too: what a dense sketch holds."""
    out = None
    for i, table in enumerate(found):
        row = table.filter("part < 0").select(F.lit(i).cast("tinyint").alias("table_id"), (F.col("range") * (RANGE // BLOCK) - 1 - F.col("part")).cast("int").alias("block"), "est")
        out = row if out is None else out.unionByName(row)

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([expand(x) for x in batch.column(2).to_pylist()], pa.binary())], names=["table_id", "block", "counters"])

    return out.mapInArrow(unpack, "table_id tinyint, block int, counters binary")
