"""The word space in parts, each with tables of its own: by prefix, by hash, or by minimizer (super-k-mers).

A word belongs to one part, so a part is counted and probed where its words meet, in memory that is known before
the run; parts run side by side, or one after another on a small machine.
"""

from __future__ import annotations

import pickle
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.dna import base_codes, pack_windows, windows_of, xxhash64_of
from .kmers import as_signed, combined_kmers, read_blocks
from .packed import UNDO, PackedWords, added, decode_counts, decode_sorted, encode_counts, encode_sorted, expand, mixed, squeeze
from .packed import _batch as packed_batch
from .sketch import SketchSpec
from .store import shared_path

MINIMIZER = 11


def part_of(kmer: Column, k: int, by: str = "hash", parts: int = 16, prefix: int = 2) -> Column:
    """The part of a packed word. Prefixes of canonical words are uneven; hashed parts are not."""
    if by == "prefix":
        return F.shiftrightunsigned(kmer, 2 * (k - prefix)).cast("int")
    if by == "hash":
        return F.pmod(F.xxhash64(kmer), F.lit(parts)).cast("int")
    raise ValueError("by is 'prefix' or 'hash'; super_kmers deals by minimizer")


def partitioned_counts(reads: DataFrame, k: int = 22, by: str = "hash", parts: int = 16, prefix: int = 2, stranded: bool = False) -> DataFrame:
    """part, kmer, cnt: exact counts with the part each word belongs to."""
    counts = combined_kmers(reads, k, stranded).groupBy("kmer").agg(F.sum("cnt").alias("cnt"))
    return counts.select(part_of(F.col("kmer"), k, by, parts, prefix).alias("part"), "kmer", "cnt")


def sharded_estimates(reads: DataFrame, queries: DataFrame, spec: SketchSpec, parts: int = 16, by: str = "hash", prefix: int = 2) -> DataFrame:
    """part, kmer, est of each query: every part builds its tables and answers its own queries in one task.

    `spec` is the size of one part's tables. One shuffle routes combined words and queries by part; a part's memory
    is its tables, however many words arrive.
    """
    occ = combined_kmers(reads, spec.k, spec.stranded).select("kmer", F.col("cnt"))
    rows = occ.unionByName(queries.select("kmer", F.lit(0).cast("long").alias("cnt")))
    rows = rows.withColumn("part", part_of(F.col("kmer"), spec.k, by, parts, prefix))
    rows = rows.repartition(parts, "part").sortWithinPartitions("part", F.desc("cnt"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, tables = None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            codes, cnt, own = np.asarray(batch.column(0)).view(np.uint64), np.asarray(batch.column(1)), np.asarray(batch.column(2))
            for p in np.unique(own).tolist():
                if p != part:
                    part, tables = p, [np.zeros(h, np.int64 if spec.counter_bits > 8 else np.uint16) for h in spec.primes]
                here = own == p
                add, ask = codes[here & (cnt > 0)], codes[here & (cnt == 0)]
                for t, at in zip(tables, spec.positions(add), strict=True):
                    _add_capped(t, at, cnt[here & (cnt > 0)], spec.cap)
                if len(ask):
                    est = np.min([t[at] for t, at in zip(tables, spec.positions(ask), strict=True)], axis=0)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ask), p, np.int32)), as_signed(ask), pa.array(est.astype(np.int64))], names=["part", "kmer", "est"])

    return rows.mapInArrow(run, "part int, kmer long, est long")


#: Bytes of words that a part's task holds in memory while it adds them up; more go to a file of its own.
HELD_BYTES = 64 << 20


def sharded_words(words: PackedWords, spec: SketchSpec, parts: int = 16) -> DataFrame:
    """part, kmer, cnt, est of all words, by hashed parts: as `sharded_estimates`, but words are sent once, as gaps.

    A part keeps what it was sent until its tables are full, and asks then.
    """
    bits, size = words.bits, words.size
    rows = words.rows.select(F.col("part").alias("own"), "n", "words", "counts")

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for own, n, raw, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                code, cnt = decode_sorted(raw), decode_counts(counts, n)
                part = xxhash64_of(mixed(code + np.uint64(own * size), bits, UNDO)) % parts
                found = [(p, own, len(at), encode_sorted(code[at]), encode_counts(cnt[at])) for p in range(parts) if len(at := np.flatnonzero(part == p))]
                yield packed_batch(found, SHARD)

    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [np.zeros(h, np.int64 if spec.counter_bits > 8 else np.uint16) for h in spec.primes]
        with tempfile.SpooledTemporaryFile(HELD_BYTES) as held:
            for batch in batches:
                for row in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("own", "n", "words", "counts")), strict=True):
                    code, cnt = mixed(decode_sorted(row[2]) + np.uint64(row[0] * size), bits, UNDO), decode_counts(row[3], row[1])
                    for t, at in zip(tables, spec.positions(code), strict=True):
                        _add_capped(t, at, cnt, spec.cap)
                    pickle.dump(row, held)
            end = held.tell()
            held.seek(0)
            while held.tell() < end:
                own, n, raw, counts = pickle.load(held)
                code = mixed(decode_sorted(raw) + np.uint64(own * size), bits, UNDO)
                est = np.min([t[at] for t, at in zip(tables, spec.positions(code), strict=True)], axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, key[0].as_py(), np.int32)), as_signed(code), pa.array(decode_counts(counts, n)), pa.array(est.astype(np.int64))], names=["part", "kmer", "cnt", "est"])

    return rows.mapInArrow(send, SHARD).groupBy("part").applyInArrow(run, "part int, kmer long, cnt long, est long")


SHARD = "part int, own int, n int, words binary, counts binary"


def _add_capped(table: np.ndarray, at: np.ndarray, cnt: np.ndarray, cap: int) -> None:
    spots, where = np.unique(at, return_inverse=True)
    more = np.bincount(where, weights=cnt, minlength=len(spots)).astype(np.int64)
    table[spots] = np.minimum(table[spots].astype(np.int64) + more, cap)


def part_report(counts: DataFrame, spec: SketchSpec) -> DataFrame:
    """part, n_distinct, n_words and the error rate expected of the part's tables."""
    out = counts.groupBy("part").agg(F.count("*").alias("n_distinct"), F.sum("cnt").alias("n_words"))
    rate = F.lit(1.0)
    for h in spec.primes:
        rate = rate * (1 - F.exp(-F.col("n_distinct") / F.lit(float(h))))
    return out.withColumn("fpr", F.round(rate, 6))


def run_parts(reads: DataFrame, path: str, k: int = 22, parts: int = 16, run: str = "parallel", by: str = "hash", stranded: bool = False) -> DataFrame:
    """Counts of each part, saved by part for later comparison. 'iterative' runs one part after another."""
    counts = partitioned_counts(reads, k, by, parts, stranded=stranded)
    if run == "parallel":
        counts.write.mode("overwrite").partitionBy("part").parquet(path)
    else:
        words = combined_kmers(reads, k, stranded).withColumn("part", part_of(F.col("kmer"), k, by, parts))
        binned = shared_path(reads.sparkSession)  # one pass over the reads; then each part's own files
        words.repartition(parts, "part").write.partitionBy("part").parquet(binned)
        for p in sorted(r["part"] for r in reads.sparkSession.read.parquet(binned).select("part").distinct().collect()):  # a row per part
            own = reads.sparkSession.read.parquet(f"{binned}/part={p}").groupBy("kmer").agg(F.sum("cnt").alias("cnt"))
            own.write.mode("overwrite").parquet(f"{path}/part={p}")
    return reads.sparkSession.read.parquet(path)


def minimizers(codes: np.ndarray, k: int, m: int = MINIMIZER) -> np.ndarray:
    """For every window of k bases, its least mixed canonical m-mer; the same for both strands."""
    from ..sources.simulate import draw

    fwd, rev = pack_windows(codes, m)
    mixed = draw(np.minimum(fwd, rev), 7, 1)
    width, have = k - m + 1, 1
    while have < width:
        step = min(have, width - have)
        mixed = np.minimum(mixed[:-step], mixed[step:])
        have += step
    return mixed


def runs_of(raw: np.ndarray, ends: np.ndarray, k: int, parts: int, m: int = MINIMIZER) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last window, and part, of each run of windows with one minimizer."""
    none = np.zeros(0, np.int64)
    if len(raw) < k:
        return none, none, none.astype(np.int32)
    codes = base_codes(raw)
    least = minimizers(codes, k, m)
    bad = np.concatenate([[0], np.cumsum(codes == 255, dtype=np.int32)])
    read = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))[: len(least)]
    at = np.flatnonzero((bad[k:] == bad[:-k]) & (np.arange(len(least)) + k <= ends[read]))
    if not len(at):
        return none, none, none.astype(np.int32)
    new = np.concatenate([[True], (np.diff(at) > 1) | (least[at][1:] != least[at][:-1])])
    first = at[new]
    return first, at[np.append(np.flatnonzero(new)[1:], len(at)) - 1], ((least[first] >> np.uint64(20)) % np.uint64(parts)).astype(np.int32)


def super_kmers(reads: DataFrame, k: int = 22, parts: int = 64, m: int = MINIMIZER) -> DataFrame:
    """part, bases: runs of windows with one minimizer, about a sixth of the bytes of their separate words.

    Bases travel as text here, two bits each in `packed`.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                first, last, part = runs_of(raw, ends, k, parts, m)
                if not len(first):
                    continue
                data = raw.tobytes()
                packed = [pack_bases(data[a : b + k]) for a, b in zip(first.tolist(), last.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(packed, pa.binary())], names=["part", "packed"])

    return reads.select("read_id", "seq").mapInArrow(run, "part int, packed binary")


RUNS = "part int, n int, sizes binary, bases binary"
#: Bases of runs that a task unpacks at a time, and words that it holds before it adds them up.
RUN_BASES, HELD_WORDS = 2 << 20, 8 << 20


def super_kmer_blocks(reads: DataFrame, k: int = 22, parts: int = 64, m: int = MINIMIZER) -> DataFrame:
    """RUNS: the super-k-mers of a block of reads that go to one bin, end to end with two bits a base, and their lengths."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                first, last, part = runs_of(raw, ends, k, parts, m)
                if not len(part):
                    continue
                order = np.argsort(part, kind="stable")
                first, size, part = first[order], (last - first)[order] + k, part[order]
                codes, out = base_codes(raw), []
                edge = np.flatnonzero(np.diff(part, prepend=-1)).tolist()
                for a, b in zip(edge, [*edge[1:], len(part)], strict=True):
                    for c in range(a, b, RUN_BASES // (4 * k)):
                        d = min(b, c + RUN_BASES // (4 * k))
                        own, start = size[c:d], first[c:d]
                        at = np.arange(own.sum()) + np.repeat(start - (np.cumsum(own) - own), own)
                        two = np.concatenate([codes[at], np.zeros(-len(at) % 4, np.uint8)]).reshape(-1, 4)
                        packed = two[:, 0] | two[:, 1] << 2 | two[:, 2] << 4 | two[:, 3] << 6
                        out.append((int(part[a]), d - c, squeeze(own.astype("<u4").tobytes()), packed.tobytes()))
                yield packed_batch(out, RUNS)

    return reads.select("read_id", "seq").mapInArrow(run, RUNS)


def counts_of_blocks(bins: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    """kmer, cnt of RUNS: a bin's words are added up where its runs meet; no word is in two bins."""
    letters = np.frombuffer(b"ACGT", np.uint8)

    def run(_key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        word, cnt, held, n_held = np.zeros(0, np.uint64), np.zeros(0, np.int64), [], 0

        def fold() -> tuple[np.ndarray, np.ndarray]:
            own, times = np.unique(np.concatenate([np.zeros(0, np.uint64), *held]), return_counts=True)
            held.clear()
            return added(np.concatenate([word, own]), np.concatenate([cnt, times])) if len(word) else (own, times)

        for batch in batches:
            for sizes, bases in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("sizes", "bases")), strict=True):
                ends = np.cumsum(np.frombuffer(expand(sizes), "<u4"), dtype=np.int64)
                two = (np.frombuffer(bases, np.uint8)[:, None] >> np.array([0, 2, 4, 6], np.uint8)) & 3
                code = windows_of(letters[two.ravel()[: ends[-1]]], ends, k, stranded)[2]
                held.append(code)
                n_held += len(code)
                if n_held >= HELD_WORDS:
                    word, cnt = fold()
                    n_held = 0
        word, cnt = fold()
        yield pa.RecordBatch.from_arrays([as_signed(word), pa.array(cnt)], names=["kmer", "cnt"])

    return bins.groupBy("part").applyInArrow(run, "kmer long, cnt long")


_DIGITS = bytes.maketrans(b"ACGTacgt", b"01230123")


def pack_bases(bases: bytes) -> bytes:
    """Two bits a base, after the length in two bytes."""
    n = len(bases)
    return n.to_bytes(2, "little") + int(bases.translate(_DIGITS) or b"0", 4).to_bytes(-(-n // 4), "little")


def unpack_bases(packed: bytes) -> np.ndarray:
    n = int.from_bytes(packed[:2], "little")
    raw = np.frombuffer(packed, np.uint8, offset=2)
    two = (raw[:, None] >> np.array([0, 2, 4, 6], np.uint8)) & 3
    return np.frombuffer(b"ACGT", np.uint8)[two.ravel()[:n][::-1]]


def counts_of_bins(bins: DataFrame, k: int = 22, stranded: bool = False, parts: int = 64) -> DataFrame:
    """part, kmer, cnt: each bin's words are counted where the bin is; no word is in two bins."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 50_000):
                own = batch.slice(a, 50_000)
                runs = [unpack_bases(x) for x in own.column(1).to_pylist()]
                if not runs:
                    continue
                ends = np.cumsum([len(x) for x in runs])
                read, _, code = windows_of(np.concatenate(runs), ends, k, stranded)
                part = np.asarray(own.column(0))[read]
                order = np.lexsort((code, part))
                code, part = code[order], part[order]
                edge = np.flatnonzero(np.concatenate([[True], (np.diff(code) != 0) | (np.diff(part) != 0)])) if len(code) else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(part[edge]), as_signed(code[edge]), pa.array(np.diff(np.append(edge, len(code))))], names=["part", "kmer", "cnt"])

    dealt = bins.repartition(parts, "part")
    return dealt.mapInArrow(run, "part int, kmer long, cnt long").groupBy("part", "kmer").agg(F.sum("cnt").alias("cnt"))


def balanced_bins(weights: dict[int, int], parts: int) -> dict[int, int]:
    """Bins to parts, the heaviest first to the lightest part; a bin never splits."""
    load, out = [0] * parts, {}
    for b in sorted(weights, key=weights.get, reverse=True):
        at = load.index(min(load))
        out[b], load[at] = at, load[at] + weights[b]
    return out
