"""Occurrences of k-mers in reads: (read_id, pos, kmer), and their combined counts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.dna import MAX_K, _check_k, canonical, cyclic_hashes, encode_kmer, windows_of
from .store import shuffles_released

#: Bases that a kernel call holds at a time.
BLOCK_BASES = 4 << 20


def read_blocks(batch: pa.RecordBatch, seq: str = "seq") -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Runs of reads of about BLOCK_BASES bases: the rows, their letters end to end, and where each read ends."""
    if not batch.num_rows:
        return
    text = batch.column(batch.schema.get_field_index(seq)).cast(pa.large_string()).fill_null("")
    batch = batch.set_column(batch.schema.get_field_index(seq), seq, text)
    offsets = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
    run = np.cumsum(np.diff(offsets)) // BLOCK_BASES
    cuts = [0, *(np.flatnonzero(np.diff(run)) + 1).tolist(), len(text)]
    data = np.frombuffer(text.buffers()[2], np.uint8) if text.buffers()[2] is not None else np.zeros(0, np.uint8)
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        if b > a:
            yield batch.slice(a, b - a), data[offsets[a] : offsets[b]], offsets[a + 1 : b + 1] - offsets[a]


def as_signed(codes: np.ndarray) -> pa.Array:
    return pa.array(codes.view(np.int64))


def explode_kmers(reads: DataFrame, k: int = 22, stranded: bool = False, impl: str = "arrow", with_pos: bool = True) -> DataFrame:
    """One row per valid window of each read. 'arrow' packs whole batches in NumPy; 'sql' is plain column functions."""
    _check_k(k)
    if impl == "sql":
        at = F.explode(F.sequence(F.lit(0), F.length("seq") - k))
        rows = reads.filter(F.length("seq") >= k).select("read_id", "seq", at.alias("pos"))
        word = F.substr("seq", F.col("pos") + 1, F.lit(k))
        rows = rows.select("read_id", "pos", word.alias("w")).filter(~F.col("w").rlike("[^ACGT]"))
        out = rows.select("read_id", "pos", encode_kmer(canonical(F.col("w"), stranded), k).alias("kmer"))
        return out if with_pos else out.select("kmer")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                read, pos, code = windows_of(raw, ends, k, stranded)
                if with_pos:
                    yield pa.RecordBatch.from_arrays([rows.column(0).take(pa.array(read)), pa.array(pos.astype(np.int32)), as_signed(code)], names=["read_id", "pos", "kmer"])
                else:
                    yield pa.RecordBatch.from_arrays([as_signed(code)], names=["kmer"])

    return reads.select("read_id", "seq").mapInArrow(run, "read_id long, pos int, kmer long" if with_pos else "kmer long")


def combined_kmers(reads: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    """(kmer, cnt) with each block's repeats already added up: what a counter should shuffle."""
    _check_k(k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                code, cnt = np.unique(windows_of(raw, ends, k, stranded)[2], return_counts=True)
                yield pa.RecordBatch.from_arrays([as_signed(code), pa.array(cnt)], names=["kmer", "cnt"])

    return reads.select("read_id", "seq").mapInArrow(run, "kmer long, cnt long")


def counts_by_source(reads: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    """(source, kmer, cnt): the distinct words of each source. Reads carry their source; nothing is joined to them."""
    _check_k(k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                names = rows.column(2).dictionary_encode()
                read, _, code = windows_of(raw, ends, k, stranded)
                own = names.indices.fill_null(-1).to_numpy(zero_copy_only=False)[read]
                for i in np.unique(own).tolist():
                    word, cnt = np.unique(code[own == i], return_counts=True)
                    name = pa.array([None if i < 0 else names.dictionary[i].as_py()], pa.string()).take(pa.array(np.zeros(len(word), np.int32)))
                    yield pa.RecordBatch.from_arrays([name, as_signed(word), pa.array(cnt)], names=["source", "kmer", "cnt"])

    found = reads.select("read_id", "seq", "source").mapInArrow(run, "source string, kmer long, cnt long")
    return found.groupBy("source", "kmer").agg(F.sum("cnt").alias("cnt"))


#: One word in so many, by its code, is counted to estimate how many distinct words there are.
SAMPLE = 17


def estimate_distinct(reads: DataFrame, k: int = 22, stranded: bool = False, sample: int = SAMPLE) -> int:
    """Distinct words of reads: those whose code is a multiple of `sample` are counted exactly, and scaled up.

    Only they are shuffled. The error is about sqrt(sample / N); a prime `sample` cuts across the codes' bases.
    """
    _check_k(k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                code = windows_of(raw, ends, k, stranded)[2]
                yield pa.RecordBatch.from_arrays([as_signed(np.unique(code[code % np.uint64(sample) == 0]))], names=["kmer"])

    found = reads.select("read_id", "seq").mapInArrow(run, "kmer long").agg(F.count_distinct("kmer"))
    with shuffles_released(reads.sparkSession):
        return sample * (found.first()[0] or 0)


def hash_kmers(reads: DataFrame, k: int, hash: str = "cyclic", stranded: bool = False) -> DataFrame:
    """(read_id, pos, kmer) with another hash of each window; 'cyclic' takes windows of any length."""
    if hash == "pack2":
        return explode_kmers(reads, k, stranded)
    if hash in ("xxhash64", "md5_60"):
        at = F.explode(F.sequence(F.lit(0), F.length("seq") - k))
        rows = reads.filter(F.length("seq") >= k).select("read_id", "seq", at.alias("pos"))
        rows = rows.select("read_id", "pos", F.substr("seq", F.col("pos") + 1, F.lit(k)).alias("w")).filter(~F.col("w").rlike("[^ACGT]"))
        word = canonical(F.col("w"), stranded)
        return rows.select("read_id", "pos", (F.xxhash64(word) if hash == "xxhash64" else md5_60(word)).alias("kmer"))
    if hash != "cyclic":
        raise ValueError("hash is 'pack2', 'cyclic', 'xxhash64' or 'md5_60'")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                if len(raw) < k:
                    continue
                found = cyclic_hashes(raw, k, stranded)
                good = np.isin(raw, np.frombuffer(b"ACGTacgt", np.uint8))
                bad = np.concatenate([[0], np.cumsum(~good, dtype=np.int32)])
                sizes = np.diff(ends, prepend=0)
                read = np.repeat(np.arange(len(ends)), sizes)[: len(found)]
                at = np.flatnonzero((bad[k:] == bad[:-k]) & (np.arange(len(found)) + k <= ends[read]))
                yield pa.RecordBatch.from_arrays([rows.column(0).take(pa.array(read[at])), pa.array((at - (ends - sizes)[read[at]]).astype(np.int32)), as_signed(found[at])], names=["read_id", "pos", "kmer"])

    return reads.select("read_id", "seq").mapInArrow(run, "read_id long, pos int, kmer long")


def md5_60(value: Column) -> Column:
    """60 bits of a value's md5 digest: a hash that other engines reproduce."""
    return F.conv(F.substring(F.md5(value.cast("string")), 1, 15), 16, 10).cast("long")


def exact_counts(reads: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    """(kmer, cnt): every distinct word and how often it occurs. Words travel by parts, as gaps of sorted numbers."""
    from .packed import layout, packed_counts, sent

    _check_k(k)
    bits, _, size = layout(reads, k)
    return packed_counts(sent(reads, k, stranded, size), bits, size)


__all__ = ["MAX_K", "combined_kmers", "estimate_distinct", "exact_counts", "explode_kmers", "hash_kmers", "md5_60", "read_blocks"]
