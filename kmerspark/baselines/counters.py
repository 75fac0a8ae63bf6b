"""Exact and filtered counters of words: one class for each kind of tool, all with the same interface."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dna import windows_of
from ..operators.kmers import SAMPLE, as_signed, combined_kmers, exact_counts, read_blocks
from ..operators.lookup import lookup
from ..operators.packed import ONE_PASS_BYTES, PASSES, ROWS, PackedWords, added, encode_counts, encode_sorted, layout, merged, mixed, packed_counts, packed_words, part_files, sent
from ..operators.packed import _batch as packed_batch
from ..operators.partitioned import counts_of_blocks, super_kmer_blocks
from ..operators.sketch import PrimeSketch, SketchSpec
from ..operators.spectrum import histogram
from ..operators.store import stored
from ..plans.sizing import parts_for, table_bytes
from ..sources.reads import write_counts


class KmerCounter:
    """build() gives (kmer, cnt); the flags say what a tool of the class can do."""

    name = ""
    exact = True
    online = False
    random_access = False

    def __init__(self, k: int = 22, stranded: bool = False):
        self.k, self.stranded, self.counts = k, stranded, None

    def build(self, reads: DataFrame) -> KmerCounter:
        self.counts = self.count(reads)
        return self

    def count(self, reads: DataFrame) -> DataFrame:
        raise NotImplementedError

    def histogram(self) -> DataFrame:
        return histogram(self.counts)

    def lookup(self, queries: DataFrame) -> DataFrame:
        """kmer, est; queries are canonical codes, so both strands are found."""
        if not self.random_access:
            raise NotImplementedError(f"{self.name} has no random access")
        found = queries.join(self.counts, "kmer", "left")
        return found.select(*queries.columns, F.coalesce("cnt", F.lit(0)).alias("est"))

    def dump(self, path: str) -> None:
        write_counts(self.counts, path)

    def stats(self) -> DataFrame:
        return self.counts.agg(F.count("*").alias("n_distinct"), F.sum("cnt").alias("n_words"), F.max("cnt").alias("max_cnt"))


class HashCounter(KmerCounter):
    """All words in a hash table, combined before they are shuffled."""

    name, random_access, online = "exact_hash", True, True

    def count(self, reads):
        return exact_counts(reads, self.k, self.stranded)


class SpillingHashCounter(KmerCounter):
    """A table of at most max_keys words per task; a full one is passed on, and all generations are merged."""

    name, random_access = "exact_hash_spill", True

    def __init__(self, k: int = 22, stranded: bool = False, max_keys: int = 200_000):
        super().__init__(k, stranded)
        self.max_keys = max_keys

    def count(self, reads):
        k, stranded, limit = self.k, self.stranded, self.max_keys

        bits, _, size = layout(reads, k)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            keys, cnt = np.zeros(0, np.uint64), np.zeros(0, np.int64)
            for batch in batches:
                for _, raw, ends in read_blocks(batch):
                    fresh, times = np.unique(mixed(windows_of(raw, ends, k, stranded)[2], bits), return_counts=True)
                    keys, cnt = added(np.concatenate([keys, fresh]), np.concatenate([cnt, times])) if len(keys) else (fresh, times)
                    if len(keys) > limit:
                        yield packed_batch(list(packed_words(keys, cnt, size)), ROWS)
                        keys, cnt = np.zeros(0, np.uint64), np.zeros(0, np.int64)
            yield packed_batch(list(packed_words(keys, cnt, size)), ROWS)

        return packed_counts(reads.select("read_id", "seq").mapInArrow(run, ROWS), bits, size)


#: Reads of which the ranges of suffixes are told, at most so many bytes and this share of them; one word in so many.
RANGE_BYTES, RANGE_SHARE, RANGE_WORDS = 64 << 20, 0.05, 64


def suffix_ranges(reads: DataFrame, k: int, stranded: bool) -> np.ndarray:
    """The least code of each range of the suffix order; ranges are about even, as many as the input asks for."""
    share = min(RANGE_SHARE, RANGE_BYTES / max(1, table_bytes(reads)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                yield pa.RecordBatch.from_arrays([as_signed(windows_of(raw, ends, k, stranded)[2][::RANGE_WORDS])], names=["kmer"])

    some = np.sort(reads.select("read_id", "seq").sample(share, 42).mapInArrow(run, "kmer long").toArrow()["kmer"].to_numpy().view(np.uint64))
    parts = 2 ** layout(reads, k)[1]
    return np.unique(np.concatenate([np.zeros(1, np.uint64), some[np.arange(1, parts) * len(some) // parts] if len(some) else some]))


def suffixes(reads: DataFrame, k: int, stranded: bool, ranges: np.ndarray, within: tuple[int, int] | None = None) -> DataFrame:
    """ROWS of each block's words by their range, of all ranges or of those from one number to another."""
    low, high = within or (0, len(ranges))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, raw, ends in read_blocks(batch):
                code, cnt = np.unique(windows_of(raw, ends, k, stranded)[2], return_counts=True)
                edge = [*np.searchsorted(code, ranges).tolist(), len(code)]
                yield packed_batch([(p, b - a, encode_sorted(code[a:b] - ranges[p]), encode_counts(cnt[a:b])) for p in range(low, high) if (b := edge[p + 1]) > (a := edge[p])], ROWS)

    return reads.select("read_id", "seq").mapInArrow(run, ROWS)


def in_order(rows: DataFrame, ranges: np.ndarray) -> DataFrame:
    """kmer, cnt of suffixes: each range is put in order where its rows meet, and the runs of equal words are measured."""

    def run(table: pa.Table) -> pa.Table:
        own, cnt = merged(table)
        return pa.table([as_signed(own + ranges[table["part"][0].as_py()]), pa.array(cnt)], names=["kmer", "cnt"])

    return rows.groupBy("part").applyInArrow(run, "kmer long, cnt long")


class SuffixOrderCounter(KmerCounter):
    """Suffixes in order by their first k bases; a word's count is the run of suffixes that agree on them."""

    name, random_access = "exact_suffix", True

    def count(self, reads):
        ranges = suffix_ranges(reads, self.k, self.stranded)
        return in_order(suffixes(reads, self.k, self.stranded, ranges), ranges)

    def lookup(self, queries):
        """Merge of two sorted sides: the range search of a sorted index, for all queries at once."""
        found = queries.join(self.counts.hint("merge"), "kmer", "left")
        return found.select(*queries.columns, F.coalesce("cnt", F.lit(0)).alias("est"))


def lcp_boundaries(reads: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    """The same in column functions: a word begins a run where it differs from the one before in suffix order.

    Equal suffixes of a block are one row; ordered within hash buckets, as many as the input asks for, so no task
    holds the whole order.
    """
    occ = combined_kmers(reads, k, stranded).withColumn("bucket", F.pmod(F.xxhash64("kmer"), F.lit(parts_for(reads, 4 << 20, 64))))
    before = F.lag("kmer").over(Window.partitionBy("bucket").orderBy("kmer"))
    return occ.withColumn("new", (before.isNull() | (before != F.col("kmer"))).cast("int")).groupBy("kmer").agg(F.sum("new").alias("runs"), F.sum("cnt").alias("cnt"))


#: Bytes of a gate up to which it is sent out; beyond it words ask it by parts.
GATE_BYTES = 16 << 20


class BloomGatedCounter(KmerCounter):
    """First a small filter that knows what was seen twice, then exact counts of those words only; singles are left out."""

    name, online = "bloom_gated", True

    def __init__(self, k: int = 22, stranded: bool = False, expected_kmers: int | None = None, fpr: float = 0.1):
        super().__init__(k, stranded)
        self.expected, self.fpr = expected_kmers, fpr

    def gate_spec(self, words: PackedWords) -> SketchSpec:
        """Three tables of two-bit counters for the distinct words expected, or estimated from distinct words."""
        n = self.expected or SAMPLE * words.sums(lambda code, _: (np.count_nonzero(code % np.uint64(SAMPLE) == 0),), 1)[0]
        return SketchSpec.for_fpr(max(1, n), self.fpr, 3, k=self.k, stranded=self.stranded, counter_bits=2)

    def gated(self, words: PackedWords, least: tuple[int, int] = (0, 0)) -> DataFrame:
        """kmer, cnt, est: every word, its count, and its count in the gate, from the least count and gate's count on."""
        spec, (cnt, est) = self.gate_spec(words), least
        if spec.fits_a_task() and spec.memory_bytes() <= GATE_BYTES:
            found = lookup(words.counts(), PrimeSketch.dense_of_counts(words.counts(), spec).stored(stored))
            return found.filter((F.col("cnt") >= cnt) & (F.col("est") >= est))
        return words.estimates(spec, lambda c, e: (c >= cnt) & (e >= est))

    def count(self, reads, keep_false: bool = False):
        return self.gated(PackedWords(reads, self.k, self.stranded), (1 if keep_false else 2, 2)).select("kmer", "cnt")


class PartitionFileCounter(KmerCounter):
    """Words in part files on disk, counted part by part; more parts need less memory at a time."""

    name = "disk_partition"

    def __init__(self, k: int = 22, stranded: bool = False, parts: int | None = None):
        super().__init__(k, stranded)
        self.parts = parts

    def range_of(self, parts: int) -> int:
        """Mixed words of a part."""
        return -(-(4**self.k) // max(2, parts))

    def files(self, reads):
        """ROWS in files by part."""
        parts, size = self.parts or parts_for(reads, 1 << 20), table_bytes(reads)
        rows = lambda within: sent(reads, self.k, self.stranded, self.range_of(parts), within=within)
        out = part_files(rows, parts, PASSES if ONE_PASS_BYTES < size < 2**56 else 1)
        out._parts = parts
        return out

    def count(self, reads):
        files = self.files(reads)
        return packed_counts(files, 2 * self.k, self.range_of(files._parts))


class SortedBinCounter(KmerCounter):
    """Bins on disk, each sorted and compacted to run lengths; words under min_count are left out."""

    name = "disk_bins_sort"

    def __init__(self, k: int = 22, stranded: bool = False, bins: int | None = None, min_count: int = 1):
        super().__init__(k, stranded)
        self.bins, self.min_count = bins, min_count

    def count(self, reads):
        own = PartitionFileCounter(self.k, self.stranded, self.bins or parts_for(reads, 2 << 20, 64))
        return packed_counts(own.files(reads), 2 * self.k, own.range_of(own.parts), self.min_count)


class MinimizerBinCounter(KmerCounter):
    """Super-k-mers in bins by minimizer: fewer bytes on the way to disk than separate words."""

    name = "disk_bins_minimizer"

    def __init__(self, k: int = 22, stranded: bool = False, bins: int | None = None):
        super().__init__(k, stranded)
        self.bins = bins

    def count(self, reads):
        bins = self.bins or parts_for(reads, 2 << 20, 64)
        return counts_of_blocks(super_kmer_blocks(reads, self.k, bins), self.k, self.stranded)


class ContainerCounter(KmerCounter):
    """Three containers with their own errors.

    'hash' is exact; 'bloom_sort' counts what a filter passes, so some single words come with it; 'cache' counts in
    a bounded table per task whose rarest words are evicted, so some words come too low or not at all.
    """

    name = "frequent_containers"

    def __init__(self, k: int = 22, stranded: bool = False, kind: str = "hash", expected_frequent: int | None = None, cache_keys: int = 500_000):
        super().__init__(k, stranded)
        if kind not in ("hash", "bloom_sort", "cache"):
            raise ValueError("kind is 'hash', 'bloom_sort' or 'cache'")
        self.kind, self.expected, self.cache_keys, self.exact = kind, expected_frequent, cache_keys, kind == "hash"

    def count(self, reads):
        if self.kind == "hash":
            return exact_counts(reads, self.k, self.stranded)
        if self.kind == "bloom_sort":
            return BloomGatedCounter(self.k, self.stranded, self.expected).count(reads, keep_false=True)
        k, stranded, limit = self.k, self.stranded, self.cache_keys

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            keys, cnt = np.zeros(0, np.uint64), np.zeros(0, np.int64)
            for batch in batches:
                for _, raw, ends in read_blocks(batch):
                    fresh = windows_of(raw, ends, k, stranded)[2]
                    keys, at = np.unique(np.concatenate([keys, fresh]), return_inverse=True)
                    cnt = np.bincount(at, weights=np.concatenate([cnt, np.ones(len(fresh))]), minlength=len(keys)).astype(np.int64)
                    if len(keys) > limit:
                        top = np.sort(np.argpartition(-cnt, limit - 1)[:limit])
                        keys, cnt = keys[top], cnt[top]
            yield pa.RecordBatch.from_arrays([as_signed(keys), pa.array(cnt)], names=["kmer", "cnt"])

        merged = reads.select("read_id", "seq").mapInArrow(run, "kmer long, cnt long").groupBy("kmer").agg(F.sum("cnt").alias("cnt"))
        return merged.filter(F.col("cnt") > 1)

    def errors(self, truth: DataFrame, min_count: int = 2) -> DataFrame:
        """False positives and negatives against exact counts, for words of at least min_count."""
        t = truth.filter(F.col("cnt") >= min_count).select("kmer", F.lit(1).alias("t"))
        own = self.counts.filter(F.col("cnt") >= 1).select("kmer", F.lit(1).alias("o"))
        return t.join(own, "kmer", "full").agg(F.count_if(F.col("t").isNull()).alias("false_positives"), F.count_if(F.col("o").isNull()).alias("false_negatives"))


class SketchCounter(KmerCounter):
    """The prime-table sketch behind the common interface."""

    name, exact, online, random_access = "prime_sketch", False, True, True

    def __init__(self, k: int = 22, stranded: bool = False, spec: SketchSpec | None = None, fpr: float = 0.01):
        super().__init__(k, stranded)
        self.spec, self.fpr = spec, fpr

    def build(self, reads):
        self.spec = self.spec or SketchSpec.for_reads(reads, self.fpr, k=self.k, stranded=self.stranded)
        from ..operators.spectrum import by_parts

        self.reads, self.sketch = reads, PrimeSketch.build(reads, self.spec)
        if not by_parts(self.spec):  # else its histogram and look-ups count what they ask for
            self.sketch = self.sketch.stored(stored)
        return self

    def histogram(self):
        from ..operators.spectrum import abundance_sketch

        return abundance_sketch(self.reads, self.sketch)

    def lookup(self, queries):
        return lookup(queries, self.sketch)


COUNTERS = {c.name: c for c in (HashCounter, SpillingHashCounter, SuffixOrderCounter, BloomGatedCounter, PartitionFileCounter, SortedBinCounter, MinimizerBinCounter, ContainerCounter, SketchCounter)}

