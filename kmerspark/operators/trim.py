"""Error profiles by position, and trimming of reads at rare words."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.dna import windows_of
from .kmers import explode_kmers, read_blocks
from .lookup import broadcast_tables, lookup
from .packed import END, PackedWords
from .sketch import PrimeSketch, SketchSpec, probe_arrays


def error_profile(reads: DataFrame, sketch: PrimeSketch, max_count: int = 1, by: str = "pos", group_cols: tuple[str, ...] = ()) -> DataFrame:
    """Share of words counted at most `max_count` times, by start position ('pos') or from the 3' end ('end_pos')."""
    k = sketch.spec.k
    found = lookup(explode_kmers(reads, k, sketch.spec.stranded), sketch)
    if by == "end_pos" or group_cols:
        found = found.join(reads.select("read_id", F.length("seq").alias("_len"), *group_cols), "read_id")
    if by == "end_pos":
        found = found.withColumn("end_pos", (F.col("_len") - k - F.col("pos")).cast("int"))
    rare = F.count_if(F.col("est") <= max_count)
    return found.groupBy(*group_cols, by).agg(F.count("*").alias("n"), rare.alias("n_rare"), F.round(rare / F.count("*"), 6).alias("share"))


def window_counts(reads: DataFrame, sketch: PrimeSketch, limit: int) -> DataFrame:
    """read_id, n (words), n_low (words below `limit`), first_low (position of the first, or null).

    Small sketches are probed where the reads are; for others the words travel and three numbers a read come back.
    """
    spec = sketch.spec
    from ..plans.strategy import choose

    if choose(spec).strategy != "broadcast":
        found = lookup(explode_kmers(reads, spec.k, spec.stranded), sketch, "cells")
        low = F.col("est") < limit
        own = found.groupBy("read_id").agg(F.count("*").alias("n"), F.count_if(low).alias("n_low"), F.min(F.when(low, F.col("pos"))).alias("first_low"))
        return reads.select("read_id").join(own, "read_id", "left").select("read_id", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("n_low", F.lit(0)).alias("n_low"), "first_low")
    shared = broadcast_tables(sketch)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                read, pos, code = windows_of(raw, ends, spec.k, spec.stranded)
                low = probe_arrays(shared.value, spec, code) < limit
                n = np.bincount(read, minlength=len(ends))
                first = np.full(len(ends), np.iinfo(np.int32).max)
                np.minimum.at(first, read[low], pos[low])
                some = np.bincount(read[low], minlength=len(ends))
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(n), pa.array(some), pa.array(first.astype(np.int32), mask=some == 0)], names=["read_id", "n", "n_low", "first_low"])

    return reads.select("read_id", "seq").mapInArrow(run, "read_id long, n long, n_low long, first_low int")


def trim_reads(reads: DataFrame, sketch: PrimeSketch, cutoff: int = 2, cut: str = "last_base", keep_short: bool = False) -> DataFrame:
    """Reads up to their first word below the cut-off; reads left shorter than a word are dropped.

    'last_base' takes off from the base that completes the word on; 'kmer_start' from the word's first base on.
    Reads without a valid word are dropped unless keep_short.
    """
    from ..plans.strategy import choose

    if choose(sketch.spec).strategy == "broadcast" and not keep_short:
        return _trim_in_place(reads, sketch, cutoff, cut)
    k = sketch.spec.k
    stats = window_counts(reads, sketch, cutoff)
    at = F.col("first_low") + (k - 1 if cut == "last_base" else 0)
    joined = reads.join(stats, "read_id")
    out = joined.withColumn("seq", F.when(F.col("first_low").isNull(), F.col("seq")).otherwise(F.substr("seq", F.lit(1), at)))
    kept = (F.length("seq") >= k) & (F.col("n") > 0)
    if keep_short:
        kept |= F.col("n") == 0
    return out.filter(kept).select(*reads.columns)


def _trim_in_place(reads: DataFrame, sketch: PrimeSketch, cutoff: int, cut: str) -> DataFrame:
    """`trim_reads` where the reads are: nothing is joined to them."""
    spec, shared = sketch.spec, broadcast_tables(sketch)
    k, more = spec.k, spec.k - 1 if cut == "last_base" else 0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch):
                read, pos, code = windows_of(raw, ends, spec.k, spec.stranded)
                low = probe_arrays(shared.value, spec, code) < cutoff
                length = np.diff(ends, prepend=0)
                end = length - more
                np.minimum.at(end, read[low], pos[low])
                end += more
                keep = (end >= k) & (np.bincount(read, minlength=len(ends)) > 0)
                at = np.arange(len(raw)) - np.repeat(ends - length, length)
                data = raw[at < np.repeat(np.where(keep, end, 0), length)]
                offsets = np.concatenate([[0], np.cumsum(end[keep])]).astype(np.int32)
                seq = pa.StringArray.from_buffers(len(offsets) - 1, pa.py_buffer(offsets), pa.py_buffer(data))
                rows = rows.filter(pa.array(keep))
                yield pa.RecordBatch.from_arrays([seq if n == "seq" else rows.column(i) for i, n in enumerate(rows.schema.names)], names=rows.schema.names)

    return reads.filter("read_id IS NOT NULL").mapInArrow(run, reads.schema)


def filter_reads(reads: DataFrame, sketch: PrimeSketch, cutoff: int = 2, mode: str = "any") -> DataFrame:
    """Reads without any ('any') or with not only ('all') words below the cut-off."""
    stats = window_counts(reads, sketch, cutoff)
    bad = F.col("n_low") > 0 if mode == "any" else F.col("n_low") == F.col("n")
    return reads.join(stats.filter(bad), "read_id", "left_anti")


def trim_iterative(reads: DataFrame, spec: SketchSpec, store: Callable[[DataFrame], DataFrame], rounds: int = 6, cutoff: int = 2, until: float | None = None) -> tuple[DataFrame, DataFrame]:
    """Trim with a fresh sketch of the same size each round; the reads left, and a log of the rounds.

    fpr is against the exact counts of the round's input; bases removed are in percent of the first input's; words
    are those of the round's output.
    """
    spark, log = reads.sparkSession, []
    total = reads.agg(F.sum(F.length("seq"))).first()[0] or 0
    bases = total
    words = PackedWords(reads, spec.k, spec.stranded, ends_too=True)
    for i in range(1, rounds + 1):
        counts = words.counts().withColumn("cnt", F.col("cnt").bitwiseAND(F.lit(END - 1)))
        sketch = (PrimeSketch.build(reads, spec) if spec.fits_a_task() else PrimeSketch.of_counts(counts, spec)).stored(store)
        wrong = _share_wrong(words, counts, sketch)
        reads = store(trim_reads(reads, sketch, cutoff))
        words.discard()
        words = PackedWords(reads, spec.k, spec.stranded, ends_too=True)
        left = reads.agg(F.sum(F.length("seq"))).first()[0] or 0
        log.append((i, round(wrong or 0.0, 6), round(100 * (bases - left) / max(1, total), 6), *words_left(words)))
        removed, bases = bases - left, left
        if until is not None and removed <= until * total:
            break
    words.discard()
    return reads, spark.createDataFrame(log, "round int, fpr double, bases_removed double, n_distinct long, n_unique long, n_unique_3p long")


def words_left(words: PackedWords) -> tuple[int, int, int]:
    """Distinct words, words that occur once, and those of them that end a read, of words with ends_too."""
    return words.sums(lambda _, cnt: (len(cnt), np.count_nonzero(cnt & (END - 1) == 1), np.count_nonzero(cnt == END + 1)), 3)


def _share_wrong(words: PackedWords, counts: DataFrame, sketch: PrimeSketch) -> float | None:
    """The share of words whose count in the sketch is not theirs."""
    from ..plans.strategy import choose

    spec = sketch.spec
    if choose(spec).strategy != "broadcast":
        return lookup(counts, sketch).agg(F.count_if(F.col("est") != F.least("cnt", F.lit(spec.cap))) / F.count("*")).first()[0]
    shared = broadcast_tables(sketch)
    n, wrong = words.sums(lambda code, cnt: (len(code), np.count_nonzero(probe_arrays(shared.value, spec, code) != np.minimum(cnt & (END - 1), spec.cap))), 2)
    return wrong / n if n else None
