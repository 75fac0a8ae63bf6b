"""Abundance spectra: how many distinct words occur how often."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.sizing import size_for_fpr
from ..sources.simulate import draw
from .kmers import combined_kmers, estimate_distinct, exact_counts
from .lookup import lookup
from .packed import PackedWords
from .sketch import PrimeSketch, SketchSpec


def histogram(counts: DataFrame, column: str = "cnt") -> DataFrame:
    """abundance, n_kmers."""
    return counts.groupBy(F.col(column).alias("abundance")).agg(F.count("*").alias("n_kmers"))


def abundance_exact(reads: DataFrame, k: int = 22, stranded: bool = False) -> DataFrame:
    return histogram(exact_counts(reads, k, stranded))


#: Words that a part's filter is made for, and the rate at which it takes a new word for a known one.
PART_WORDS, LOST = 1_000_000, 0.001


def distinct_kmers(reads: DataFrame, k: int = 22, stranded: bool = False, seen: str = "exact", expected: int | None = None, lost: float = LOST) -> DataFrame:
    """Each distinct word of the input once. 'bloom' keeps no keys: a word is passed on when its filter bits are new.

    A word goes to one part, so a part's filter sees all its occurrences; a share `lost` of the words, at most, is
    taken for known. Parts and filters are sized for `expected` distinct words, which are estimated if not given.
    """
    words = combined_kmers(reads, k, stranded).select("kmer")
    if seen == "exact":
        return words.distinct()
    expected = max(1, expected or estimate_distinct(reads, k, stranded))
    parts = max(1, -(-expected // PART_WORDS))
    part_bits = math.ceil(size_for_fpr(1.2 * expected / parts, lost, 3, exact=True).memory) + 64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, bits = None, None
        for batch in batches:
            owner, codes = np.asarray(batch.column(0)), np.asarray(batch.column(1)).view(np.uint64)
            for p in np.unique(owner).tolist():
                if p != part:
                    part, bits = p, np.zeros(part_bits, bool)
                code = np.unique(codes[owner == p])
                at = [(draw(code, 11, s + 1) % np.uint64(part_bits)).astype(np.int64) for s in range(3)]
                known = bits[at[0]] & bits[at[1]] & bits[at[2]]
                for a in at:
                    bits[a] = True
                yield pa.RecordBatch.from_arrays([pa.array(code[~known].view(np.int64))], names=["kmer"])

    dealt = words.select(F.pmod(F.xxhash64("kmer"), F.lit(parts)).cast("int").alias("part"), "kmer")
    return dealt.repartition("part").sortWithinPartitions("part").mapInArrow(run, "kmer long")


def abundance_sketch(reads: DataFrame, sketch: PrimeSketch, seen: str = "exact", strategy: str = "auto") -> DataFrame:
    """The histogram of the sketch's counts over the distinct words of the input, which are read once more.

    A sketch of these very reads that is too large for a broadcast is made anew in parts (`packed`), and not by cells.
    """
    if strategy == "auto" and sketch.reads is reads and by_parts(sketch.spec):
        return PackedWords(reads, sketch.spec.k, sketch.spec.stranded, None if seen == "exact" else LOST).histogram(sketch.spec)
    words = distinct_kmers(reads, sketch.spec.k, sketch.spec.stranded, seen)
    return histogram(lookup(words, sketch, strategy), "est")


def by_parts(spec: SketchSpec) -> bool:
    """Whether all words get their counts by parts: no task can hold the tables."""
    from ..plans.strategy import choose

    return choose(spec).strategy == "sharded" and spec.layout == "primes" and spec.cap < 2**32


def spectrum_summary(hist: DataFrame) -> DataFrame:
    """Cumulative and relative columns of a histogram (a row per abundance)."""
    up = Window.orderBy("abundance").rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy()
    out = hist.withColumn("cumulative", F.sum("n_kmers").over(up)).withColumn("n_words", F.col("abundance") * F.col("n_kmers"))
    return out.withColumn("fraction", F.round(F.col("n_kmers") / F.sum("n_kmers").over(every), 6)).withColumn("cumulative_fraction", F.round(F.col("cumulative") / F.sum("n_kmers").over(every), 6))


def valley_and_peak(hist: DataFrame) -> dict[str, int]:
    """The first rise of the histogram (a cut-off for errors) and the peak beyond it (the coverage)."""
    rows = [(r["abundance"], r["n_kmers"]) for r in hist.filter("abundance < 1000").orderBy("abundance").collect()]  # at most 1000
    valley = next((a for (a, n), (_, m) in zip(rows[:-1], rows[1:], strict=True) if m > n), rows[-1][0] if rows else 0)
    beyond = [r for r in rows if r[0] >= valley]
    return {"valley": valley, "peak": max(beyond, key=lambda r: r[1])[0] if beyond else 0}


def estimate_coverage(hist: DataFrame) -> dict[str, float]:
    """Coverage from the peak, and the genome's size as the words beyond the valley over it."""
    at = valley_and_peak(hist)
    total = hist.filter(F.col("abundance") >= at["valley"]).agg(F.sum(F.col("abundance") * F.col("n_kmers"))).first()[0] or 0
    return at | {"genome_size": total / max(1, at["peak"])}


def repeat_kmers(reads: DataFrame, sketch: PrimeSketch, min_count: int) -> DataFrame:
    """Distinct words counted at least `min_count` times."""
    return lookup(distinct_kmers(reads, sketch.spec.k, sketch.spec.stranded), sketch).filter(F.col("est") >= min_count)


def classify_kmers(counts: DataFrame, cutoff: int = 2) -> DataFrame:
    """Words below the cut-off are likely errors in data of high coverage."""
    return counts.withColumn("kind", F.when(F.col("cnt") < cutoff, "error").otherwise("true"))
