"""Simulated reads from a genome, with truth and quality scores; every number comes from the portable mixer."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.dna import _CODE, decode_codes, mixer

SCHEMA = "read_id long, source string, seq string, start long, true_seq string, n_errors int, qual array<tinyint>"


def genome_string(contigs: DataFrame, limit: int | None = None) -> str:
    """The contigs end to end by id, at most `limit` bases: the reference of a simulation, held by the driver."""
    rows = contigs.orderBy("contig_id").toLocalIterator()
    out, size = [], 0
    for r in rows:
        out.append(r["seq"])
        size += len(r["seq"])
        if limit and size >= limit:
            break
    return "".join(out)[:limit]


def error_ppm(pos: np.ndarray, read_len: int, rate: float, profile: str) -> np.ndarray:
    """Errors per million at each position: flat, or rising with the third power (the same mean at the limit)."""
    ppm = int(rate * 1_000_000)
    return np.full(len(pos), ppm) if profile == "flat" else 4 * ppm * pos.astype(np.int64) ** 3 // read_len**3


def simulate_reads(spark: SparkSession, genome: str, coverage: int = 3, error_rate: float = 0.01, profile: str = "flat", read_len: int = 100, seed: int = 42, n_reads: int | None = None) -> DataFrame:
    """Reads at uniform places; each base is replaced with the profile's chance by another one.

    The genome is broadcast; the draws per base are a counter-based mix of (read, position), computed in the task,
    so any partition can be computed again.
    """
    n = n_reads if n_reads is not None else coverage * len(genome) // read_len
    shared = spark.sparkContext.broadcast(np.frombuffer(genome.encode(), np.uint8))
    starts = spark.range(n).select(F.col("id").alias("read_id"), F.pmod(mixer("s", F.col("id"), seed=seed), F.lit(len(genome) - read_len + 1)).alias("start"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pos = np.arange(read_len)
        limit = error_ppm(pos, read_len, error_rate, profile).astype(np.uint64)
        letters = np.frombuffer(b"ACGT", np.uint8)
        for batch in batches:
            ids, at = (np.asarray(c) for c in batch.columns)
            for a in range(0, len(ids), 20_000):
                i, s = ids[a : a + 20_000], at[a : a + 20_000]
                true = shared.value[s[:, None] + pos]
                cell = i[:, None].astype(np.uint64) * np.uint64(read_len) + pos.astype(np.uint64)
                wrong = draw(cell, seed, 1) % np.uint64(1_000_000) < limit
                other = (_CODE[true].astype(np.uint64) + np.uint64(1) + draw(cell, seed, 2) % np.uint64(3)) & np.uint64(3)
                seq = np.where(wrong, letters[other.astype(np.int64)], true)
                q = 40 - (36 * (pos / read_len) ** 3).astype(np.int64) - (draw(cell, seed, 3) % np.uint64(5)).astype(np.int64)
                q = np.maximum(2, q - np.where(wrong & (draw(cell, seed, 4) % np.uint64(10) < 8), 20, 0)).astype(np.int8)
                offsets = pa.array(np.arange(0, len(i) * read_len + 1, read_len), pa.int32())
                text = lambda m: pa.Array.from_buffers(pa.string(), len(m), [None, offsets.buffers()[1], pa.py_buffer(np.ascontiguousarray(m))])
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(["sim"] * len(i)), text(seq), pa.array(s), text(true), pa.array(wrong.sum(axis=1), pa.int32()), pa.ListArray.from_arrays(offsets, pa.array(q.ravel()))], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return starts.mapInArrow(run, SCHEMA)


def draw(cell: np.ndarray, seed: int, stream: int) -> np.ndarray:
    """A pseudo-random 64-bit number for each cell of a stream (a counter through a bijective mix)."""
    with np.errstate(over="ignore"):
        x = cell * np.uint64(4) + np.uint64(stream - 1) + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
        return x ^ (x >> np.uint64(31))


def random_kmers(spark: SparkSession, n: int, k: int = 22, seed: int = 42) -> DataFrame:
    """n draws of random words of k bases, as reads of that length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = np.asarray(batch.column(0))
            code = draw(ids.astype(np.uint64), seed, 1) & np.uint64(4**k - 1 if k < 32 else 2**64 - 1)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(["random"] * len(ids)), pa.array(decode_codes(code, k), pa.string())], names=["read_id", "source", "seq"])

    return spark.range(n).mapInArrow(run, "read_id long, source string, seq string")
