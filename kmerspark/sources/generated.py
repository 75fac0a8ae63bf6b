"""Reads that are made where they are read: a Python data source, and a stream at a given rate."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.dna import mixer

SCHEMA = "read_id long, seq string"


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class ReadsFromGenome(DataSource):
    """spark.read.format("reads_from_genome") with the options genome, reads, length (100), seed (42) and parts (8).

    Reads without errors, at the places that the simulation draws; any part can be made again.
    """

    @classmethod
    def name(cls) -> str:
        return "reads_from_genome"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.genome, self.n = options["genome"], int(options["reads"])
        self.length, self.seed, self.parts = int(options.get("length", 100)), int(options.get("seed", 42)), int(options.get("parts", 8))

    def partitions(self) -> list[Range]:
        edges = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [Range(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True)]

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        room = len(self.genome) - self.length + 1
        for a in range(partition.first, partition.last, 10_000):
            ids = range(a, min(a + 10_000, partition.last))
            starts = [int(hashlib.md5(f"s|{self.seed}|{i}".encode()).hexdigest()[:15], 16) % room for i in ids]
            yield pa.RecordBatch.from_arrays([pa.array(list(ids), pa.int64()), pa.array([self.genome[s : s + self.length] for s in starts])], names=["read_id", "seq"])


def reads_at_rate(spark: SparkSession, genome: str, per_batch: int = 1000, length: int = 100, seed: int = 42) -> DataFrame:
    """A stream of reads from a genome of bounded size, `per_batch` in each micro-batch, for trying out online counting."""
    ticks = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", per_batch).load()
    at = F.pmod(mixer("s", F.col("value"), seed=seed), F.lit(len(genome) - length + 1))
    return ticks.select(F.col("value").alias("read_id"), F.col("timestamp").alias("ts"), F.substr(F.lit(genome), (at + 1).cast("int"), F.lit(length)).alias("seq"))
