"""Sketches that grow while a stream runs.

Counts only ever grow, so an update must not be applied twice: every version of a sketch is a new folder, named by
the batch that made it, and a batch that finds its version committed does nothing.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

from ..operators.kmers import combined_kmers
from ..operators.lookup import lookup
from ..operators.normalize import decide
from ..operators.sketch import PrimeSketch, SketchSpec
from ..operators.store import publish

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


class VersionedSketch:
    """A sketch under a folder: v=<batch>/cells, made visible by its commit file."""

    def __init__(self, spark: SparkSession, path: str, spec: SketchSpec):
        self.spark, self.path, self.spec = spark, path, spec
        hadoop = spark._jvm.org.apache.hadoop.fs
        self._at = lambda p: hadoop.Path(f"{path}/{p}")
        self._fs = self._at("").getFileSystem(spark._jsc.hadoopConfiguration())

    def version(self) -> int:
        """The last batch that is counted in; -1 for none."""
        if not self._fs.exists(self._at("commits")):
            return -1
        return max((int(f.getPath().getName()) for f in self._fs.listStatus(self._at("commits")) if f.getPath().getName().isdigit()), default=-1)

    def current(self) -> PrimeSketch:
        v = self.version()
        if v < 0:
            return PrimeSketch.empty(self.spark, self.spec)
        name = self.spark.read.text(f"{self.path}/commits/{v:010d}").first()[0]
        return PrimeSketch(self.spec, self.spark.read.schema("table_id tinyint, cell long, cnt long").parquet(f"{self.path}/{name}"))

    def update(self, counts: DataFrame, batch_id: int) -> bool:
        """Count a batch in, exactly once; False if it was counted before."""
        if batch_id <= self.version():
            return False
        name = f"v{batch_id}-{uuid.uuid4().hex}"
        self.current().merge(PrimeSketch.of_counts(counts, self.spec)).cells.write.parquet(f"{self.path}/{name}")
        return publish(self.spark, f"{self.path}/commits/{batch_id:010d}", name)


def count_stream(stream: DataFrame, sketch: VersionedSketch, checkpoint: str, available_now: bool = True):
    """Count a stream of reads (read_id, seq) into a versioned sketch; returns the started query."""
    spec = sketch.spec

    def step(batch: DataFrame, batch_id: int) -> None:
        sketch.update(combined_kmers(batch, spec.k, spec.stranded).groupBy("kmer").agg(F.sum("cnt").alias("cnt")), batch_id)

    writer = stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def normalize_stream(stream: DataFrame, sketch: VersionedSketch, out: str, checkpoint: str, coverage: int = 20):
    """Keep, per micro-batch, the reads that the sketch of all kept before finds rare; count them, and write them out.

    A batch writes to a folder of its own, so a repeated batch overwrites the same rows.
    """
    spec = sketch.spec

    def step(batch: DataFrame, batch_id: int) -> None:
        if batch_id <= sketch.version():
            return
        decide(batch, sketch.current(), coverage).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")
        kept = batch.sparkSession.read.schema(batch.schema).parquet(f"{out}/batch={batch_id}")
        sketch.update(combined_kmers(kept, spec.k, spec.stranded).groupBy("kmer").agg(F.sum("cnt").alias("cnt")), batch_id)

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class _ShardCounter(StatefulProcessor):
    """Counters of one shard as one value of bytes; emits each key of a batch with its count after the batch."""

    def __init__(self, primes: tuple[int, ...], cap: int):
        self.primes, self.cap = primes, cap

    def init(self, handle) -> None:
        self.state = handle.getValueState("counters", "raw binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        size = sum(self.primes)
        flat = np.frombuffer(self.state.get()[0], np.uint8).copy() if self.state.exists() else np.zeros(size, np.uint8)
        tables, at = [], 0
        for p in self.primes:
            tables.append(flat[at : at + p])
            at += p
        codes = np.concatenate([r["kmer"].to_numpy(np.int64) for r in rows]).view(np.uint64)
        keys, cnt = np.unique(codes, return_counts=True)
        for t, p in zip(tables, self.primes, strict=True):
            spots, where = np.unique((keys % np.uint64(p)).astype(np.int64), return_inverse=True)
            t[spots] = np.minimum(t[spots].astype(np.int64) + np.bincount(where, weights=cnt).astype(np.int64), self.cap)
        est = np.min([t[(keys % np.uint64(p)).astype(np.int64)] for t, p in zip(tables, self.primes, strict=True)], axis=0)
        self.state.update((flat.tobytes(),))
        yield pd.DataFrame({"kmer": keys.view(np.int64), "est": est.astype(np.int64)})

    def close(self) -> None:
        pass


def online_counts(occurrences: DataFrame, spec: SketchSpec, shards: int = 8) -> DataFrame:
    """A stream of words in, each with its count so far out: update and look-up in one pass over keyed state.

    `spec` is the size of one shard's tables; the session needs the RocksDB state store for states beyond memory.
    """
    dealt = occurrences.select(F.pmod(F.xxhash64("kmer"), F.lit(shards)).cast("int").alias("shard"), "kmer")
    return dealt.groupBy("shard").transformWithStateInPandas(_ShardCounter(spec.primes, spec.cap), "kmer long, est long", "Update", "None")


class OnlineCounter:
    """Interleaved updates and look-ups of micro-batches on one handle."""

    def __init__(self, spark: SparkSession, spec: SketchSpec):
        self.sketch = PrimeSketch.empty(spark, spec)

    def update_and_get(self, kmers: DataFrame, store) -> DataFrame:
        """Count the batch (kmer), then give each of its distinct words with its count."""
        self.sketch = self.sketch.increment(kmers).stored(store)
        return lookup(kmers.select("kmer").distinct(), self.sketch)


def event_words(events: DataFrame, k: int, base: Column) -> DataFrame:
    """user_id, ts, kmer: words of k consecutive event types of each user; a break in the alphabet gives none.

    A user's k-1 events before are a bounded frame of a window by user.
    """
    from pyspark.sql import Window

    frame = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-(k - 1), 0)
    word = F.array_join(F.collect_list(base).over(frame), "")
    out = events.select("user_id", F.col("ts").cast("timestamp").alias("ts"), word.alias("word"))
    return out.filter((F.length("word") == k) & ~F.col("word").contains("N"))


def windowed_counts(events: DataFrame, window: str = "10 minutes", slide: str | None = None, gap: str | None = None, watermark: str | None = "10 minutes", by: str = "event_type") -> DataFrame:
    """Events by window (tumbling, sliding, or by session with a gap); late rows beyond the watermark are dropped."""
    ts = F.col("ts").cast("timestamp")
    rows = events.withColumn("ts", ts)
    if watermark and events.isStreaming:
        rows = rows.withWatermark("ts", watermark)
    w = F.session_window("ts", gap) if gap else F.window("ts", window, slide) if slide else F.window("ts", window)
    out = rows.groupBy(w.alias("w"), by).agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), by, "n")


def dedup_stream(stream: DataFrame, watermark: str = "10 minutes", keys: list[str] | None = None) -> DataFrame:
    """Rows of one read_id (or of the given keys) within the watermark once."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys or ["read_id"])


def dropped_late(progress: list) -> int:
    """Rows that a stream's stateful operators have dropped as later than the watermark, over all its batches."""
    return sum(s["numRowsDroppedByWatermark"] for p in progress for s in p["stateOperators"])
