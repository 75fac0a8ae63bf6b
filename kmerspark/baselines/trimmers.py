"""Quality trimmers: reads with scores per base (Phred), cut without looking at other reads."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Error probability of each score, in millionths (10^6 * 10^(-q/10), rounded).
ERROR_PPM = np.rint(1_000_000 * 10 ** (-np.arange(128) / 10)).astype(np.int64)


def qtrim_error_sum(reads: DataFrame, limit: float = 0.05, min_len: int = 1) -> DataFrame:
    """Quality trimmer 1: the stretch with the largest sum of (limit - error probability); the first, longest of equals."""
    ppm = int(limit * 1_000_000)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            quals = batch.column(batch.schema.get_field_index("qual")).to_pylist()
            begin, size = [], []
            for q in quals:
                sums = np.concatenate([[0], np.cumsum(ppm - ERROR_PPM[np.array(q or [], np.int64)])])
                low = np.minimum.accumulate(sums)
                gain = sums - low
                top = gain.max()
                if top <= 0:
                    begin.append(0)
                    size.append(0)
                    continue
                ends = np.flatnonzero(gain == top)
                starts = np.array([np.flatnonzero(sums[: e + 1] == low[e])[0] for e in ends])
                first = starts.min()
                begin.append(int(first))
                size.append(int(ends[starts == first].max() - first))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(begin, pa.int32()), pa.array(size, pa.int32())], names=["read_id", "_begin", "_size"])

    cut = reads.select("read_id", "qual").mapInArrow(run, "read_id long, _begin int, _size int")
    return _cut(reads.join(cut, "read_id"), reads.columns, min_len)


def qtrim_tail(reads: DataFrame, min_q: int = 20, min_len: int = 30) -> DataFrame:
    """Quality trimmer 2: bases below min_q go from the 3' end on; reads left too short go."""
    keep = F.array_max(F.transform("qual", lambda q, i: F.when(q >= min_q, i + 1).otherwise(0)))
    return _cut(reads.withColumn("_begin", F.lit(0)).withColumn("_size", F.coalesce(keep, F.lit(0))), reads.columns, min_len)


def _cut(df: DataFrame, columns: list[str], min_len: int) -> DataFrame:
    out = df.withColumn("seq", F.substr("seq", F.col("_begin") + 1, F.col("_size"))).withColumn("qual", F.slice("qual", F.col("_begin") + 1, F.col("_size")))
    return out.filter(F.col("_size") >= max(1, min_len)).select(*columns)
