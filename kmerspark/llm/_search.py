"""What the vector searches share: clean vectors, blocks of queries, and merging of ranked lists."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Queries that are broadcast at a time.
QUERY_BLOCK = 8_192
#: Below every whole-number score, and safe to negate.
LOWEST = -(2**62)


def clean_vectors(df: DataFrame, id_col: str, vector_col: str, nonzero: bool = False) -> DataFrame:
    """id and vector (doubles) of the rows that take part: no null id, no null vector, all components finite."""
    v = df.select(df[id_col].cast("long").alias("id"), df[vector_col].cast("array<double>").alias("v"))
    good = F.col("id").isNotNull() & (F.size("v") > 0) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    if nonzero:
        good &= F.exists("v", lambda x: x != 0)
    return v.filter(good)


def to_matrix(vectors: pa.Array) -> np.ndarray:
    vectors = vectors.cast(pa.large_list(pa.float64()))
    return np.asarray(vectors.flatten()).reshape(len(vectors), -1) if len(vectors) else np.zeros((0, 0))


def distinct_rows(rows: np.ndarray, ids: np.ndarray, keep: int) -> np.ndarray:
    """Places of the rows to keep: of equal rows, those with the `keep` smallest distinct ids, keep - 1 of each id.

    Equal rows score alike against any query and ties go to the smaller id, so no other copy can be among a query's
    keep - 1 best. A query may itself be one of the copies: all rows of its id are then out, however many they are.
    """
    order = np.lexsort((ids, *_words(rows).T))
    same = np.concatenate([[False], (rows[order][1:] == rows[order][:-1]).all(axis=1)]) if len(rows) else np.zeros(0, bool)
    at = np.arange(len(rows))
    again = same & np.concatenate([[False], ids[order][1:] == ids[order][:-1]]) if len(rows) else same
    nth = np.cumsum(~again)  # by distinct id
    return np.sort(order[(nth - nth[_starts(same)] < keep) & (at - _starts(again) < max(keep - 1, 1))])


def _starts(follows: np.ndarray) -> np.ndarray:
    """For each place, the first place of its run."""
    return np.maximum.accumulate(np.where(follows, 0, np.arange(len(follows))))


def _words(rows: np.ndarray) -> np.ndarray:
    """Two 64-bit keys of each row, equal for equal rows."""
    weights = np.random.default_rng(7).standard_normal((rows.shape[1], 2))
    return (rows[:, :, None] * weights).sum(axis=1) if rows.size else np.zeros((len(rows), 2))


def query_blocks(queries: DataFrame, size: int = QUERY_BLOCK) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Ids and vectors of the queries, at most `size` at a time on the driver; ids in ascending order."""
    low, n = None, queries.count()
    for _ in range(-(-n // size)):
        part = (queries if low is None else queries.filter(F.col("id") > low)).orderBy("id").limit(size).toArrow()
        ids = part["id"].to_numpy()
        if not len(ids):
            return
        low = int(ids[-1])
        yield ids, to_matrix(part["v"].combine_chunks())


class TopK:
    """The best k candidates of each of many queries: higher score first, then smaller id."""

    def __init__(self, n: int, k: int, dtype=np.float64):
        low = -np.inf if np.issubdtype(dtype, np.floating) else LOWEST
        self.k, self.score, self.id = k, np.full((n, k), low, dtype), np.full((n, k), np.iinfo(np.int64).max)

    def floor(self) -> np.ndarray:
        """The score that a candidate must reach, for each query."""
        return self.score[:, -1]

    def add(self, rows: np.ndarray, score: np.ndarray, ids: np.ndarray) -> None:
        """Offer to each query in `rows` a row of candidates."""
        score = np.concatenate([self.score[rows], score], axis=1)
        ids = np.concatenate([self.id[rows], np.broadcast_to(ids, (len(rows), ids.shape[-1]))], axis=1)
        order = np.lexsort((ids, -score), axis=1)[:, : self.k]
        self.score[rows], self.id[rows] = np.take_along_axis(score, order, 1), np.take_along_axis(ids, order, 1)

    def batch(self, query_ids: np.ndarray) -> pa.RecordBatch:
        at = np.nonzero(self.id != np.iinfo(np.int64).max)
        return pa.RecordBatch.from_arrays([pa.array(query_ids[at[0]]), pa.array(self.id[at]), pa.array(self.score[at])], names=["query_id", "vec_id", "score"])


def merge_ranked(parts: list[DataFrame], k: int, empty: Callable[[], DataFrame]) -> DataFrame:
    """The k best of each query over all tasks' lists, ranked from 1."""
    if not parts:
        return empty()
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return out.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
