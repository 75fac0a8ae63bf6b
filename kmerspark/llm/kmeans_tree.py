"""Nearest neighbours by a hierarchical k-means tree with best-bin-first traversal.

The tree is fitted on a bounded sample; every row is then assigned to a leaf. A query walks the tree, in a task, through
a priority queue of branches by distance and visits leaves in that order. How many leaves is calibrated: visits are
widened until sample queries reach the wanted recall against brute force, and for each query further until its
leaves hold enough rows. Queries travel to the leaves they visit; a leaf's rows are dealt to several tasks if they are
many, and each is read once for all queries. What leaves a task is k rows a query and leaf.
"""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._search import TopK, clean_vectors, distinct_rows, merge_ranked, to_matrix
from ._state import stored

#: Rows that the tree is fitted on at most, the first by a seeded hash of their ids.
SAMPLE_ROWS = 20_000
BRANCHES = 8
LEAF_ROWS = 64
CALIBRATION_QUERIES = 400
RECALL = 0.97
#: Rows of a leaf that one task holds; queries stream past them.
PART_ROWS = 16_384
SEED = 42


@dataclass
class KMeansTree:
    """Unit-length centres of the nodes; `children` of inner nodes, `leaf` (or -1) of all."""

    centre: np.ndarray
    children: list[list[int]]
    leaf: np.ndarray
    visits: int = 1

    @classmethod
    def fit(cls, rows: np.ndarray, branches: int = BRANCHES, leaf_rows: int = LEAF_ROWS, seed: int = SEED) -> KMeansTree:
        rng = np.random.default_rng(seed)
        centre, children, leaf, n_leaves = [rows.mean(axis=0)], [[]], [-1], 0
        todo = [(0, np.arange(len(rows)))]
        while todo:
            node, own = todo.pop()
            groups = _kmeans(rows[own], branches, rng) if len(own) > leaf_rows else []
            if len(groups) < 2:
                leaf[node], n_leaves = n_leaves, n_leaves + 1
                continue
            for mean, members in groups:
                centre.append(mean)
                children.append([])
                leaf.append(-1)
                children[node].append(len(centre) - 1)
                todo.append((len(centre) - 1, own[members]))
        return cls(np.stack(centre), children, np.array(leaf))

    @property
    def leaves(self) -> int:
        return int(self.leaf.max()) + 1

    def assign(self, rows: np.ndarray) -> np.ndarray:
        """The leaf of each row: at every node on to the nearest child."""
        out, todo = np.zeros(len(rows), np.int64), [(0, np.arange(len(rows)))]
        while todo:
            node, own = todo.pop()
            if not len(own):
                continue
            if self.leaf[node] >= 0:
                out[own] = self.leaf[node]
                continue
            kids = self.children[node]
            c = self.centre[kids]
            best = np.argmin((c**2).sum(axis=1) - 2 * rows[own] @ c.T, axis=1)
            todo += [(kid, own[best == i]) for i, kid in enumerate(kids)]
        return out

    def order(self, query: np.ndarray) -> Iterator[int]:
        """Leaves by best bin first."""
        tick = itertools.count()
        heap = [(0.0, next(tick), 0)]
        while heap:
            _, _, node = heapq.heappop(heap)
            if self.leaf[node] >= 0:
                yield int(self.leaf[node])
            else:
                kids = self.children[node]
                c = self.centre[kids]
                for d, kid in zip(((c - query) ** 2).sum(axis=1).tolist(), kids, strict=True):
                    heapq.heappush(heap, (d, next(tick), kid))

    def calibrate(self, rows: np.ndarray, k: int, recall: float = RECALL, queries: int = CALIBRATION_QUERIES, seed: int = SEED) -> None:
        """Widen the visits until the k nearest sample rows of sample queries are reached with the wanted recall."""
        if len(rows) < 2 or self.leaves < 2:
            self.visits = self.leaves
            return
        leaf = self.assign(rows)
        picked = np.random.default_rng(seed).permutation(len(rows))[:queries]
        k = min(k, len(rows) - 1)
        needed = np.zeros((len(picked), k), np.int64)
        for i, q in enumerate(picked.tolist()):
            near = rows @ rows[q]
            near[q] = -np.inf
            turn = np.empty(self.leaves, np.int64)
            turn[list(self.order(rows[q]))] = np.arange(1, self.leaves + 1)
            needed[i] = turn[leaf[np.argpartition(-near, k - 1)[:k]]]
        self.visits = int(np.sort(needed, axis=None)[int(np.ceil(recall * needed.size)) - 1])


def _kmeans(rows: np.ndarray, k: int, rng: np.random.Generator, turns: int = 8) -> list[tuple[np.ndarray, np.ndarray]]:
    c = rows[rng.choice(len(rows), min(k, len(rows)), replace=False)].copy()
    for _ in range(turns):
        own = np.argmin((c**2).sum(axis=1) - 2 * rows @ c.T, axis=1)
        for i in range(len(c)):
            if (at := own == i).any():
                c[i] = rows[at].mean(axis=0)
    own = np.argmin((c**2).sum(axis=1) - 2 * rows @ c.T, axis=1)
    return [(c[i], np.flatnonzero(own == i)) for i in range(len(c)) if (own == i).any()]


def cosine(queries: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Cosines of paired vectors in double precision, the same for equal vectors wherever they stand."""
    dot = (queries * rows).sum(axis=-1)
    return dot / (np.sqrt((queries * queries).sum(axis=-1)) * np.sqrt((rows * rows).sum(axis=-1)))


def nearest(rows: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", recall: float = RECALL) -> DataFrame:
    """query_id, rank, vec_id, score: the k rows of largest cosine found for each query, but for its own.

    Ties go to the smaller id. Rows whose vector is null, empty or zero or holds null or non-finite components, and
    rows without an id, take no part, nor do they as queries. Rows of another dimension than the query's are no
    candidates of it. Fewer than k candidates: all of them. Empty tables give an empty result.
    """
    spark = rows.sparkSession
    data = clean_vectors(rows, id_col, vector_col, nonzero=True)
    every = clean_vectors(queries, id_col, vector_col, nonzero=True).dropDuplicates(["id"])
    parts = []
    for dim in [r[0] for r in data.select(F.size("v").alias("d")).distinct().collect()]:
        own = data.filter(F.size("v") == dim)
        sample = to_matrix(own.orderBy(F.xxhash64(F.lit(SEED), "id"), "id").limit(SAMPLE_ROWS).select("v").toArrow()["v"].combine_chunks())
        sample = _unit(sample)
        sample = sample[distinct_rows(sample, np.arange(len(sample)), 2)]
        tree = KMeansTree.fit(sample)
        tree.calibrate(sample, k, recall)
        shared = spark.sparkContext.broadcast(tree)  # at most SAMPLE_ROWS leaves
        index = stored(own.mapInArrow(_assign(shared, k), "id long, v array<double>, leaf int"))
        sizes = index.groupBy("leaf").agg(F.count("*").alias("n")).withColumn("wide", F.ceil(F.col("n") / PART_ROWS).cast("int"))
        sizes = stored(sizes)
        held = np.zeros((2, tree.leaves), np.int64)
        for r in sizes.collect():  # a row per leaf, SAMPLE_ROWS at most
            held[:, r["leaf"]] = r["n"], r["wide"]
        dealt = index.join(F.broadcast(sizes.select("leaf", "wide")), "leaf").select("leaf", F.pmod(F.xxhash64("id"), F.col("wide")).cast("int").alias("part"), F.lit(0).alias("kind"), "id", "v")
        asked = every.filter(F.size("v") == dim).mapInArrow(_route(shared, held, k), "leaf int, part int, kind int, id long, v array<double>")
        met = dealt.unionByName(asked).repartition("leaf", "part").sortWithinPartitions("leaf", "part", "kind")
        parts.append(met.mapInArrow(_score(k), "query_id long, vec_id long, score double"))
    return merge_ranked(parts, k, lambda: spark.createDataFrame([], "query_id long, rank int, vec_id long, score double"))


def _unit(rows: np.ndarray) -> np.ndarray:
    """Rows of length 1; scaled by the largest component first, so that squares neither overflow nor vanish."""
    rows = rows / np.abs(rows).max(axis=1, keepdims=True) if rows.size else rows
    return rows / np.sqrt((rows * rows).sum(axis=1, keepdims=True)) if rows.size else rows


def _assign(shared, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                rows, ids = to_matrix(batch.column(1)), np.asarray(batch.column(0))
                keep = distinct_rows(rows, ids, k + 1)
                leaf = shared.value.assign(_unit(rows[keep]))
                order = np.argsort(leaf, kind="stable")
                yield pa.RecordBatch.from_arrays([*(c.take(pa.array(keep[order])) for c in batch.columns), pa.array(leaf[order], pa.int32())], names=["id", "v", "leaf"])

    return run


def _route(shared, held: np.ndarray, k: int):
    """Each query once for every part of every leaf that it visits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                own = batch.slice(at, 256)
                goes: list[tuple[int, int, int]] = []
                for i, q in enumerate(_unit(to_matrix(own.column(1)))):
                    seen = 0
                    for n, leaf in enumerate(tree.order(q), 1):
                        goes += [(i, leaf, part) for part in range(held[1, leaf])]
                        seen += int(held[0, leaf])
                        if n >= tree.visits and seen > k:
                            break
                who, leaf, part = np.array(goes, np.int64).reshape(-1, 3).T
                yield pa.RecordBatch.from_arrays([pa.array(leaf, pa.int32()), pa.array(part, pa.int32()), pa.array(np.ones(len(who)), pa.int32()), *(c.take(pa.array(who)) for c in own.columns)], names=["leaf", "part", "kind", "id", "v"])

    return run


def _score(k: int):
    """Rows come by part of a leaf: first the part's rows, then the queries that visit it."""

    def ranked(rows: np.ndarray, ids: np.ndarray, queries: np.ndarray, query_ids: np.ndarray) -> pa.RecordBatch:
        best = TopK(len(query_ids), k)
        near = _unit(queries) @ _unit(rows).T
        near[ids[None, :] == query_ids[:, None]] = -np.inf
        floor = np.full(len(query_ids), -np.inf)
        if len(ids) > k:
            floor = -np.partition(-near, k - 1, axis=1)[:, k - 1]
        q, r = np.nonzero((near >= floor[:, None] - 1e-9) & (near > -np.inf))
        if len(q):
            exact = cosine(queries[q], rows[r])
            width = np.bincount(q, minlength=len(query_ids)).max()
            place = np.arange(len(q)) - np.searchsorted(q, q)
            score, found = np.full((len(query_ids), width), -np.inf), np.full((len(query_ids), width), np.iinfo(np.int64).max)
            score[q, place], found[q, place] = exact, ids[r]
            best.add(np.arange(len(query_ids)), score, found)
        return best.batch(query_ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, ids, rows, ready = None, [], [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([np.asarray(batch.column(i)) for i in range(3)], axis=1)
            edges = np.flatnonzero(np.concatenate([[True], (np.diff(keys, axis=0) != 0).any(axis=1), [True]]))
            for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                leaf, part, kind = keys[a].tolist()
                if (leaf, part) != cell:
                    cell, ids, rows, ready = (leaf, part), [], [], None
                own, vectors = np.asarray(batch.column(3))[a:b], to_matrix(batch.column(4).slice(a, b - a))
                if kind == 0:
                    ids.append(own)
                    rows.append(vectors)
                    continue
                if ready is None and ids:
                    ready = np.concatenate(ids), np.concatenate(rows)
                if ready is not None:
                    for c in range(0, len(own), 512):
                        yield ranked(ready[1], ready[0], vectors[c : c + 512], own[c : c + 512])

    return run
