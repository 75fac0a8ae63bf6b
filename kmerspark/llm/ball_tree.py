"""Exact largest inner products by branch and bound in ball trees, one tree per shard of the rows.

A shard is a run of at most SHARD_ROWS rows of one task; its tree splits a ball between two rows far apart. A node has
two bounds for a query, of which the lower counts: the product with its centre plus the query's norm times its
radius; and the query's norm times the node's largest norm times the cosine of the angle between the query and the
node's cone, which is the tighter one for vectors of about the same length. Nodes are taken by descending bound, all
queries of a block that can still gain from a node at once; a query's k-th score so far prunes, and a task hands it
on from shard to shard. It starts at the k-th score over a small set of the rows with the largest norms, which all
shards share, or in the leaf to which the query descends first. Vectors without any structure can't be pruned by either bound; the result is exact all the same.
"""

from __future__ import annotations

import heapq
import itertools
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._search import LOWEST, TopK, clean_vectors, distinct_rows, merge_ranked, query_blocks, to_matrix
from ._state import stored

SHARD_ROWS = 4_096
LEAF_ROWS = 64
#: Rows of largest norm from which every query's first bound is taken.
SEED_ROWS = 512


def quantise(rows: np.ndarray) -> np.ndarray:
    return np.floor(256.0 * rows)


def _cone(rows: np.ndarray, centre: np.ndarray) -> tuple[np.ndarray, float, float]:
    """A direction, the largest angle of a row to it, and the largest norm; rows of zeros are in any cone."""
    norms = np.sqrt((rows**2).sum(axis=1))
    length = np.sqrt((centre**2).sum())
    if not length or not norms.any():
        return np.zeros_like(centre), np.pi, float(norms.max())
    some = norms > 0
    cosine = rows[some] @ (centre / length) / norms[some]
    return centre / length, float(np.arccos(np.clip(cosine.min(), -1, 1))) + 1e-7, float(norms.max())


class BallTree:
    """Balls over whole-number rows; leaves are runs of `order`."""

    def __init__(self, rows: np.ndarray, ids: np.ndarray, leaf: int = LEAF_ROWS):
        order, nodes, todo = np.arange(len(rows)), [], [(0, len(rows), -1)]
        while todo:
            a, b, parent = todo.pop()
            own = rows[order[a:b]]
            centre = own.mean(axis=0)
            radius = np.sqrt(((own - centre) ** 2).sum(axis=1).max())
            at = len(nodes)
            nodes.append([a, b, centre, radius, [], *_cone(own, centre)])
            if parent >= 0:
                nodes[parent][4].append(at)
            if b - a > leaf and radius > 0:
                one = own[np.argmax(((own - centre) ** 2).sum(axis=1))]
                other = own[np.argmax(((own - one) ** 2).sum(axis=1))]
                along = own @ (other - one)
                order[a:b] = order[a:b][np.argsort(along, kind="stable")]
                mid = a + int((along < (one + other) @ (other - one) / 2).sum())  # each row to the nearer of two far ones
                if min(mid - a, b - mid) < (b - a) // 16:
                    mid = (a + b) // 2
                todo += [(a, mid, at), (mid, b, at)]
        self.rows, self.ids = rows[order], ids[order]
        self.begin, self.end = np.array([n[0] for n in nodes]), np.array([n[1] for n in nodes])
        self.centre = np.stack([n[2] for n in nodes])
        self.radius = np.array([n[3] for n in nodes])
        self.children = [n[4] for n in nodes]
        self.axis = np.stack([n[5] for n in nodes])
        self.spread, self.longest = np.array([n[6] for n in nodes]), np.array([n[7] for n in nodes])

    def search(self, queries: np.ndarray, query_ids: np.ndarray, best: TopK, seeded: np.ndarray) -> int:
        """Offer to `best` all rows that could enter; returns how many products of rows and queries it took."""
        norms = np.sqrt((queries**2).sum(axis=1))
        slack = 1e-6 * (1 + norms * np.sqrt((self.centre**2).sum(axis=1)).max(initial=0))

        def bound(node: int, rows: np.ndarray) -> np.ndarray:
            ball = queries[rows] @ self.centre[node] + norms[rows] * self.radius[node]
            if not self.longest[node]:  # nothing but zeros
                return np.minimum(ball, 0) + slack[rows]
            angle = np.arccos(np.clip(queries[rows] @ self.axis[node] / np.maximum(norms[rows], 1e-300), -1, 1)) - self.spread[node]
            cosine = np.cos(np.clip(angle, 0, np.pi))
            cone = norms[rows] * np.where(cosine > 0, self.longest[node] * cosine, 0.0)  # below 0 some shorter row may be the best
            return np.minimum(ball, cone) + slack[rows]

        tick, every = itertools.count(), np.arange(len(queries))
        seeded, taken = self._descend(queries, query_ids, bound, best.k, seeded)
        first = bound(0, every)
        heap = [(-float(first.max(initial=-np.inf)), next(tick), 0, every, first)]
        while heap:
            _, _, node, rows, upper = heapq.heappop(heap)
            live = upper >= np.maximum(best.floor()[rows], seeded[rows])
            rows = rows[live]
            if not len(rows):
                continue
            if not self.children[node]:
                a, b = self.begin[node], self.end[node]
                score = (queries[rows] @ self.rows[a:b].T).astype(np.int64)
                score[self.ids[a:b][None, :] == query_ids[rows][:, None]] = LOWEST
                ids = np.where(score == LOWEST, np.iinfo(np.int64).max, self.ids[a:b][None, :])
                best.add(rows, score, ids)
                taken += len(rows) * (b - a)
                continue
            for child in self.children[node]:
                upper = bound(child, rows)
                heapq.heappush(heap, (-float(upper.max()), next(tick), child, rows, upper))
        return taken

    def _descend(self, queries: np.ndarray, query_ids: np.ndarray, bound, k: int, seeded: np.ndarray) -> tuple[np.ndarray, int]:
        """Every query straight down to one leaf, always to the child of higher bound: its k-th score there is a floor."""
        seeded, taken, todo = seeded.copy(), 0, [(0, np.arange(len(queries)))]
        while todo:
            node, rows = todo.pop()
            if not len(rows):
                continue
            if self.children[node]:
                first, second = self.children[node]
                nearer = bound(first, rows) >= bound(second, rows)
                todo += [(first, rows[nearer]), (second, rows[~nearer])]
                continue
            a, b = self.begin[node], self.end[node]
            score = queries[rows] @ self.rows[a:b].T
            taken += score.size
            score[self.ids[a:b][None, :] == query_ids[rows][:, None]] = -np.inf
            if b - a > k:
                seeded[rows] = np.maximum(seeded[rows], -np.partition(-score, k - 1, axis=1)[:, k - 1])
        return seeded, taken


def exact_top_k(rows: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", shard_rows: int = SHARD_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: the k rows of largest integer inner product with each query, but for its own.

    Components are quantised to floor(256 x). Ties go to the smaller id. Rows whose vector is null or empty or holds
    null or non-finite components, and rows without an id, take no part, nor do they as queries. Products are exact
    up to 2^53, as double precision has them. Rows of another dimension than the query's are no candidates of it. Repeated ids are candidates of their own, but no row of the
    query's own id is. Fewer than k candidates: all of them. Empty tables give an empty result.
    """
    spark = rows.sparkSession
    data = clean_vectors(rows, id_col, vector_col)
    norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    seeds = data.orderBy(F.desc(norm), "id").limit(SEED_ROWS).toArrow()
    seed_ids, seed_list = seeds["id"].to_numpy(), [np.array(v) for v in seeds["v"].to_pylist()]

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}

        def emit(parts: list) -> pa.RecordBatch:
            ids, values = (np.concatenate(x) for x in zip(*parts, strict=True))
            keep = distinct_rows(values, ids, k + 1)
            tree = BallTree(values[keep], ids[keep])
            return pa.RecordBatch.from_arrays([pa.array([values.shape[1]], pa.int64()), pa.array([pickle.dumps(tree)], pa.large_binary()).cast(pa.binary())], names=["dim", "tree"])

        for batch in batches:
            sizes = np.diff(np.asarray(batch.column(1).offsets)) if batch.num_rows else np.zeros(0, int)
            for dim in np.unique(sizes).tolist():
                own = batch.filter(pa.array(sizes == dim))
                parts = held.setdefault(dim, [])
                for a in range(0, own.num_rows, shard_rows):
                    cut = own.slice(a, shard_rows)
                    parts.append((np.asarray(cut.column(0)), quantise(to_matrix(cut.column(1)))))
                    if sum(len(p[0]) for p in parts) >= shard_rows:
                        yield emit(parts)
                        parts.clear()
        for parts in held.values():
            if parts:
                yield emit(parts)

    trees = stored(data.mapInArrow(build, "dim long, tree binary"))
    parts = []
    for dim in [r[0] for r in trees.select("dim").distinct().collect()]:
        own = clean_vectors(queries, id_col, vector_col).filter(F.size("v") == dim).dropDuplicates(["id"])
        seed_at = [i for i, v in enumerate(seed_list) if len(v) == dim]
        seed = quantise(np.stack([seed_list[i] for i in seed_at])) if seed_at else np.zeros((0, dim))
        for ids, vectors in query_blocks(stored(own)):
            block = spark.sparkContext.broadcast((ids, quantise(vectors), seed_ids[seed_at], seed))
            parts.append(trees.filter(F.col("dim") == dim).select("tree").mapInArrow(_search(block, k), "query_id long, vec_id long, score long"))
    return merge_ranked(parts, k, lambda: spark.createDataFrame([], "query_id long, rank int, vec_id long, score long"))


def _search(block, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, queries, seed_ids, seed = block.value
        best = TopK(len(ids), k, np.int64)
        seeded = np.full(len(ids), -np.inf)
        if len(seed) > k:
            product = queries @ seed.T
            product[seed_ids[None, :] == ids[:, None]] = -np.inf
            seeded = -np.partition(-product, k - 1, axis=1)[:, k - 1]
        some = False
        for batch in batches:
            for raw in batch.column(0).to_pylist():
                pickle.loads(raw).search(queries, ids, best, seeded)
                some = True
        if some:
            yield best.batch(ids)

    return run
