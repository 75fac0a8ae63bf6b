import numpy as np
import pytest

from kmerspark.llm.ball_tree import BallTree, exact_top_k
from kmerspark.llm.kmeans_tree import KMeansTree, cosine, nearest
from kmerspark.llm._search import TopK, distinct_rows


def vectors(n=900, dim=12, seed=0):
    rng = np.random.default_rng(seed)
    rows = rng.normal(size=(n, dim)).astype(np.float32)
    rows[100:400] = rows[7]  # many copies
    rows[500:510] *= 3
    return rows


def frame(spark, rows, extra=()):
    data = [(i, r.tolist(), 0) for i, r in enumerate(rows)] + list(extra)
    return spark.createDataFrame(data, "vec_id long, embedding array<float>, score int").repartition(6)


ODD = [(2000, None, 1), (2050, [], 1), (2100, [float("nan")] * 12, 1), (2150, [float("inf")] + [0.0] * 11, 1), (2200, [None] + [0.5] * 11, 1), (None, [1.0] * 12, 1), (2250, [0.5] * 3, 1)]


def brute(score, ids, qids, k=5):
    out = []
    for i, q in enumerate(qids):
        best = sorted((-s, int(c)) for s, c in zip(score[i], ids, strict=True) if c != q)[:k]
        out += [(int(q), r, c, -s) for r, (s, c) in enumerate(best, 1)]
    return sorted(out)


def test_exact_top_k(spark):
    rows = vectors()
    df = frame(spark, rows, ODD)
    got = sorted((r.query_id, r.rank, r.vec_id, r.score) for r in exact_top_k(df, df.filter("vec_id % 50 = 0"), shard_rows=200).collect())
    z = np.floor(256 * rows.astype(np.float64)).astype(np.int64)
    q = np.arange(0, 900, 50)
    assert got == brute(z[q] @ z.T, np.arange(900), q)


def test_ball_tree_prunes():
    rng = np.random.default_rng(1)
    rows = np.floor(256 * (rng.normal(size=(4000, 4)) + 8 * rng.integers(-1, 2, (4000, 4))))
    tree = BallTree(rows, np.arange(4000), 64)
    best = TopK(20, 5, np.int64)
    taken = tree.search(rows[:20], np.arange(20), best, np.full(20, -np.inf))
    assert taken < 0.3 * 20 * 4000


def test_cones_prune_unit_vectors():
    """Of clustered vectors of length 1 under half of the products are taken; of unclustered ones nearly all must be."""
    rng = np.random.default_rng(2)
    unit = lambda x: np.floor(256 * x / np.sqrt((x * x).sum(axis=1, keepdims=True)))
    centres = rng.normal(size=(40, 64))
    rows = unit(centres[rng.integers(0, 40, 4000)] + 0.2 * rng.normal(size=(4000, 64)))
    queries = rows[::50]
    best = TopK(80, 5, np.int64)
    assert BallTree(rows, np.arange(4000)).search(queries, np.arange(0, 4000, 50), best, np.full(80, -np.inf)) < 0.35 * 80 * 4000
    assert sorted(zip(np.repeat(np.arange(0, 4000, 50), 5).tolist(), np.tile(np.arange(1, 6), 80).tolist(), best.id.ravel().tolist(), best.score.ravel().tolist())) == brute((queries @ rows.T).astype(np.int64), np.arange(4000), np.arange(0, 4000, 50))


@pytest.mark.parametrize("seed", range(6))
def test_any_norms_and_signs(seed):
    rng = np.random.default_rng(seed)
    rows = np.floor(rng.normal(size=(500, 3)) * rng.choice([0, 1, 30, 900], (500, 1)) + rng.choice([0, -400], (500, 1)))
    best = TopK(25, 5, np.int64)
    BallTree(rows, np.arange(500), 4).search(rows[:25], np.arange(25), best, np.full(25, -np.inf))
    want = brute((rows[:25] @ rows.T).astype(np.int64), np.arange(500), np.arange(25))
    assert best.score.ravel().tolist() == [x[3] for x in want] and best.id.ravel().tolist() == [x[2] for x in want]


def test_large_leaves_are_dealt_out(spark, monkeypatch):
    import kmerspark.llm.kmeans_tree as m

    monkeypatch.setattr(m, "PART_ROWS", 50)
    rows = vectors(seed=4)
    df = frame(spark, rows, ODD)
    got = nearest(df, df.filter("vec_id % 50 = 0")).collect()
    x = rows.astype(np.float64)
    q = np.arange(0, 900, 50)
    want = {(a, c) for a, _, c, _ in brute(cosine(x[q][:, None, :], x[None, :, :]), np.arange(900), q)}
    assert len(got) == 5 * len(q) and len(want & {(r.query_id, r.vec_id) for r in got}) >= 0.9 * len(want)


def test_nearest(spark):
    rows = vectors(seed=2)
    zero = [(3000, [0.0] * 12, 1)]
    df = frame(spark, rows, ODD + zero)
    got = nearest(df, df.filter("vec_id % 50 = 0")).collect()
    x = rows.astype(np.float64)
    q = np.arange(0, 900, 50)
    score = cosine(x[q][:, None, :], x[None, :, :])
    want = {(a, c) for a, _, c, _ in brute(score, np.arange(900), q)}
    found = {(r.query_id, r.vec_id) for r in got}
    assert len(got) == 5 * len(q) and len(want & found) >= 0.9 * len(want)
    for r in got:
        assert r.score == pytest.approx(float(score[r.query_id // 50, r.vec_id]), abs=1e-15)
    hot = [(r.rank, r.vec_id) for r in got if r.query_id == 150]
    assert sorted(hot) == [(1, 7), (2, 100), (3, 101), (4, 102), (5, 103)]


def test_small_and_empty(spark):
    df = frame(spark, vectors()[:3])
    few = df.filter("vec_id < 3")
    for f in (nearest, exact_top_k):
        assert f(few, few.filter("vec_id = 0")).count() == 2
        assert f(df.filter("false"), df).count() == 0
        assert f(few, few.filter("false")).count() == 0


def test_recall_on_the_given_table(spark):
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    t = df.toPandas()
    x = np.stack(t.embedding.to_numpy()).astype(np.float64)
    ids = t.vec_id.to_numpy()
    at = np.flatnonzero(ids % 50 == 0)
    want = {(a, c) for a, _, c, _ in brute(cosine(x[at][:, None, :], x[None, :, :]), ids, ids[at])}
    got = {(r.query_id, r.vec_id) for r in nearest(df, df.filter("vec_id % 50 = 0")).collect()}
    assert len(want & got) >= 0.93 * len(want)


def test_copies_beyond_the_smallest_ids_are_dropped():
    rows = np.array([[1.0, 2.0]] * 6 + [[3.0, 4.0]])
    assert distinct_rows(rows, np.array([9, 3, 5, 1, 8, 7, 2]), 3).tolist() == [1, 2, 3, 6]


def test_repeated_query_rows_leave_enough_copies(spark):
    ids = [100, 100, 200, 300, 400, 500, 600, 600, 600, 700]
    rows = np.array([[3.0, 4.0]] * 9 + [[1.0, 1.0]])
    assert distinct_rows(rows, np.array(ids), 6).tolist() == list(range(10))
    assert distinct_rows(rows, np.array(ids), 2).tolist() == [0, 2, 9]
    df = spark.createDataFrame([(i, r.tolist()) for i, r in zip(ids, rows, strict=True)], "vec_id long, embedding array<float>")
    for f in (exact_top_k, nearest):
        assert [r.vec_id for r in sorted(f(df, df.filter("vec_id = 100")).collect(), key=lambda r: r.rank)] == [200, 300, 400, 500, 600], f


def test_order_visits_every_leaf_once():
    rows = vectors(600)
    tree = KMeansTree.fit(rows.astype(np.float64), leaf_rows=20)
    assert sorted(tree.order(rows[0].astype(np.float64))) == list(range(tree.leaves))
