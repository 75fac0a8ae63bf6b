import itertools
import re

import numpy as np

from kmerspark.llm.mixing import fit_budget, mix_sources, source_targets


def test_budget_is_met_as_well_as_can_be():
    rng = np.random.default_rng(0)
    for _ in range(60):
        sizes = rng.choice(np.arange(1, 40), 5, replace=False)
        counts = rng.integers(0, 4, 5)
        budget = int(rng.integers(0, int((sizes * counts).sum()) + 3))
        take = fit_budget(sizes, counts, budget)
        assert ((take >= 0) & (take <= counts)).all() and (take * sizes).sum() <= budget
    sizes, counts = np.array([7, 11, 13]), np.array([3, 2, 2])
    best = max(s for c in itertools.product(*(range(n + 1) for n in counts)) if (s := int((sizes * c).sum())) <= 50)
    assert best - int((fit_budget(sizes, counts, 50) * sizes).sum()) <= 2


def test_large_budget_is_exact():
    rng = np.random.default_rng(3)
    sizes, counts = np.arange(1, 3000), rng.integers(1, 50, 2999)
    total = int((sizes * counts).sum())
    for budget in (total // 3, 2 * total // 3, total // 7 + 5):
        assert int((fit_budget(sizes, counts, budget) * sizes).sum()) == budget
    assert 0 <= total - 1 - int((fit_budget(sizes, counts, total - 1) * sizes).sum()) < 3000


def waterfill(sizes, cap=3):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: i % 3 + 1 for i, s in enumerate(names)}
    target, open_, left = {}, set(names), float(sum(sizes.values()))
    while open_:
        level = left / sum(w[s] for s in open_)
        full = {s for s in open_ if w[s] * level >= cap * sizes[s]}
        if not full:
            return target | {s: w[s] * level for s in open_}
        for s in full:
            target[s] = float(cap * sizes[s])
            left -= target[s]
        open_ -= full
    return target


def test_targets(spark):
    sizes = {"a": 10, "b": 500, "c": 30, "é": 0, None: 77, "d": 1000, "B": 60}
    got = source_targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long"))
    want = waterfill(sizes)
    for r in got.collect():
        assert abs(r.target - want[r.source]) < 1e-6


def test_mix(spark):
    rng = np.random.default_rng(5)
    rows = [(i, None if i % 50 == 7 else " \t".join("w" * int(rng.integers(1, 80))) + "\x0b", None if i % 11 == 0 else f"s{i % 4}", 0) for i in range(400)]
    rows += [(900, "", "s1", 0), (None, "a b c", "s1", 0), (3, "same row", "s2", 0), (3, "same row", "s2", 0)] + [(1000 + i, "x " * 30, "s3", 1) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, size int").repartition(7)
    got = mix_sources(docs).toPandas()
    again = mix_sources(docs.repartition(3)).toPandas()
    key = ["doc_id", "source", "size", "taken"]
    assert got.sort_values(key)[key].fillna("-").values.tolist() == again.sort_values(key)[key].fillna("-").values.tolist()
    assert len(got) == len(rows)
    count = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    sizes = {}
    for _, t, s, _ in rows:
        sizes[s] = sizes.get(s, 0) + count(t)
    want = waterfill(sizes)
    for s, part in got.groupby(got.source.where(got.source.notna(), None), dropna=False):
        s = None if not isinstance(s, str) else s
        assert (part.source_size == sizes[s]).all() and abs(part.target.iloc[0] - want[s]) < 1e-6
        assert abs(part.taken.sum() - want[s]) <= max(2, 0.01 * want[s])
    assert (got.taken <= 3 * got["size"]).all()
    assert mix_sources(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0
