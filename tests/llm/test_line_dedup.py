import re
from collections import defaultdict

import numpy as np

from kmerspark.llm.line_dedup import CuckooFilter, ReferenceCounts, ReversibleLineIndex, line_dedup

WS = " \t\n\x0b\x0c\r"


def brute(rows, short=20, least=3):
    key = lambda x: re.sub("[A-Z]", lambda m: m[0].lower(), x.strip(WS))
    held = defaultdict(list)
    for i, (d, t) in enumerate(rows):
        for k in {key(x) for x in (t or "").split("\n")}:
            if len(k) >= short:
                held[k].append(-(2**63) if d is None else d)
    out = []
    for d, t in rows:
        lines = (t or "").split("\n")
        own = -(2**63) if d is None else d
        kept = [x for x in lines if not (len(held.get(key(x), [])) >= least and own < max(held[key(x)]))]
        out.append((d, len(lines), len(lines) - len(kept), "\n".join(kept)))
    return sorted(out, key=str)


def fixture():
    line = "The Same line of more than twenty"
    rows = [(i, f"own {i}\n{line}\n\t{line.upper()} \nshort") for i in range(40)]
    rows += [(100, None), (101, ""), (102, "é" * 19), (103, "é" * 19), (104, "é" * 19), (105, "é" * 20), (106, "É" * 20), (107, "é" * 20), (108, "é" * 20)]
    rows += [(5, line), (None, line), (None, "x"), (200, "a" * 300_000 + "\n" + line), (200, line + "\n"), (201, "two only, not dropped here\n" * 5), (202, "two only, not dropped here")]
    return rows


def test_against_brute_force(spark):
    rows = fixture()
    docs = spark.createDataFrame([(d, t, 7) for d, t in rows], "doc_id long, text string, n_dropped int").repartition(5)
    got = line_dedup(docs)
    assert got.columns == ["doc_id", "text", "n_lines", "n_dropped", "kept_text"]
    assert sorted([(r.doc_id, r.n_lines, r.n_dropped, r.kept_text) for r in got.collect()], key=str) == brute(rows)
    assert line_dedup(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_exact_counts_by_key():
    halves = np.array([[5, 1], [5, 2], [7, 1], [5, 1], [5, 9]], np.uint64)
    counts = ReferenceCounts(halves, np.array([1, 2, 3, 4, 5]), np.array([10, 20, 30, 5, 50]))
    assert counts.n_docs[counts.at(halves)].tolist() == [5, 2, 3, 5, 5] and counts.max_id[counts.at(halves)].tolist() == [10, 20, 30, 10, 50]
    assert counts.at(np.array([[5, 3], [8, 1], [0, 0]], np.uint64)).tolist() == [-1, -1, -1]
    none = np.zeros((0, 2), np.uint64)
    assert ReferenceCounts(none, np.zeros(0, int), np.zeros(0, int)).at(halves).tolist() == [-1] * 5


def test_any_number_of_blocks_and_shards(spark, monkeypatch):
    import kmerspark.llm._blocks as m

    monkeypatch.setattr(m, "BLOCK_BYTES", 300)
    monkeypatch.setattr(m, "RANGES_EACH", 16)
    rows = fixture()
    got = line_dedup(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted([(r.doc_id, r.n_lines, r.n_dropped, r.kept_text) for r in got.collect()], key=str) == brute(rows)


def test_cuckoo_filter():
    keys = np.random.default_rng(1).integers(0, 2**63, (20_000, 2), dtype=np.uint64)
    f = CuckooFilter.of(keys)
    assert f.contains(keys).all()
    other = np.random.default_rng(2).integers(0, 2**63, (20_000, 2), dtype=np.uint64)
    assert f.contains(other).mean() < 0.001
    f.delete(keys[:10_000])
    assert f.contains(keys[10_000:]).all() and f.contains(keys[:10_000]).mean() < 0.01
    assert CuckooFilter.from_bytes(f.to_bytes()).contains(keys[10_000:]).all()


def test_a_full_filter_is_made_anew(spark, tmp_path):
    texts = lambda a, b: spark.createDataFrame([(i, f"a line that only document {i} has") for i in range(a, b)], "doc_id long, text string")
    index = ReversibleLineIndex(spark, str(tmp_path), shards=2)
    index.insert(texts(0, 4))
    index.insert(texts(4, 600))
    assert index.may_hold([f"a line that only document {i} has" for i in range(600)]).all()
    assert index.may_hold([f"a line that no document {i} has" for i in range(600)]).mean() < 0.01
    index.delete(texts(0, 600))
    assert not index.may_hold([f"a line that only document {i} has" for i in range(600)]).any() and index.counts().isEmpty()


def test_index_is_reversible(spark, tmp_path):
    a = spark.createDataFrame([(i, f"line that all of them have here\nonly the document {i} has this") for i in range(20)], "doc_id long, text string")
    b = spark.createDataFrame([(i, f"line that all of them have here\nanother of the document {i} here") for i in range(20, 30)], "doc_id long, text string")
    index = ReversibleLineIndex(spark, str(tmp_path), shards=3)
    index.insert(a)
    before = sorted(tuple(r) for r in index.counts().collect())
    index.insert(b)
    counts = {r.n_docs: r.max_id for r in index.counts().collect()}
    assert counts[30] == 29
    assert index.may_hold(["another of the document 25 here"])[0]
    index.delete(b)
    assert sorted(tuple(r) for r in index.counts().collect()) == before
    assert list(index.may_hold(["Line that all of them have here", "another of the document 25 here", "only the document 3 has this"])) == [True, False, True]
