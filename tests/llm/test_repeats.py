import hashlib
import random
import re
from collections import defaultdict

import pytest

from kmerspark.llm.substring_dedup import SuffixAutomaton, search_automata, substring_dedup
from kmerspark.llm.suffix_array_dedup import repeated_passages, search_suffixes


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def held(rows, w):
    out = defaultdict(set)
    for d, t in rows:
        if d is not None:
            own = words(t)
            for s in range(len(own) - w + 1):
                out[tuple(own[s : s + w])].add(d)
    return out


def brute_dedup(rows, w=50):
    at, out = held(rows, w), []
    for d, t in rows:
        own = words(t)
        gone = [False] * len(own)
        for s in range(len(own) - w + 1) if d is not None else ():
            if min(at[tuple(own[s : s + w])]) < d:
                gone[s : s + w] = [True] * w
        kept = [x for x, g in zip(own, gone, strict=True) if not g]
        out.append((d, len(own), sum(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def brute_spans(rows, w=50):
    at, out = held(rows, w), []
    for d, t in rows:
        own = words(t)
        if d is None:
            continue
        lows = [at[tuple(own[s : s + w])] for s in range(len(own) - w + 1)]
        mark = [len(x) > 1 for x in lows]
        cover = [any(mark[max(0, i - w + 1) : i + 1]) for i in range(len(own))]
        a = 0
        while a < len(own):
            b = a
            while b < len(own) and cover[b]:
                b += 1
            if b > a:
                out.append((d, a, b - a, min(min(lows[s]) for s in range(a, b - w + 1) if mark[s]), len(own)))
            a = max(b, a + 1)
    return sorted(out)


def fixture(seed=0):
    rng = random.Random(seed)
    vocab = [f"w{i}é" for i in range(300)]
    text = lambda n: [rng.choice(vocab) for _ in range(n)]
    passages = [text(n) for n in (49, 50, 51, 75, 130, 400)]
    rows = []
    for d in range(60):
        own = text(rng.randint(0, 60))
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            a = rng.randint(0, 20)
            own += p[a : len(p) - rng.randint(0, 20)] + text(rng.randint(0, 30))
        rows.append((d, rng.choice([" ", "\n", " \t "]).join(own)))
    copy = rows[7][1] + " " + " ".join(passages[4])
    rows += [(100 + i, copy) for i in range(20)] + [(7, copy), (7, copy), (None, copy), (90, None), (91, ""), (92, " \n"), (93, "a " * 500), (94, "a " * 120), (95, " ".join(text(3000) + passages[3]))]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("seed", [0, 1])
def test_against_brute_force(spark, seed):
    rows = fixture(seed)
    docs = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, n_words string").repartition(5)
    got = sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup(docs).collect()), key=str)
    assert got == brute_dedup(rows)
    assert sorted(tuple(r) for r in repeated_passages(docs).collect()) == brute_spans(rows)


def near_copies():
    """One anchor with many distinct slices: copies of one passage, each with edits of its own and some shared ones."""
    rng = random.Random(5)
    base = [f"p{i}" for i in range(90)]
    rows = []
    for d in range(60):
        own = list(base)
        for _ in range(rng.randint(0, 2)):
            own[rng.randrange(90)] = rng.choice(["x", "y", f"z{d}"])
        rows.append((d, " ".join(own[rng.randint(0, 20) :])))
    rng.shuffle(rows)
    return rows


def test_hot_anchors_are_cut_again(spark, monkeypatch):
    import kmerspark.llm._repeats as m

    cuts = []
    refine = m._refine
    monkeypatch.setattr(m, "HOT_SLICES", 3)
    monkeypatch.setattr(m, "_refine", lambda w, level: cuts.append(level) or refine(w, level))
    rows = near_copies()
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup(docs).collect()), key=str) == brute_dedup(rows)
    assert cuts == [1, 2, 3, 4]
    assert sorted(tuple(r) for r in repeated_passages(docs).collect()) == brute_spans(rows)


def test_empty(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert substring_dedup(none).count() == 0 and repeated_passages(none).count() == 0


def test_both_searches_agree_with_sets(monkeypatch):
    import kmerspark.llm.substring_dedup as m

    monkeypatch.setattr(m, "SHARD_PASSAGES", 7)
    rng = random.Random(3)
    for _ in range(20):
        anchor = [b"x", b"y"]
        base = [rng.choice([b"a", b"b"]) for _ in range(6)] + anchor + [rng.choice([b"a", b"b"]) for _ in range(6)]
        slices, at = [], []
        for _ in range(20):
            p = [w if rng.random() < 0.85 or w in anchor else b"c" for w in base]
            a, b = rng.randint(0, 3), rng.randint(0, 3)
            slices.append(p[a : len(p) - b])
            at.append(6 - a)
        lo = [rng.randint(0, 50) for _ in slices]
        hi = [x + rng.randint(0, 9) for x in lo]
        w = 8
        holds = defaultdict(list)
        for p, x, y in zip(slices, lo, hi, strict=True):
            for s in range(len(p) - w + 1):
                holds[tuple(p[s : s + w])] += [x, y]
        for search in (search_automata, search_suffixes):
            for p, (los, his) in zip(slices, search(slices, at, lo, hi, w), strict=True):
                assert los.tolist() == [min(holds[tuple(p[s : s + w])]) for s in range(len(p) - w + 1)]
                assert his.tolist() == [max(holds[tuple(p[s : s + w])]) for s in range(len(p) - w + 1)]


def test_overlapping_passages_of_one_run():
    """Windows keep the ids of their own passage, wherever the passages are joined, and equal ones share theirs."""
    rng = random.Random(4)
    run = [b"w%d" % rng.randrange(400) for _ in range(300)]
    run[200:230] = run[20:50]
    w = 8
    cuts = [(0, 20), (13, 30), (23, 50), (43, 52), (60, 90), (83, 120), (150, 170), (163, 200), (193, 240), (240, 300)]
    starts = [a for a, _ in cuts]
    slices = [run[a:b] for a, b in cuts]
    lo = [rng.randint(0, 50) for _ in cuts]
    hi = [x + rng.randint(0, 9) for x in lo]
    holds = defaultdict(list)
    for p, x, y in zip(slices, lo, hi, strict=True):
        for s in range(len(p) - w + 1):
            holds[tuple(p[s : s + w])] += [x, y]
    for search in (search_automata,):
        for p, (los, his) in zip(slices, search(slices, [0] * len(cuts), lo, hi, w, starts), strict=True):
            assert los.tolist() == [min(holds[tuple(p[s : s + w])]) for s in range(len(p) - w + 1)]
            assert his.tolist() == [max(holds[tuple(p[s : s + w])]) for s in range(len(p) - w + 1)]


def test_automaton_has_every_substring():
    a = SuffixAutomaton()
    a.add([b"a", b"b", b"a", b"b", b"c"], [3] * 5, [3] * 5)
    a.add([b"b", b"a", b"b", b"d"], [1] * 4, [1] * 4)
    a.close()
    assert list(a.statistics([b"b", b"a", b"b", b"c", b"z", b"a", b"b", b"d"], 3)) == [(0, 1, 3), (1, 3, 3), (5, 1, 1)]
