import math
import zlib
from collections import defaultdict

import duckdb
import numpy as np
import pyarrow as pa

from kmerspark.llm.queries import op5_toxicity
from kmerspark.llm.toxicity import ToxicModel, fit, kneser_ney_ratios, score_documents


def test_classes_are_distributions_and_backoff_is_shared():
    rng = np.random.default_rng(0)
    grams = np.unique(rng.integers(1, 5, (60, 3)), axis=0).astype("<u4")
    t, o = rng.integers(0, 4, len(grams)).astype(float), rng.integers(0, 9, len(grams)).astype(float)
    keep = t + o > 0
    m = kneser_ney_ratios(grams[keep], t[keep], o[keep])
    same = kneser_ney_ratios(grams[keep], o[keep] + 1, o[keep] + 1)
    assert np.allclose(same.gram_ratio, 0) and np.allclose(same.context_ratio, 0)
    assert np.isfinite(m.gram_ratio).all() and (np.diff(m.grams.astype(object)) > 0).all()


def brute_kneser_ney(toxic, ordinary, order, discount=0.75):
    """Log-likelihood ratios of words, by the textbook recursion over dictionaries of n-grams."""
    pad = lambda w: "\x01" * (order - 1) + w.lower() + "\x02"
    counts = [defaultdict(int), defaultdict(int)]
    for c, words in zip(counts, (ordinary, toxic), strict=True):
        for w in words:
            for i in range(order - 1, len(pad(w))):
                c[pad(w)[i - order + 1 : i + 1]] += 1
    seen = set(counts[0]) | set(counts[1])

    def shared(letter, context):  # continuation counts of both classes together
        n = len(context) + 1
        kinds = {g[order - n - 1 :] for g in seen}  # one more letter on the left
        after = [g for g in kinds if g[1:-1] == context]
        lower = shared(letter, context[1:]) if context else 1 / len({g[-1] for g in seen})
        if not after:
            return lower
        mine = sum(g[-1] == letter for g in after)
        return max(mine - discount, 0) / len(after) + discount * len({g[-1] for g in after}) / len(after) * lower

    def log_p(c, gram):
        own = {g: v for g, v in c.items() if g[:-1] == gram[:-1] and v}
        lower = shared(gram[-1], gram[1:-1])
        if not own:
            return math.log(lower)
        total = sum(own.values())
        return math.log(max(c.get(gram, 0) - discount, 0) / total + discount * len(own) / total * lower)

    return lambda w: sum(log_p(counts[1], pad(w)[i - order + 1 : i + 1]) - log_p(counts[0], pad(w)[i - order + 1 : i + 1]) for i in range(order - 1, len(pad(w))))


def test_ratios_against_the_textbook_recursion(spark):
    toxic, ordinary = "scum scam cum bad badly scum idiot".split(), "good mood bad calm scan idea good moon".split()
    for order in (2, 3, 4):
        every = ["\x01" * (order - 1) + w + "\x02" for w in toxic + ordinary]
        grams = sorted({w[i - order + 1 : i + 1] for w in every for i in range(order - 1, len(w))})
        count = lambda words, g: sum(("\x01" * (order - 1) + w + "\x02")[i : i + order] == g for w in words for i in range(len(w) + 1))  # noqa: B023, E731
        m = kneser_ney_ratios(np.array([[ord(x) for x in g] for g in grams], "<u4"), np.array([count(toxic, g) for g in grams], float), np.array([count(ordinary, g) for g in grams], float))
        want = brute_kneser_ney(toxic, ordinary, order)
        words = ["scum", "bad", "good", "moom", "SCAM", "madly"]
        assert np.allclose(m.word_ratios(pa.array([w.encode() for w in words])), [want(w) for w in words]), order


def test_windows_do_not_cross_documents():
    m = ToxicModel(*(np.zeros(0, np.uint64), np.zeros(0)) * 2)
    m.word_ratios = lambda words: np.array([5.0 if w == b"bad" else -1.0 for w in words.to_pylist()])
    got = m.evidence(pa.array(["ok " * 100 + "bad", "", None, "bad " * 15 + "ok " * 500, "bad"]))
    assert got[1:3].tolist() == [[0, 0, 0]] * 2
    assert np.isclose(got[0, 1], (5 - 15) / 16) and np.isclose(got[3, 1], (15 * 5 - 1) / 16) and np.isclose(got[4], 5).all()


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.1"
    got = op5_toxicity(spark, d).toArrow()
    con = duckdb.connect()
    con.register("got", got)
    n, right, caught, wrong = con.sql(f"""SELECT count(*), avg((predicted = toxic)::INT), avg(predicted) FILTER (toxic = 1), avg(predicted) FILTER (toxic = 0)
        FROM got JOIN '{d}/labels.parquet' USING (doc_id) WHERE held_out""").fetchall()[0]
    print(n, right, caught, wrong)
    assert right > 0.92 and caught > 0.5 and wrong < 0.02  # few labels here: 50 toxic ones in a language but English
    for r in got.slice(0, 50).to_pylist():
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) and r["predicted"] == int(r["score"] >= 0.3)


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, "you scum", "x"), (2, None, None), (3, "", "y"), (None, "fine", "z"), (1, "you scum", "x")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(1, 1), (2, 0), (3, None), (None, 1), (4, 0)], "doc_id long, toxic int")
    got = score_documents(docs, fit(docs, labels)).collect()
    assert len(got) == 5 and all(0 <= r.score <= 1 for r in got)
    none = fit(docs, labels.filter("false"))
    assert [r for r in score_documents(docs.filter("false"), none).collect()] == []


def test_the_sample_is_bounded_by_bytes(spark, monkeypatch):
    import kmerspark.llm.toxicity as m

    docs = spark.createDataFrame([(i, ("scum " if i % 2 else "good ") * 50) for i in range(40)], "doc_id long, text string")
    labels = docs.selectExpr("doc_id", "cast(doc_id % 2 as int) AS toxic")
    whole = fit(docs, labels)
    monkeypatch.setattr(m, "MAX_TRAIN_BYTES", 1000)  # four documents of each class
    few = fit(docs, labels)
    assert len(few.grams) == len(whole.grams) > 0
    assert [r.score > 0.5 for r in score_documents(docs, few).orderBy("doc_id").collect()] == [bool(i % 2) for i in range(40)]
