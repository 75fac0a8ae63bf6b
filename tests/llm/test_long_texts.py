"""One text of a hundred thousand words and more, through every text operator, beside short ones."""

import random

import pytest

from kmerspark.llm.line_dedup import line_dedup
from kmerspark.llm.mixing import mix_sources
from kmerspark.llm.ngram_join import ngram_join
from kmerspark.llm.substring_dedup import substring_dedup
from kmerspark.llm.suffix_array_dedup import repeated_passages
from kmerspark.llm.toxicity import fit, score_documents

N = 120_000


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(1)
    long = [f"w{rng.getrandbits(30)}" for _ in range(N)]
    near = list(long)
    for i in range(0, N, 500):
        near[i] = "edit"
    return [(1, " ".join(long), "a"), (2, " ".join(near), "b"), (3, " ".join(long[:200]), "a"), (4, "bad " * N, "b"), (5, None, None)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)


def test_join(docs):
    got = {r.doc_id: r for r in ngram_join(docs).collect()}
    assert got[1].n_shingles == N - 4 and got[2].component_id == 1 and got[1].n_links == got[2].n_links == 1
    assert got[4].n_shingles == 1 and [got[i].component_id for i in (3, 4, 5)] == [3, 4, 5]


def test_repeats(docs):
    removed = {r.doc_id: r.n_removed for r in substring_dedup(docs).collect()}
    assert removed == {1: 0, 2: N - N // 500, 3: 200, 4: 0, 5: 0}
    spans = repeated_passages(docs).collect()
    assert sum(r.length for r in spans if r.doc_id == 2) == N - N // 500 and {r.doc_id for r in spans} == {1, 2, 3}


def test_lines_mix_and_scores(spark, docs):
    assert {r.doc_id: r.n_lines for r in line_dedup(docs).collect()} == dict.fromkeys(range(1, 6), 1)
    assert {r.doc_id: r["size"] for r in mix_sources(docs).collect()} == {1: N, 2: N, 3: 200, 4: N, 5: 0}
    labels = spark.createDataFrame([(4, 1), (3, 0), (3, 1), (1, 0)], "doc_id long, toxic int")
    scores = {r.doc_id: r.score for r in score_documents(docs, fit(docs, labels)).collect()}
    assert len(scores) == 5 and all(0 <= x <= 1 for x in scores.values()) and scores[4] > scores[1]
