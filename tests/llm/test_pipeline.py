import pytest

pipeline = pytest.importorskip("corpus_pipeline")
from kmerspark.llm._state import stored  # noqa: E402
from test_line_dedup import brute as brute_lines  # noqa: E402
from test_ngram_join import brute as brute_groups  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_stages_one_after_another(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    stages = dict(pipeline.STAGES)
    assert list(stages) == ["toxicity", "line_dedup", "ngram_jaccard_join", "mixing", "packing"]

    clean = stored(stages["toxicity"](spark, docs, SF))
    assert clean.columns == columns and clean.count() > 0.8 * docs.count()

    rows = [(r.doc_id, r.text) for r in clean.collect()]
    lines = stored(stages["line_dedup"](spark, clean, SF))
    assert lines.columns == columns
    assert sorted((r.doc_id, r.text) for r in lines.collect()) == sorted((d, t) for d, _, _, t in brute_lines(rows))

    rows = [(r.doc_id, r.text) for r in lines.collect()]
    single = stored(stages["ngram_jaccard_join"](spark, lines, SF))
    keep = sorted(d for d, _, c in brute_groups(rows) if d == c)
    assert single.columns == columns and sorted(r.doc_id for r in single.collect()) == keep

    mixed = stored(stages["mixing"](spark, single, SF))
    assert mixed.columns == columns
    times = {r.doc_id: r["count"] for r in mixed.groupBy("doc_id").count().collect()}
    assert set(times) <= set(keep) and max(times.values()) <= 3

    pieces = stages["packing"](spark, mixed, SF).toPandas()
    assert set(pieces.doc_id) == set(times)
    per_doc = pieces.groupby("doc_id").agg(n=("length", "sum"), t=("doc_tokens", "first"))
    assert all(per_doc.n[d] == per_doc.t[d] * times[d] for d in times)


def test_odd_documents(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (None, "lost words here", "en", "s", 3), (2, "", "en", "s", 0), (3, "some text " * 40, "en", "t", 1), (4, "some text " * 40, "en", "t", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in pipeline.STAGES:
        docs = stored(stage(spark, docs, SF))
    assert docs.count() >= 2
    none = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in pipeline.STAGES:
        none = stored(stage(spark, none, SF))
    assert none.count() == 0


def test_the_mix_holds_for_rows_without_an_id(spark):
    import corpus_pipeline as P
    from kmerspark.llm.mixing import mix_sources

    rows = [(None if i % 3 else i, s, " ".join(["w"] * (2 + i % 5) + [str(i)])) for s, n in (("a", 60), ("b", 20), ("c", 40), (None, 5)) for i in range(1000 * (s or "z").encode()[0], 1000 * (s or "z").encode()[0] + n)]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string")
    want = {r.source: r.w for r in mix_sources(docs).groupBy("source").sum("taken").toDF("source", "w").collect()}
    got = {}
    for r in P.source_mix(spark, docs, "").collect():
        got[r.source] = got.get(r.source, 0) + len(r.text.split())
    assert got == {s: w for s, w in want.items() if w}


def test_columns_that_stages_use_themselves(spark):
    extra = ["score", "n_lines", "kept_text", "_copy", "_times", "_size", "_words", "id", "block", "payload", "taken", "component_id"]
    rows = [(i, f"the text number {i} has a line of its own\nand one that all of them share here", "en", f"s{i % 2}", 70, *(f"{c}{i}" for c in extra)) for i in range(6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{c} string" for c in extra))
    for name, stage in pipeline.STAGES[:-1]:
        docs = stored(stage(spark, docs, SF))
        assert docs.columns[5:] == extra, name
        assert all(r[c] == f"{c}{r.doc_id}" for r in docs.collect() for c in extra), name
    assert pipeline.STAGES[-1][1](spark, docs, SF).count() >= docs.count() > 0
