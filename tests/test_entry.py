import importlib.util

import __spark_entry__ as entry


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 90


def test_flagship(spark):
    rows = entry.entry(spark).collect()
    assert sum(r.n_exact for r in rows) == sum(r.n_sketch for r in rows) > 0


def test_queries_match_their_sql(spark):
    import duckdb

    con = duckdb.connect()
    d = "/root/testdata/sf0.001"
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    queries, sql = entry.queries(), entry.oracle_sql()
    for name in ("kmers_positions", "sketch_cells", "sketch_lookup", "abundance_sketch_f05", "miscount", "trim_once", "count_bins_minimizer", "normalize_batch_by_chance", "containment_benchmark", "windows_session", "asof_sketch_version", "udtf_kmers"):
        df = queries[name](spark, d)
        rel = con.sql(sql[name])
        columns = sorted(df.columns)
        assert columns == sorted(rel.columns), name
        at = [rel.columns.index(c) for c in columns]
        assert sorted(map(str, (tuple(r[c] for c in columns) for r in df.collect()))) == sorted(map(str, (tuple(r[i] for i in at) for r in rel.fetchall()))), name


def test_nothing_but_the_guard_knows_the_training_data_operators():
    import pathlib

    root = pathlib.Path(entry.__file__).parent / "kmerspark"
    for path in root.rglob("*.py"):
        if "llm" not in path.parts:
            assert "llm" not in path.read_text(), path
    assert importlib.util.find_spec("kmerspark.queries")
