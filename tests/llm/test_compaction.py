import math

import pytest

from kmerspark.llm.compaction import ConflictError, TieredStore, compact_documents
from pyspark.sql import functions as F


def simulate(sizes, target, base, factor, min_run):
    """(ordinal, generation, bytes) of the shards left, given the arrivals' sizes in order."""
    shards = [(i, 0, b) for i, b in enumerate(sizes)]
    while True:
        tiers = {}
        for s in shards:
            if s[2] < target / 2:
                tiers.setdefault(int(math.log(max(s[2] / base, 1)) / math.log(factor) + 1e-9), []).append(s)
        merges = []
        for own in tiers.values():
            runs, before = {}, 0
            for s in sorted(own):
                runs.setdefault(before // target, []).append(s)
                before += s[2]
            merges += [r for r in runs.values() if len(r) >= min_run or len(r) >= 2 and sum(s[2] for s in r) >= target / 2]
        if not merges:
            return sorted(shards)
        gone = {s[0] for r in merges for s in r}
        shards = [s for s in shards if s[0] not in gone] + [(min(s[0] for s in r), max(s[1] for s in r) + 1, sum(s[2] for s in r)) for r in merges]


def test_against_a_simulation(spark, tmp_path):
    sizes = [10, 12, 300, 9, 11, 45, 50, 60, 700, 44, 10, 10, 10, 10, 10, 10, 0, 0, 0, 0, 5]
    rows = [(i, "x" * b, "en", i) for i, b in enumerate(sizes)]
    limits = {"target": 100, "base": 8, "factor": 3, "min_run": 3}
    got = compact_documents(spark.createDataFrame(rows, "doc_id long, text string, shard string, weight long"), per_arrival=1, path=str(tmp_path / "s"), **limits)
    assert sorted(r.doc_id for r in got.collect()) == list(range(len(sizes)))
    store = TieredStore(spark, str(tmp_path / "s"), **limits)
    left = sorted((r.ordinal, r.generation, r.n_bytes) for r in store.manifest().collect())
    assert left == simulate(sizes, *limits.values())
    assert store.read().select("payload.*").orderBy("doc_id").collect() == spark.createDataFrame(rows, "doc_id long, text string, shard string, weight long").collect()


def test_versions_and_conflicts(spark, tmp_path):
    a, b = (TieredStore(spark, str(tmp_path / "v"), target=1000, base=10, min_run=2) for _ in range(2))
    df = spark.range(8).withColumn("text", F.lit("abcdefghij"))
    a.append(df, F.col("id"), F.length("text"))
    assert b.version() == 1 and b.manifest().count() == 8
    a.append(df.filter("id < 3"), F.col("id"), F.length("text"))
    assert b.read().count() == 11
    with pytest.raises(ConflictError):
        b._commit(b.manifest(1), 2)
    assert b.read().count() == 11 and b.version() == 2
    assert a.compact() and a.version() == 3 and a.manifest(2).count() == 11 and a.read().count() == 11
    a.vacuum()
    assert a.read().count() == 11 and not a.compact()


def test_odd_rows(spark):
    rows = [(None, "a"), (None, None), (5, ""), (5, ""), (-3, "z" * 10)]
    got = compact_documents(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(str(r.doc_id) for r in got.collect()) == ["-3", "5", "5", "None", "None"]
    assert compact_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_two_writers_at_once(spark, tmp_path):
    """The one that loses leaves no row behind, and appends its rows once when it tries again."""
    a, b = (TieredStore(spark, str(tmp_path / "w"), target=1000, base=10, min_run=2) for _ in range(2))
    rows = lambda low, high: spark.range(low, high).withColumn("text", F.lit("abcdefghij"))
    a.append(rows(0, 3), F.col("id"), F.length("text"))
    commit = a._commit

    def late(manifest, version):  # another writer commits between this one's write and its commit
        a._commit = commit
        b.append(rows(10, 14), F.col("id"), F.length("text"))
        commit(manifest, version)

    a._commit = late
    with pytest.raises(ConflictError):
        a.append(rows(20, 28), F.col("id"), F.length("text"))
    held = lambda s: sorted(r.id for r in s.read().select("payload.id").collect())
    assert held(a) == held(b) == [0, 1, 2, 10, 11, 12, 13]
    a.append(rows(20, 28), F.col("id"), F.length("text"))
    want = [0, 1, 2, 10, 11, 12, 13, *range(20, 28)]
    assert held(a) == want and a.manifest().agg(F.sum("n_rows")).first()[0] == len(want)
    a._commit = late
    with pytest.raises(ConflictError):
        a.compact()
    while b.compact():
        pass
    assert held(a) == held(b) == sorted(want + [10, 11, 12, 13])


def test_vacuum_spares_what_is_not_committed_yet(spark, tmp_path):
    a, b = (TieredStore(spark, str(tmp_path / "u"), target=1000, base=10, min_run=2) for _ in range(2))
    rows = spark.range(6).withColumn("text", F.lit("abcdefghij"))
    a.append(rows, F.when(F.col("id") > 0, F.col("id")), F.length("text"))
    assert a.compact()  # the first batch is dead now
    commit = a._commit

    def late(manifest, version):
        b.vacuum()
        commit(manifest, version)

    a._commit = late
    before = len(a._names("data"))
    a.append(rows, F.col("id"), F.length("text"))  # its shards are written, then the other vacuums
    assert len(a._names("data")) == before == 2 and a.versions() == [2, 3]
    assert a.read().count() == a.manifest().agg(F.sum("n_rows")).first()[0] == 12


def test_a_half_written_commit_is_not_seen(spark, tmp_path):
    a = TieredStore(spark, str(tmp_path / "h"))
    a.append(spark.range(3).withColumn("text", F.lit("x")), F.col("id"), F.length("text"))
    (tmp_path / "h" / "commits" / ".0123").write_text("manif")
    assert a.version() == 1 and a.read().count() == 3
