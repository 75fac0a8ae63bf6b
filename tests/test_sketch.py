import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from kmerspark.operators import accuracy as acc
from kmerspark.operators.kmers import counts_by_source, exact_counts, explode_kmers
from kmerspark.operators.lookup import lookup, with_overflow
from kmerspark.operators import packed
from kmerspark.operators.partitioned import part_report, partitioned_counts, run_parts, sharded_estimates
from kmerspark.operators.sketch import PrimeSketch, SketchSpec
from kmerspark.operators.spectrum import abundance_sketch, histogram
from kmerspark.operators.store import stored
from kmerspark.operators.variants import CountingBloom, bloom_filter, conservative_estimates, spectral_estimates
from kmerspark.plans import sizing
from kmerspark.plans.strategy import choose
from kmerspark.sources.reads import from_documents
from tests_support import WANT, reads_frame


def est(df):
    return {r.kmer: r.est for r in df.collect()}


def test_worked_example(spark):
    counts = exact_counts(reads_frame(spark), 4)
    spec = SketchSpec((7, 5), k=4)
    sketch = PrimeSketch.build(reads_frame(spark), spec)
    cells = {(r.table_id, r.cell): r.cnt for r in sketch.cells.collect()}
    assert cells == {(0, 0): 1, (0, 1): 3, (0, 2): 4, (0, 3): 8, (0, 6): 5, (1, 0): 3, (1, 1): 1, (1, 2): 10, (1, 3): 7}
    want = {0: 1, 27: 5, 85: 3, 108: 7, 176: 1, 177: 4, 192: 8}
    for strategy in ("broadcast", "cells"):
        assert est(lookup(counts.select("kmer"), sketch, strategy)) == want
    assert est(lookup(counts.select("kmer"), PrimeSketch.build_dense(reads_frame(spark), spec))) == want
    r = acc.accuracy(acc.compare(counts, sketch)).first()
    assert r.fpr == round(2 / 7, 6) and r.miscount == round(8 / 7, 6) and r.undercounts == 0
    assert math.isclose(sketch.load_fpr(), 4 / 7)
    assert sketch.get_count("CGTA") == 7 and sketch.get_count("TACG") == 7
    sketch.increment_count("CGTA")
    assert sketch.get_count("CGTA") == 8
    small = acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, SketchSpec((5, 3), k=4)))).first()
    assert small.fpr == round(4 / 7, 6) and small.miscount == round(22 / 7, 6)


def test_exact_without_clashes_and_one_sided(spark):
    counts = stored(exact_counts(from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet")), 22))
    n = counts.count()
    for f in (0.01, 0.1, 0.5, 0.9):
        spec = SketchSpec.for_fpr(n, f)
        r = acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, spec))).first()
        assert abs(r.fpr - sizing.expected_fpr(n, spec.primes)) < 0.01 and r.undercounts == 0
        if f <= 0.1:
            assert r.pct <= 115 * f
        assert r.miscount <= 4.2
    sure = acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, SketchSpec.for_fpr(n, 1e-9, 8)))).first()
    assert sure.fpr == 0


def test_saturation_overflow_and_widths(spark):
    df = spark.createDataFrame([(1, "A" * 304), (2, "ACGTTGCA")], "read_id long, seq string")
    counts = stored(exact_counts(df, 5))
    for bits in (1, 2, 4, 8, 16, 32, 64):
        spec = SketchSpec((1009, 1013), k=5, counter_bits=bits)
        assert est(lookup(counts.select("kmer"), PrimeSketch.of_counts(counts, spec)))[0] == min(300, spec.cap)
    full = with_overflow(PrimeSketch.of_counts(counts, SketchSpec((1009, 1013), k=5)), counts)
    assert est(lookup(counts.select("kmer"), full, overflow=True))[0] == 300
    assert est(lookup(counts.select("kmer"), full))[0] == 255


def test_merge_save_load_assess(spark, tmp_path):
    df = reads_frame(spark)
    spec = SketchSpec((101, 97), k=4)
    whole = PrimeSketch.build(df, spec)
    parts = PrimeSketch.build(df.filter("read_id < 3"), spec).merge(PrimeSketch.build(df.filter("read_id >= 3"), spec))
    key = lambda s: sorted((r.table_id, r.cell, r.cnt) for r in s.cells.collect())
    assert key(whole) == key(parts)
    for codec in ("none", "gzip"):
        whole.save(str(tmp_path / codec), codec)
        back = PrimeSketch.load(spark, str(tmp_path / codec))
        assert key(back) == key(whole) and back.spec == spec
    with pytest.raises(ValueError):
        whole.merge(PrimeSketch.build(df, SketchSpec((101, 89), k=4)))
    with pytest.raises(ValueError):
        PrimeSketch.build(df, SketchSpec((5, 3), k=4)).assess(0.1, "raise")
    with pytest.warns(UserWarning):
        assert not PrimeSketch.build(df, SketchSpec((5, 3), k=4)).assess(0.1)["valid"]
    with pytest.raises(MemoryError):
        SketchSpec.for_fpr(1e6, 0.01).check_memory(1000)
    more = PrimeSketch.empty(spark, spec).increment(explode_kmers(df, 4).select("kmer"))
    assert key(more) == key(whole)


def test_sizing():
    s = sizing.size_for_fpr(50e9, 0.01)
    assert abs(s.memory / 2**30 - 446) < 0.5 and abs(s.tables - 6.64) < 0.01
    for m in (2, 3.3, 7, 12, 40):
        best = min(range(1, 60), key=lambda z: sizing.expected_fpr(1, m / z, z))
        assert sizing.expected_fpr(1, m / best, best) == sizing.expected_fpr(1, m / sizing.optimal_tables(m, 1), sizing.optimal_tables(m, 1))
    assert sizing.prime_table_sizes(20, 4) == [19, 17, 13, 11]
    for bad in (lambda: sizing.prime_table_sizes(5, 4), lambda: sizing.size_for_fpr(10, 1.0), lambda: SketchSpec((7, 7)), lambda: SketchSpec((7,), counter_bits=3)):
        with pytest.raises(ValueError):
            bad()
    x = sizing.size_for_fpr(1e6, 0.2, 4, exact=True)
    assert math.isclose(sizing.expected_fpr(1e6, x.table_size, 4), 0.2, rel_tol=1e-9)
    assert SketchSpec.for_memory(10_000, 4).memory_bytes() <= 10_000
    assert choose(SketchSpec.for_memory(10_000)).strategy == "broadcast" and choose(SketchSpec.for_memory(1 << 40), 10**9).strategy == "sharded"
    b = sizing.overcount_bound(1000, 100, 3)
    assert b["expected_excess"] == 10 and math.isclose(b["chance"], math.exp(-3))


def test_partitions(spark, tmp_path):
    reads = from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    counts = stored(exact_counts(reads, 22))
    one = sorted(tuple(r) for r in run_parts(reads, str(tmp_path / "a"), 22, 4).select("kmer", "cnt").collect())
    two = sorted(tuple(r) for r in run_parts(reads, str(tmp_path / "b"), 22, 4, "iterative").select("kmer", "cnt").collect())
    assert one == two == sorted(tuple(r) for r in counts.select("kmer", "cnt").collect())
    n = counts.count()
    spec = SketchSpec.for_fpr(n / 8, 0.1)
    got = sharded_estimates(reads, counts, spec, 8)
    r = acc.accuracy(counts.join(got, "kmer").select(F.least("cnt", F.lit(255)).alias("truth"), "est")).first()
    assert r.n == n and r.undercounts == 0 and abs(r.fpr - 0.1) < 0.02
    report = part_report(partitioned_counts(reads, 22, "prefix"), spec).collect()
    sizes = sorted(p.n_distinct for p in report)
    assert sizes[-1] > 2 * (sizes[0] + 1)  # canonical prefixes are uneven


def test_relatives(spark):
    df = reads_frame(spark)
    counts = stored(exact_counts(df, 4))
    spec = SketchSpec((11, 7), k=4, counter_bits=16)
    plain = est(sharded_estimates(df, counts, spec, 2))
    for other in (conservative_estimates, spectral_estimates):
        got = est(other(df, spec, 2))
        assert all(WANT[k] <= got[k] <= plain[k] for k in WANT)
    bloom = est(lookup(counts.select("kmer"), bloom_filter(counts, 100, 0.001, k=4)))
    assert set(bloom.values()) == {1}
    twice = CountingBloom(10_007).add(counts).add(counts)
    assert est(twice.lookup(counts.select("kmer"))) == {k: 2 * c for k, c in WANT.items()}
    assert est(twice.remove(counts).lookup(counts.select("kmer"))) == WANT
    single = PrimeSketch.of_counts(counts, SketchSpec((10_007,) * 3, k=4, layout="single"))
    assert est(lookup(counts.select("kmer"), single)) == WANT


def test_empty(spark):
    none = spark.createDataFrame([], "read_id long, seq string")
    sketch = PrimeSketch.build(none, SketchSpec((7, 5), k=4))
    assert sketch.cells.count() == 0 and sketch.load_fpr() == 0
    assert histogram(exact_counts(none, 4)).count() == 0 and abundance_sketch(none, sketch).count() == 0
    assert est(lookup(spark.createDataFrame([(3,)], "kmer long"), sketch)) == {3: 0}


def test_dense_copies_of_many_tasks_are_summed_in_rounds(spark, monkeypatch):
    """Two hundred tasks and more: no group holds more than MERGE copies, and the counters are those of the whole."""
    import kmerspark.operators.sketch as m

    df = spark.createDataFrame([(i, "x", "ACGTTGCAACGGTTACGT"[i % 7 :]) for i in range(3000)], "read_id long, source string, seq string").repartition(230)
    for bits in (2, 8):
        own = SketchSpec((31, 37, 41), k=5, counter_bits=bits)
        got = sorted(tuple(r) for r in PrimeSketch.build_dense(df, own).cells.collect())
        want = sorted(tuple(r) for r in PrimeSketch.of_counts(exact_counts(df, 5), own).cells.collect())
        assert got == want and m.MERGE < 230
        again = sorted(tuple(r) for r in PrimeSketch.dense_of_counts(exact_counts(df, 5), own).cells.collect())
        assert again == want


def test_the_estimate_of_distinct_words(spark):
    from kmerspark.operators.kmers import estimate_distinct
    from kmerspark.sources.simulate import random_kmers

    reads = random_kmers(spark, 40_000, 22)
    assert abs(estimate_distinct(reads) - 40_000) < 0.1 * 40_000
    spec = SketchSpec.for_reads(reads, 0.05)
    counts = exact_counts(reads)
    assert abs(acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, spec))).first()["fpr"] - 0.05) < 0.02


def test_stored_leaves_no_shuffle_and_discard_deletes(spark):
    from pathlib import Path

    from kmerspark.operators import store

    manager = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: {f.getName() for f in spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(manager.getAllFiles()) if f.getName().startswith("shuffle_")}
    before = files()
    table = store.stored(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert not files() - before
    assert table.count() == 7 and Path(table._stored_at).exists()
    store.discard(table, spark.range(3))
    assert not Path(table._stored_at).exists() and table._stored_at not in store.WRITTEN


def test_few_keys_are_looked_up_without_all_counters(spark, monkeypatch):
    """Beyond the broadcast bound, a few keys ask for their own counters only: the plan has no row per word and table."""
    reads, spec = reads_frame(spark), SketchSpec((7, 5), k=4)
    monkeypatch.setattr(choose, "__defaults__", (None, 1))
    monkeypatch.setattr(SketchSpec, "fits_a_task", lambda self: False)
    sketch = PrimeSketch.build(reads, spec)
    monkeypatch.setattr(PrimeSketch, "arrays", lambda self: pytest.fail("the tables went to the driver"))
    keys = spark.createDataFrame([(x,) for x in (0, 27, 85, 108, 176, 177, 192, 250)], "kmer long")
    found = lookup(keys, sketch)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "sum(cnt" in plan and plan.count("Generate") == 1  # the keys' own
    assert est(found) == est(lookup(keys, sketch, "cells"))


def test_words_by_source_need_no_join(spark):
    reads = spark.createDataFrame([(1, "a", "ACGTACGT"), (2, None, "ACGTAC"), (3, "b", "TTTTNACGT"), (4, "a", "ACGTA")], "read_id long, source string, seq string")
    found = counts_by_source(reads, 4)
    assert "Join" not in found._jdf.queryExecution().optimizedPlan().toString()
    want = explode_kmers(reads, 4).join(reads, "read_id").groupBy("source", "kmer").agg(F.count("*").alias("cnt"))
    assert sorted(map(str, found.collect())) == sorted(map(str, want.collect()))


def test_a_rollup_sends_numbers_and_not_words(spark, monkeypatch):
    rows = [(1, "de/a", "ACGTACGT"), (2, None, "ACGTAC"), (3, "fr/a", "TTTTNACGT"), (4, "de/b", "ACGTAGGC"), (5, "de/a", "ACGTA"), (6, "fr", "GGGGG"), (7, "it/x", "AC")]
    reads = spark.createDataFrame(rows, "read_id long, source string, seq string").repartition(3)
    words = {}
    for r in explode_kmers(reads, 4).join(reads, "read_id").collect():
        lang, source = [*(r.source or "").split("/"), None][:2] if r.source else (None, None)
        for key in ((0, lang, source), (1, lang, None), (2, None, None)):
            words.setdefault(key, []).append(r.kmer)
    want = sorted(str((k[1], k[2], len(w), len(set(w)))) for k, w in words.items())
    for passes in (1, 3):
        monkeypatch.setattr(packed, "ONE_PASS_BYTES", 1 << 40 if passes == 1 else 0)
        found = packed.rollup_by_source(reads, 4)
        assert "kmer" not in found._jdf.queryExecution().optimizedPlan().toString()
        assert sorted(str(tuple(r)) for r in found.collect()) == want


def test_no_key_is_absent(spark):
    """A large table can hold every key that is asked for: then there is no share, as in the query's SQL."""
    counts = spark.createDataFrame([(5, 1), (9, 2)], "kmer long, cnt long")
    sketch = PrimeSketch.of_counts(counts, SketchSpec((11, 7, 5, 3), k=4))
    asked = counts.select("kmer")
    for spec in (sketch.spec, SketchSpec.for_fpr(50_000_000, 0.2, k=4)):  # sent out, and too large for it
        assert [tuple(r) for r in acc.absent_fpr(asked, counts, PrimeSketch.of_counts(counts, spec)).collect()] == [(0, None)]
    found = acc.absent_fpr(spark.createDataFrame([(5,), (16,), (1,)], "kmer long"), counts, sketch).first()
    assert found["n"] == 2 and found["fpr_absent"] is not None


def test_packed_numbers_come_back():
    codes, cnt = np.array([0, 5, 2**63, 2**64 - 1], np.uint64), np.array([1, 254, 255, 2**40])
    assert packed.mixed(packed.mixed(codes, 64), 64, packed.UNDO).tolist() == codes.tolist()
    assert packed.decode_sorted(packed.encode_sorted(codes)).tolist() == codes.tolist()
    assert packed.decode_counts(packed.encode_counts(cnt), 4).tolist() == cnt.tolist()


def test_histogram_of_a_large_sketch_goes_by_parts(spark, monkeypatch):
    reads = reads_frame(spark)
    sketch = PrimeSketch.build(reads, SketchSpec((7, 5), k=4))
    want = sorted(abundance_sketch(reads, sketch).collect())
    monkeypatch.setattr(choose, "__defaults__", (None, 1))
    own = abundance_sketch(reads, sketch)
    assert "Generate" not in own._jdf.queryExecution().optimizedPlan().toString()  # no row per word and table
    assert sorted(own.collect()) == want


def _plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_xxhash64_as_the_engine_has_it(spark):
    from kmerspark.functions.dna import xxhash64_of

    values = [0, 1, -1, 2**43 + 12345, -(2**63), 2**63 - 1]
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, v long").orderBy("i")
    rows = df.select(F.xxhash64("v"), F.xxhash64("v", F.lit(0)), F.xxhash64("v", F.lit(3))).collect()
    own = np.array(values, np.int64)
    assert [tuple(r) for r in rows] == list(zip(*(xxhash64_of(own, n).tolist() for n in (None, 0, 3)), strict=True))


def test_counts_travel_packed(spark, monkeypatch):
    """Exact counts send no row per word, in one pass or several, and stay right for long words and large counts."""
    rows = spark.range(40).selectExpr("id AS read_id", "'x' AS source", "concat(repeat('A', 20 + id), 'CGTTGCA', repeat('ACGT', 10)) AS seq")
    for k, stranded in ((5, False), (22, False), (32, True)):
        want = sorted(map(tuple, explode_kmers(rows, k, stranded).groupBy("kmer").agg(F.count("*")).collect()))
        found = exact_counts(rows, k, stranded)
        assert sorted(map(tuple, found.collect())) == want
        assert "FlatMapGroupsInArrow" in _plan(found) and "Aggregate" not in _plan(found)
        for limit in (1 << 40, 0):
            monkeypatch.setattr(packed, "ONE_PASS_BYTES", limit)
            words = packed.PackedWords(rows, k, stranded)
            assert sorted(map(tuple, words.counts().collect())) == want
            words.discard()


def test_single_array_is_probed_in_tasks(spark):
    reads = reads_frame(spark)
    counts = exact_counts(reads, 4)
    spec = SketchSpec((1009,) * 3, k=4, layout="single")
    dense, cells = PrimeSketch.build(reads, spec), PrimeSketch.of_counts(counts, spec)
    assert dense.dense is not None and {tuple(r) for r in dense.cells.collect()} == {tuple(r) for r in cells.cells.collect()}
    found = lookup(counts, dense, "broadcast")
    assert "Join" not in _plan(found) and est(found) == est(lookup(counts, cells, "cells"))


def test_overflow_of_distinct_words_is_not_shuffled(spark):
    df = spark.createDataFrame([(1, "A" * 304), (2, "ACGTTGCA")], "read_id long, seq string")
    full = with_overflow(PrimeSketch.build(df, SketchSpec((1009, 1013), k=5)), packed.PackedWords(df, 5).counts(), distinct=True)
    assert {tuple(r) for r in full.overflow.collect()} == {(0, 300)} and "Aggregate" not in _plan(full.overflow)


def test_sharded_words_as_sharded_estimates(spark, monkeypatch):
    from kmerspark.operators import partitioned

    reads = from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    counts = stored(exact_counts(reads, 22))
    spec = SketchSpec((2003, 1999), k=22)
    want = {tuple(r) for r in sharded_estimates(reads, counts, spec, 4).collect()}
    for limit in (64 << 20, 1000):
        monkeypatch.setattr(partitioned, "HELD_BYTES", limit)
        found = partitioned.sharded_words(packed.PackedWords(reads, 22), spec, 4)
        assert {(r.part, r.kmer, r.est) for r in found.collect()} == want and "Join" not in _plan(found)


def test_first_sight_by_filters_and_gate_by_parts(spark, monkeypatch):
    from kmerspark.baselines.counters import BloomGatedCounter
    from kmerspark.operators import sketch as module
    from kmerspark.plans import strategy

    reads = from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").filter("doc_id < 60"))
    key = lambda d: sorted(map(tuple, d.collect()))
    gated = key(BloomGatedCounter(22).count(reads, keep_false=True))
    spec = SketchSpec.for_reads(reads, 0.2)
    exact = {r.abundance: r.n_kmers for r in abundance_sketch(reads, PrimeSketch.build(reads, spec)).collect()}
    monkeypatch.setattr(module, "DENSE_BYTES", 10)
    monkeypatch.setattr(strategy.choose, "__defaults__", (None, 10))
    assert key(BloomGatedCounter(22).count(reads, keep_false=True)) == gated
    found = abundance_sketch(reads, PrimeSketch.build(reads, spec), seen="bloom")
    assert "FlatMapGroupsInArrow" not in _plan(found) and "Generate" not in _plan(found)
    n = {r.abundance: r.n_kmers for r in found.collect()}
    assert all(n.get(a, 0) <= m for a, m in exact.items()) and 0.998 * sum(exact.values()) <= sum(n.values())


def test_few_keys_are_looked_up_where_reads_are(spark, monkeypatch):
    """The look-up of a few keys reads the reads themselves: one pass through Python, not one for the words and one for the sums."""
    from kmerspark.operators import sketch as module

    monkeypatch.setattr(module, "DENSE_BYTES", 1)
    reads, spec = reads_frame(spark), SketchSpec((7, 5), k=4)
    sketch, counts = PrimeSketch.build(reads, spec), stored(exact_counts(reads, 4))
    found = lookup(counts.select("kmer"), sketch, "few")
    assert est(found) == est(lookup(counts.select("kmer"), PrimeSketch.of_counts(counts, spec), "few")) == {0: 1, 27: 5, 85: 3, 108: 7, 176: 1, 177: 4, 192: 8}
    assert _plan(found).count("MapInArrow") == 1
