import random
import time
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from kmerspark.baselines.counters import COUNTERS, ContainerCounter, SortedBinCounter
from kmerspark.baselines.trimmers import ERROR_PPM, qtrim_error_sum, qtrim_tail
from kmerspark.functions import udf
from kmerspark.operators.graph import assembly_proxy, graph_components, n50, unitigs
from kmerspark.operators.kmers import exact_counts, explode_kmers
from kmerspark.operators.normalize import normalize_batches, normalize_sequential
from kmerspark.operators.sketch import PrimeSketch, SketchSpec
from kmerspark.operators.spectrum import distinct_kmers, valley_and_peak
from kmerspark.operators.store import publish, stored
from kmerspark.operators.trim import filter_reads, trim_iterative, trim_reads
from kmerspark.sources import reads as R
from kmerspark.sources.simulate import random_kmers, simulate_reads
from kmerspark.streaming import online
from test_kernels import READS, code, reads_frame, words


def genome(n=3000, seed=0):
    return "".join(random.Random(seed).choices("ACGT", k=n))


@pytest.fixture(scope="module")
def deep(spark):
    return stored(simulate_reads(spark, genome(), 30, 0.01, "rising"))


def test_counters_agree(spark):
    rng = random.Random(2)
    data = [(i, "".join(rng.choices("ACGT", k=60)) if i % 3 else "ACGTTGCAACGGT" * 5) for i in range(60)]
    df = spark.createDataFrame(data, "read_id long, seq string").repartition(3)
    want = Counter(code(w) for _, s in data for w in words(s, 13))
    for name, make in COUNTERS.items():
        if name == "prime_sketch":
            continue
        got = {r.kmer: r.cnt for r in make(13).build(df).counts.collect()}
        assert got == ({k: c for k, c in want.items() if c > 1} if name == "bloom_gated" else want), name
    assert {r.kmer for r in SortedBinCounter(13, min_count=5).build(df).counts.collect()} == {k for k, c in want.items() if c >= 5}
    err = ContainerCounter(13, kind="cache", expected_frequent=5).build(df).errors(exact_counts(df, 13)).first()
    assert err.false_positives == 0 and err.false_negatives >= 0
    q = spark.createDataFrame([(k,) for k in [*list(want)[:5], 1]], "kmer long")
    for name in ("exact_hash", "exact_suffix", "prime_sketch"):
        got = {r.kmer: r.est for r in COUNTERS[name](13).build(df).lookup(q).collect()}
        assert got == {k: want.get(k, 0) for k in got}
    with pytest.raises(NotImplementedError):
        COUNTERS["disk_partition"](13).build(df).lookup(q)


def test_simulation(spark, deep):
    rows = deep.collect()
    g = genome()
    assert len(rows) == 30 * 3000 // 100
    for r in rows[:50]:
        assert r.true_seq == g[r.start : r.start + 100]
        assert sum(a != b for a, b in zip(r.seq, r.true_seq, strict=True)) == r.n_errors and len(r.qual) == 100
    rate = sum(r.n_errors for r in rows) / (100 * len(rows))
    assert 0.007 < rate < 0.013
    wrong = np.array([i for r in rows for i, (a, b) in enumerate(zip(r.seq, r.true_seq, strict=True)) if a != b])
    assert (wrong >= 50).mean() > 0.85
    assert random_kmers(spark, 100).select("seq").distinct().count() == 100


def test_trimming(spark, deep):
    counts = stored(exact_counts(deep, 22))
    spec = SketchSpec.for_fpr(counts.count(), 0.8)
    left, log = trim_iterative(deep, spec, stored, 3)
    rounds = log.orderBy("round").collect()
    assert 0.75 < rounds[0].fpr < 0.85 and rounds[0].bases_removed > rounds[1].bases_removed > rounds[2].bases_removed
    assert rounds[0].n_unique > rounds[2].n_unique and rounds[0].fpr > rounds[1].fpr
    fine = PrimeSketch.of_counts(counts, SketchSpec.for_fpr(counts.count(), 1e-6)).stored(stored)
    cut = trim_reads(deep.select("read_id", "seq"), fine)
    exact = {r.kmer: r.cnt for r in counts.collect()}
    got = {r.read_id: r.seq for r in cut.collect()}
    for r in deep.select("read_id", "seq").collect():
        low = next((i for i, w in enumerate(words(r.seq, 22)) if exact[code(w)] < 2), None)
        want = r.seq if low is None else r.seq[: low + 21]
        assert got.get(r.read_id) == (want if len(want) >= 22 else None)
    clean = filter_reads(deep.select("read_id", "seq"), fine)
    assert all(min(exact[code(w)] for w in words(r.seq, 22)) >= 2 for r in clean.collect())


def test_cut_of_the_worked_example(spark):
    df = spark.createDataFrame([r for r in READS if r[1]], "read_id long, seq string")
    fine = PrimeSketch.build(df, SketchSpec((1009, 1013), k=4))
    assert {r.read_id for r in trim_reads(df, fine).collect()} == {1, 3, 4}
    assert {r.read_id for r in trim_reads(df, fine, keep_short=True).collect()} == {1, 3, 4, 7, 8}


def test_sequential_normalization_keeps_the_first_two(spark):
    a, b = genome(60, 1), genome(60, 2)
    df = spark.createDataFrame([(1, a), (2, a), (3, a), (4, b), (5, "ACG")], "read_id long, seq string")
    kept = normalize_sequential(df, SketchSpec((100_003, 100_019), k=22), 2)
    assert sorted(r.read_id for r in kept.collect()) == [1, 2, 4]


def test_normalization(spark, deep):
    df = deep.select("read_id", "source", "seq")
    spec = SketchSpec.for_fpr(exact_counts(df, 22).count(), 0.01)
    strict = normalize_sequential(df, spec, 10).count()
    kept, sketch = normalize_batches(R.with_arrival(df, batches=8), spec, stored, 10, 8)
    assert strict <= kept.count() < df.count()
    g = spark.createDataFrame([(0, genome())], "contig_id long, seq string")
    assert assembly_proxy(kept, g).first().recovered > 0.98
    seen = PrimeSketch.build(kept, spec)
    key = lambda s: sorted((r.table_id, r.cell, r.cnt) for r in s.cells.collect())
    assert key(seen) == key(sketch)  # reads that were dropped left no trace


def test_quality_trimmers(spark):
    q = [[40] * 5 + [2] * 3 + [40] * 10 + [2] * 4, [2] * 5, [30] * 6]
    df = spark.createDataFrame([(i, "A" * len(x), x) for i, x in enumerate(q)], "read_id long, seq string, qual array<tinyint>")
    got = {r.read_id: len(r.seq) for r in qtrim_error_sum(df, 0.05).collect()}
    assert got == {0: 10, 2: 6}
    assert {r.read_id: len(r.seq) for r in qtrim_tail(df, 20, 3).collect()} == {0: 18, 2: 6}
    assert ERROR_PPM[10] == 100_000


def test_graph(spark):
    a, b = genome(200, 3), genome(200, 4)
    df = spark.createDataFrame([(i, (a, b)[i % 2][s : s + 80]) for i, s in enumerate([0, 0, 40, 40, 80, 80, 120, 120])], "read_id long, seq string")
    groups = {r.read_id: r.component for r in graph_components(df, 22, stored).collect()}
    assert groups == {i: i % 2 for i in range(8)}
    u = unitigs(df, 22, stored)
    assert sorted(r.n_bases for r in u.collect()) == [200, 200] and n50(u) == 200
    chain = spark.createDataFrame([(0, genome(3000, 9))], "read_id long, seq string")
    assert [r.n_bases for r in unitigs(chain, 22, stored).collect()] == [3000]


def test_first_sight_by_filters(spark, deep):
    n = distinct_kmers(deep, 22).count()
    assert 0.99 * n <= distinct_kmers(deep, 22, seen="bloom", expected=n).count() <= n
    hist = exact_counts(deep, 22).groupBy(F.col("cnt").alias("abundance")).agg(F.count("*").alias("n_kmers"))
    at = valley_and_peak(hist)
    assert 2 <= at["valley"] < at["peak"] and 12 <= at["peak"] <= 30


def test_files(spark, tmp_path):
    (tmp_path / "a.fa").write_text(">one x\nACGT\nAC\n>two\n\n>three\nggg")
    assert {(r.source, r.seq) for r in R.read_fasta(spark, str(tmp_path / "a.fa")).collect()} == {("one x", "ACGTAC"), ("two", ""), ("three", "GGG")}
    (tmp_path / "a.fq").write_text("@r1\nACG\n+\nI5!\n@r2\nT\n+\n#\n")
    assert [(r.source, r.seq, r.qual) for r in R.read_fastq(spark, str(tmp_path / "a.fq")).orderBy("source").collect()] == [("r1", "ACG", [40, 20, 0]), ("r2", "T", [2])]
    R.write_fasta(reads_frame(spark).filter("seq is not null"), str(tmp_path / "out"))
    back = R.read_fasta(spark, str(tmp_path / "out"))
    assert {r.seq for r in back.collect()} == {s for _, s in READS if s is not None}
    COUNTERS["exact_hash"](4).build(reads_frame(spark)).dump(str(tmp_path / "tsv"))
    assert R.read_counts(spark, str(tmp_path / "tsv")).count() == 7


def test_sql_functions(spark):
    udf.register(spark)
    r = spark.sql("SELECT encode_kmer('CGTA') a, decode_kmer(108L, 4) b, cyclic_hash('ACGTT') = cyclic_hash('AACGT') c, encode_kmer('ACN') d").first()
    assert (r.a, r.b, r.c, r.d) == (108, "CGTA", True, None)
    assert spark.sql("SELECT count(*) n FROM kmers_of('ACGTACGTAC', 4)").first().n == 7


def test_versioned_sketch_counts_a_batch_once(spark, tmp_path):
    spec = SketchSpec((101, 97), k=4)
    v = online.VersionedSketch(spark, str(tmp_path / "v"), spec)
    counts = exact_counts(reads_frame(spark), 4)
    assert v.update(counts, 0) and not v.update(counts, 0) and v.version() == 0
    key = lambda s: sorted((r.table_id, r.cell, r.cnt) for r in s.cells.collect())
    assert key(v.current()) == key(PrimeSketch.of_counts(counts, spec))
    assert v.update(counts, 1) and key(v.current()) == key(PrimeSketch.of_counts(counts.unionByName(counts), spec))


def test_streams_equal_batches(spark, tmp_path):
    rng = random.Random(8)
    data = [(i, "".join(rng.choices("ACGT", k=50))) for i in range(40)]
    df = spark.createDataFrame(data, "read_id long, seq string")
    df.repartition(4).write.parquet(str(tmp_path / "in"))
    spec = SketchSpec((10_007, 10_009), k=12)
    stream = lambda: spark.readStream.schema("read_id long, seq string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    v = online.VersionedSketch(spark, str(tmp_path / "v"), spec)
    online.count_stream(stream(), v, str(tmp_path / "c")).awaitTermination()
    key = lambda s: sorted((r.table_id, r.cell, r.cnt) for r in s.cells.collect())
    assert key(v.current()) == key(PrimeSketch.build(df, spec)) and v.version() >= 2
    w = online.VersionedSketch(spark, str(tmp_path / "w"), spec)
    online.normalize_stream(stream(), w, str(tmp_path / "kept"), str(tmp_path / "d"), 5).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "kept")).count() == 40


def test_online_state(spark, tmp_path):
    rng = random.Random(9)
    df = spark.createDataFrame([(i, "".join(rng.choices("ACGT", k=40))) for i in range(20)], "read_id long, seq string")
    explode_kmers(df, 8).select("kmer").repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("kmer long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", online.ROCKSDB)
    try:
        q = online.online_counts(stream, SketchSpec((4001, 4003), k=8), 2).writeStream.format("memory").queryName("online").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)
    last = {r.kmer: r.est for r in spark.sql("SELECT kmer, max(est) est FROM online GROUP BY kmer").collect()}
    exact = {r.kmer: r.cnt for r in exact_counts(df, 8).collect()}
    assert set(last) == set(exact) and all(last[k] >= exact[k] for k in exact) and sum(last[k] == exact[k] for k in exact) > 0.8 * len(exact)


def test_interleaved_updates(spark):
    c = online.OnlineCounter(spark, SketchSpec((1009, 1013), k=4))
    a = spark.createDataFrame([(5,), (5,), (9,)], "kmer long")
    assert {r.kmer: r.est for r in c.update_and_get(a, stored).collect()} == {5: 2, 9: 1}
    assert {r.kmer: r.est for r in c.update_and_get(a, stored).collect()} == {5: 4, 9: 2}


def test_late_rows_are_dropped(spark, tmp_path):
    rows = [("2024-01-01 00:00:01", "a"), ("2024-01-01 02:00:00", "a")], [("2024-01-01 03:00:00", "a")], [("2024-01-01 00:00:02", "a"), ("2024-01-01 05:00:00", "a")]
    for i, part in enumerate(rows):
        spark.createDataFrame(part, "ts string, event_type string").selectExpr("cast(ts as timestamp) ts", "event_type").coalesce(1).write.mode("append").parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema("ts timestamp, event_type string").option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(str(tmp_path / "in/*"))
    q = online.windowed_counts(stream, "1 hour").writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.w_start.hour: r.n for r in spark.sql("SELECT * FROM late").collect()}
    assert got[0] == 1


def test_reads_of_long_texts_keep_to_their_text(spark):
    from kmerspark.operators.graph import containment

    rng = random.Random(5)
    long = "".join(rng.choices("ACGT", k=1_000_450))
    docs = spark.createDataFrame([(1, long), (2, "ACGT" * 30), (-1, "GATTACA" * 20), (10**14, "CCGT" * 30), (None, "ACCT" * 30)], "doc_id long, text string")
    reads = stored(R.from_documents(docs).withColumn("doc", R.text_of(F.col("read_id"))))
    assert {r.doc: r.n for r in reads.groupBy("doc").agg(F.countDistinct("read_id").alias("n")).collect()} == {1: 10_005, 2: 2, -1: 2, 10**14: 2, None: 0}
    assert reads.filter("doc = 1 AND read_id BETWEEN 10000 AND 19999").count() == 10_000
    tail = reads.filter("doc = 1 AND read_id < 0").orderBy("read_id").limit(2).select(F.lit(7).cast("long").alias("contig_id"), "seq")
    assert [(r.doc_id, r.share) for r in containment(reads, tail).collect()] == [(1, 1.0)]
    turns = spark.createDataFrame([(c, t, "user", "ACGT") for c in (3, 4) for t in (0, 99, 100, 101, 250)], "conv_id long, turn int, role string, text string")
    ids = [r.read_id for r in R.from_conversations(turns).collect()]
    assert len(set(ids)) == 10 and {3_000_000, 3_990_000, 4_000_000, 4_990_000} <= set(ids)
    with pytest.raises(Exception, match="no read id"):
        R.from_documents(docs.filter("doc_id = 1").withColumn("doc_id", F.lit(2**40))).collect()


def test_reads_at_a_rate(spark, tmp_path):
    from kmerspark.sources.generated import reads_at_rate

    genome = "ACGTTGCA" * 40
    run = reads_at_rate(spark, genome, 50, 30).select("read_id", "seq").writeStream.option("checkpointLocation", str(tmp_path / "c")).start(str(tmp_path / "o"), format="parquet")
    try:
        while not run.lastProgress or run.lastProgress.batchId < 1:
            assert run.isActive, run.exception()
            time.sleep(0.2)
    finally:
        run.stop()
    got = spark.read.parquet(str(tmp_path / "o")).collect()
    assert len(got) >= 50 and all(r.seq in genome and len(r.seq) == 30 for r in got)


def test_a_half_written_commit_is_not_seen(spark, tmp_path):
    sketch = online.VersionedSketch(spark, str(tmp_path / "v"), SketchSpec((101, 103), k=5))
    words = spark.createDataFrame([(1, 2), (5, 1)], "kmer long, cnt long")
    assert sketch.update(words, 0)
    (tmp_path / "v" / "commits" / ".0123").write_text("v1-ha")
    assert sketch.version() == 0 and sketch.current().cells.count() == 4
    assert not sketch.update(words, 0) and sketch.update(words, 1) and sketch.current().cells.agg({"cnt": "max"}).first()[0] == 4


def test_publish_takes_a_path_once(spark, tmp_path):
    path = str(tmp_path / "p" / "0001")
    assert publish(spark, path, "one") and not publish(spark, path, "two")
    assert open(path).read() == "one" and sorted(f.name for f in (tmp_path / "p").iterdir() if not f.name.endswith(".crc")) == ["0001"]


def test_trimming_joins_nothing(spark):
    """Reads are trimmed where they are, and the words left are told without a row per word and read."""
    from kmerspark.operators.packed import PackedWords
    from kmerspark.operators.sketch import PrimeSketch, SketchSpec
    from kmerspark.operators.trim import trim_reads, words_left

    rows = [(1, "s", "ACGTTGCAAC"), (2, "s", "ACGTTGCATT"), (3, "s", "AC"), (4, "s", ""), (5, "s", "NNNNNNN"), (None, "s", "ACGTTGCAAC")]
    reads = spark.createDataFrame(rows, "read_id long, source string, seq string")
    for cut, want in (("last_base", {(1, "s", "ACGTTGCAAC"), (2, "s", "ACGTTGCA")}), ("kmer_start", {(1, "s", "ACGTTGCAAC"), (2, "s", "ACGTT")})):
        left = trim_reads(reads, PrimeSketch.build(reads, SketchSpec((100003, 99991), k=4)), 2, cut)
        assert {tuple(r) for r in left.collect()} == want
        assert "Join" not in left._jdf.queryExecution().optimizedPlan().toString()
    few = spark.createDataFrame([(1, "s", "AAAACG"), (2, "s", "AAAA")], "read_id long, source string, seq string")
    assert words_left(PackedWords(few, 4, True, ends_too=True)) == (3, 2, 1)
