"""Counters, costs, components and normalization whose words travel packed: the same results as plain ways."""

import random
import zlib
from functools import reduce

import numpy as np

from kmerspark.baselines import counters as C
from kmerspark.operators import graph, normalize, packed
from kmerspark.operators.components import connected_components
from kmerspark.operators.kmers import exact_counts, explode_kmers
from kmerspark.operators.sketch import PrimeSketch, SketchSpec
from kmerspark.operators.spectrum import abundance_sketch
from kmerspark.operators.store import WRITTEN, stored
from kmerspark.plans import costs, growing, strategy
from kmerspark.sources.reads import from_documents, with_arrival, write_counts


def documents(spark, n=60):
    return from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").filter(f"doc_id < {n}"))


def _plan(df):
    return str(df._jdf.queryExecution().executedPlan())


def pairs(df):
    return {r.kmer: r.cnt for r in df.collect()}


def test_counters_shuffle_packed_words_only(spark):
    """no exact counter has a row for each word of a block before its words have been added up."""
    reads = stored(documents(spark))
    want = pairs(explode_kmers(reads, 22).groupBy("kmer").count().withColumnRenamed("count", "cnt"))
    for make in (C.HashCounter(22), C.SpillingHashCounter(22, max_keys=500), C.SuffixOrderCounter(22), C.PartitionFileCounter(22), C.SortedBinCounter(22), C.MinimizerBinCounter(22)):
        counts = make.build(reads).counts
        assert pairs(counts) == want, make.name
        assert not any(x in _plan(counts) for x in ("HashAggregate", "partitioning(kmer")), make.name


def test_large_sketch_is_not_written_as_rows(spark, monkeypatch):
    """a sketch that no task can hold gives its histogram by parts."""
    reads = stored(documents(spark))
    spec = SketchSpec.for_reads(reads, 0.2)
    want = {tuple(r) for r in abundance_sketch(reads, PrimeSketch.build(reads, spec)).collect()}
    monkeypatch.setattr(strategy.choose, "__defaults__", (None, 10))
    n = len(WRITTEN)
    counter = C.SketchCounter(22, spec=spec).build(reads)
    assert len(WRITTEN) == n
    found = counter.histogram()
    assert {tuple(r) for r in found.collect()} == want and "Generate" not in _plan(found)


def test_tables_by_parts_are_those_of_the_sketch(spark):
    """the tables made by parts are the sketch's, and the same answers give its histogram."""
    reads = stored(documents(spark))
    spec = SketchSpec.for_reads(reads, 0.05)
    words = packed.PackedWords(reads, 22)
    found = words.answered(spec, tables_too=True)
    rows = lambda df: {(r.table_id, r.block): bytes(r.counters).rstrip(b"\0") for r in df.collect()}
    sketch = PrimeSketch.build(reads, spec)
    assert rows(packed.tables_of(found)) == rows(sketch.dense)
    assert {tuple(r) for r in words.histogram(spec, found).collect()} == {tuple(r) for r in abundance_sketch(reads, sketch).collect()}


def test_disk_use_keeps_one_structure_at_a_time(spark, tmp_path, monkeypatch):
    """structures are measured in pieces and deleted; the dump's bytes follow from its digits."""
    reads = stored(documents(spark))
    counts, before = stored(exact_counts(reads, 22)), list(WRITTEN)
    write_counts(counts, str(tmp_path / "tsv"))
    monkeypatch.setattr(costs, "PIECE_BYTES", packed.PART_BYTES)
    spec = SketchSpec.for_fpr(1000, 0.5)
    found = {r.structure: r.bytes for r in costs.disk_use(reads, spec).collect()}
    assert found["dump_tsv"] == costs.bytes_of(spark, str(tmp_path / "tsv"))
    assert WRITTEN == before and all(found.values())
    monkeypatch.setattr(SketchSpec, "fits_a_task", lambda self: False)
    again = {r.structure: r.bytes for r in costs.disk_use(reads, spec).collect()}
    assert again.keys() == found.keys() and again["sketch_memory"] == found["sketch_memory"]


def test_components_without_a_row_for_each_word(spark, monkeypatch):
    """components are those of plain edges, and no table of (read, word) is written."""
    reads = documents(spark)
    words = stored(explode_kmers(reads, 22).select("read_id", "kmer").distinct())
    hubs = words.groupBy("kmer").agg({"read_id": "min"}).withColumnRenamed("min(read_id)", "hub")
    edges = words.join(hubs, "kmer").select("read_id", "hub").distinct()
    want = {(r.node, r.component) for r in connected_components(edges, stored, "hub", "read_id").collect()}
    kinds = []

    def store(df):
        kinds.append(df.columns)
        return stored(df)

    for limit in (64 << 20, 1 << 14):  # in one pass, and in several
        monkeypatch.setattr(graph, "PASS_BYTES", limit)
        assert {tuple(r) for r in graph.graph_components(reads, 22, store).collect()} == want
    assert not any("kmer" in c for c in kinds)
    twice = spark.createDataFrame([(1, "ACGTTGCAACGGT"), (2, "ACGTTGCAACGGT"), (2, "TTTTTCCCCCTTTTT"), (3, "TTTTTCCCCCTTTTT"), (4, "AAAAAGAGAGAAA"), (5, "ACG")], "read_id long, seq string").repartition(6)
    assert {tuple(r) for r in graph.graph_components(twice, 13, stored).collect()} == {(1, 1), (2, 1), (3, 1), (4, 4)}


def test_normalization_by_parts_keeps_the_same_reads(spark, monkeypatch):
    """a sketch that no task can hold judges batches without a row for each word and table."""
    rng = random.Random(4)
    text = "".join(rng.choices("ACGT", k=400))
    seqs = [text[(at := rng.randrange(300)) : at + 100] for _ in range(200)] + ["ACGTN" * 20, "AC"]
    reads = stored(with_arrival(spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string"), batches=4))
    spec = SketchSpec.for_fpr(400, 0.3)
    keep = lambda: {r.read_id for r in normalize.keep_by_batches(reads, spec, stored, 5, 4).collect()}
    want = keep()
    assert 0 < len(want) < 200
    monkeypatch.setattr(normalize, "window_counts", None)
    monkeypatch.setattr(strategy.choose, "__defaults__", (None, 10))
    assert keep() == want
    monkeypatch.setattr(strategy, "JOIN_KEYS", 3)
    assert keep() == want


def test_growing_subsets_share_their_words(spark, monkeypatch):
    """structures of growing subsets are those of each subset by itself, though words are put in order only once."""
    layers = [stored(documents(spark).filter(f"read_id div 10000 % 3 = {i}").select("read_id", "seq")) for i in range(3)]
    cut, before = [], list(WRITTEN)
    monkeypatch.setattr(growing, "sent", lambda *a, **b: cut.append(a) or packed.sent(*a, **b))
    monkeypatch.setattr(growing, "SEND_WORDS", 5000)
    found = {(r.subset, r.structure): r.bytes for r in growing.disk_on_layers(layers, 22, 0.05).collect()}
    assert len(cut) == 3 + 3 and WRITTEN == before and len(found) == 24  # a layer's words, and a subset's part files
    words = growing.LayeredWords(layers, 22)
    sums = words.sums(lambda code, cnt: (len(code), cnt.sum(), (code % np.uint64(1009) * cnt.view(np.uint64)).sum()), 3)
    for i in (1, 2, 3):
        reads = stored(reduce(lambda a, b: a.unionByName(b), layers[:i]))
        counts = pairs(exact_counts(reads, 22))
        assert sums[i - 1] == (len(counts), sum(counts.values()), sum(x % 1009 * n for x, n in counts.items()))
        alone = {r.structure: r.bytes for r in costs.disk_use(reads, SketchSpec.for_reads(reads, 0.05)).collect()}
        own = {x: found[i, x] for x in alone}
        assert own["sketch_memory"] == alone["sketch_memory"] and own["dump_tsv"] == alone["dump_tsv"]
        assert all(0.8 < own[x] / alone[x] < 1.25 for x in alone), (own, alone)
    monkeypatch.setattr(growing, "ONE_PASS_PARTS", 2)
    monkeypatch.setattr(growing, "PASSES", 3)
    again = growing.LayeredWords(layers, 22)
    assert len(cut) == 6 + 3 + 9 and again.sums(lambda code, cnt: (len(code), cnt.sum()), 2) == [x[:2] for x in sums]


def test_counters_of_a_growing_sketch_are_the_sketch_s(spark, monkeypatch):
    """the blocks that are measured are those of the sketch of that subset, also where words repeat beyond the cap."""
    base = documents(spark, 20).select("read_id", "seq")
    often = spark.createDataFrame([(10**9 + i, "ACGTTGCAACGGTACCATTGACGATTT") for i in range(400)], "read_id long, seq string")
    layers = [stored(base), stored(often), stored(base.unionByName(often)), stored(often.limit(0))]
    spec = SketchSpec.for_fpr(2000, 0.5)
    monkeypatch.setattr(growing, "saved_bytes", lambda table, blocks: (sum(zlib.crc32(bytes([table]) + x[0].to_bytes(4, "little") + x[1]) for x in blocks), len(blocks)))
    words = growing.LayeredWords(layers, 22)
    for i in (1, 3, 4):
        reads = reduce(lambda a, b: a.unionByName(b), layers[:i])
        blocks = PrimeSketch.build(reads, spec).dense.collect()
        want = sum(zlib.crc32(bytes([r.table_id]) + r.block.to_bytes(4, "little") + bytes(r.counters)) for r in blocks)
        assert words.sketch_bytes(spec, i) == (want, len(blocks))


def test_layers_of_words_without_room_in_one_number():
    """words and counts too wide for one number are put in order by their parts; empty layers take nothing."""
    rng = np.random.default_rng(3)
    code, layer, cnt = rng.integers(0, 50, 400, dtype=np.uint64), rng.integers(0, 3, 400).astype(np.uint8), rng.integers(1, 9, 400)
    for bits in (6, 62):
        found = list(zip(*(x.tolist() for x in growing.in_layers(code, layer, cnt, bits)), strict=True))
        want = {}
        for c, x, n in zip(code.tolist(), layer.tolist(), cnt.tolist(), strict=True):
            want[c, x] = want.get((c, x), 0) + n
        assert found == sorted((*key, n) for key, n in want.items())
    assert [len(x) for x in growing.in_layers(code[:0], layer[:0], cnt[:0], 44)] == [0, 0, 0]


def test_growing_subsets_of_nothing(spark):
    """reads without a word have structures without one."""
    none = spark.createDataFrame([(1, "ACGT")], "read_id long, seq string")
    found = {(r.subset, r.structure): r.bytes for r in growing.disk_on_layers([none, none], 22, 0.05).collect()}
    assert len(found) == 16 and all(found[i, x] == 0 for i in (1, 2) for x in ("dump_tsv", "sketch_none", "sketch_gzip", "exact_hash", "exact_suffix"))
