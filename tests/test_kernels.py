import random
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from kmerspark.functions import dna
from kmerspark.operators.kmers import combined_kmers, explode_kmers, hash_kmers
from kmerspark.operators.partitioned import balanced_bins, counts_of_bins, pack_bases, super_kmers, unpack_bases

RC = str.maketrans("ACGT", "TGCA")


def words(seq, k, stranded=False):
    out = []
    for i in range(len(seq) - k + 1):
        w = seq[i : i + k]
        if set(w) <= set("ACGT"):
            out.append(w if stranded else min(w, w[::-1].translate(RC)))
    return out


def code(w):
    n = 0
    for c in w:
        n = 4 * n + "ACGT".index(c)
    return n


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text("ACGTN", max_size=60), min_size=1, max_size=6), st.integers(1, 32), st.booleans())
def test_windows(seqs, k, stranded):
    raw = np.frombuffer("".join(seqs).encode(), np.uint8)
    read, pos, codes = dna.windows_of(raw, np.cumsum([len(s) for s in seqs]), k, stranded)
    want = [(i, p, code(min(w, w[::-1].translate(RC)) if not stranded else w)) for i, s in enumerate(seqs) for p in range(len(s) - k + 1) if set(w := s[p : p + k]) <= set("ACGT")]
    assert list(zip(read.tolist(), pos.tolist(), codes.tolist(), strict=True)) == want


@pytest.mark.parametrize("k", [1, 4, 22, 31, 32])
def test_decode_and_complement(k):
    rng = random.Random(k)
    ws = ["".join(rng.choice("ACGT") for _ in range(k)) for _ in range(50)]
    codes = np.array([code(w) for w in ws], np.uint64)
    assert dna.decode_codes(codes, k) == ws
    assert dna.reverse_complement_codes(codes, k).tolist() == [code(w[::-1].translate(RC)) for w in ws]


def test_cyclic_hash_is_rolling_and_strand_symmetric():
    rng = random.Random(5)
    s = "".join(rng.choice("ACGT") for _ in range(300))
    for k in (5, 40, 64, 100):
        whole = dna.cyclic_hashes(np.frombuffer(s.encode(), np.uint8), k)
        alone = [int(dna.cyclic_hashes(np.frombuffer(s[i : i + k].encode(), np.uint8), k)[0]) for i in range(len(s) - k + 1)]
        back = dna.cyclic_hashes(np.frombuffer(s[::-1].translate(RC).encode(), np.uint8), k)[::-1]
        assert whole.tolist() == alone == back.tolist()


def test_unsigned_modulo_and_codes_of_32_bases(spark):
    df = spark.createDataFrame([("T" * 32,), ("ACGT" * 8,), ("G" + "A" * 31,)], "w string")
    got = df.select("w", dna.encode_kmer(F.col("w"), 32).alias("c")).withColumn("m", dna.unsigned_mod(F.col("c"), 1_000_003)).withColumn("back", dna.decode_kmer(F.col("c"), 32)).collect()
    for r in got:
        assert r.c % 2**64 == code(r.w) and r.m == code(r.w) % 1_000_003 and r.back == r.w
    assert got[0].m == 350686


def test_too_long_words_are_refused(spark):
    with pytest.raises(ValueError):
        dna.encode_kmer(F.lit("A"), 33)
    with pytest.raises(ValueError):
        explode_kmers(spark.createDataFrame([(1, "ACGT")], "read_id long, seq string"), 33)


READS = [(1, "ACGTACGTAC"), (2, "TTTTACGTNA"), (3, "GTACGTACGT"), (4, "CCCCC"), (5, ""), (6, None), (7, "ACG"), (8, "NNNNNNNN")]
WANT = {0: 1, 27: 5, 85: 2, 108: 7, 176: 1, 177: 4, 192: 1}


def reads_frame(spark):
    return spark.createDataFrame(READS, "read_id long, seq string").repartition(3)


def test_worked_example(spark):
    for impl in ("arrow", "sql"):
        assert Counter(r.kmer for r in explode_kmers(reads_frame(spark), 4, impl=impl).collect()) == WANT
    assert explode_kmers(reads_frame(spark), 4, stranded=True).select("kmer").distinct().count() == 8


def test_super_kmers_count_the_same(spark):
    rng = random.Random(1)
    data = [(i, "".join(rng.choices("ACGTN", [10, 10, 10, 10, 1], k=rng.randint(0, 120)))) for i in range(80)]
    df = spark.createDataFrame(data, "read_id long, seq string").repartition(4)
    want = Counter(code(w) for _, s in data for w in words(s, 15))
    got = {r.kmer: r.cnt for r in counts_of_bins(super_kmers(df, 15, 8, 7), 15, parts=8).collect()}
    assert got == want
    assert {r.kmer: r.c for r in combined_kmers(df, 15).groupBy("kmer").agg(F.sum("cnt").alias("c")).collect()} == want
    assert hash_kmers(df, 40).count() == sum(len(words(s, 40)) for _, s in data)


def test_packed_bases():
    for s in (b"", b"A", b"ACGTT", b"T" * 77):
        assert unpack_bases(pack_bases(s)).tobytes() == s


def test_balanced_bins():
    bins = balanced_bins({1: 10, 2: 9, 3: 5, 4: 5, 5: 1}, 2)
    loads = [sum(w for b, w in {1: 10, 2: 9, 3: 5, 4: 5, 5: 1}.items() if bins[b] == p) for p in (0, 1)]
    assert sorted(loads) == [15, 15]


def test_reads_are_cut_from_bytes_as_from_columns(spark):
    from kmerspark.functions.dna import project_text
    from kmerspark.sources.reads import cut_reads, cut_texts

    every = ["".join(chr(c) for c in range(a, min(a + 997, 0x11000)) if not 0xD800 <= c < 0xE000 and c) for a in range(0, 0x11000, 997)]
    rows = [(1, None, "x"), (2, "", "x"), (3, "Ação! K", None), (None, "acgt" * 30, "y"), (-4, "İK" + "Z" * 210, "y"), (5, "a" * 200, "z"), *((10 + i, t, "e") for i, t in enumerate(every))]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    key = lambda d: sorted(map(repr, d.collect()))
    for junk in ("drop", "N"):
        for size in (100, 7):
            want = cut_reads(df, "doc_id", project_text(F.col("text"), junk), F.col("source"), read_len=size)
            found = cut_texts(df, "doc_id", F.col("text"), F.col("source"), junk, read_len=size)
            assert key(found) == key(want) and found.count() > 10
            assert "MapInArrow" in found._jdf.queryExecution().toString()
    assert key(cut_texts(df, "doc_id", F.col("text"), stride=50)) == key(cut_reads(df, "doc_id", project_text(F.col("text")), stride=50))
