"""Registered queries of the sketch engine, each with its SQL where SQL can state it.

All run over whole tables. Sketches named after an error rate are sized from the data for it (`for_reads`), and their
SQL finds the same primes from the same estimate. The others have a fixed size, and no rate is claimed of them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines import counters as C
from .baselines.trimmers import qtrim_error_sum, qtrim_tail
from .functions import dna, udf
from .operators import accuracy as acc
from .operators import graph, spectrum, variants
from .operators import partitioned as par
from .operators.kmers import SAMPLE, estimate_distinct, exact_counts, explode_kmers, hash_kmers, md5_60
from .operators.lookup import counts_of_few, lookup, with_overflow
from .operators.normalize import normalize_batch, normalize_batches, normalize_sequential
from .operators.packed import PackedWords, rollup_by_source
from .operators.sketch import PrimeSketch, SketchSpec
from .operators.store import shared_path, stored
from .operators.trim import error_profile, filter_reads, trim_iterative, trim_reads, window_counts
from .plans import costs, sizing
from .plans import workloads as W
from .plans.sizing import prime_table_sizes
from .sources import reads as R
from .streaming import online

K = 22
#: Counters per table of the sketches of fixed size, large and small.
SIZES = {"f10": 1_500_000, "f20": 1_120_000}
#: The error rates that others are sized for.
RATE = {"f01": 0.01, "f05": 0.05, "f20": 0.2}
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def spec(name: str = "f10", **kw) -> SketchSpec:
    return SketchSpec(tuple(prime_table_sizes(SIZES[name], 4)), k=K, **kw)


def docs(spark: SparkSession, d: str, **kw) -> DataFrame:
    return W.document_reads(spark, d, **kw)


def words(spark: SparkSession, d: str) -> DataFrame:
    return exact_counts(docs(spark, d), K)


def passages(spark: SparkSession, d: str) -> DataFrame:
    """Words of the benchmark passages: a set of look-ups, some present in the documents."""
    contigs = R.genome_of(W.table(spark, d, "benchmark"))
    return explode_kmers(contigs.select(F.col("contig_id").alias("read_id"), "seq"), K).select("kmer").distinct()


# -- SQL parts ------------------------------------------------------------------------------------------------------

RC = "reverse(translate({0}, 'ACGT', 'TGCA'))"


def dna_sql(text: str) -> str:
    return f"translate(regexp_replace(translate(lower({text}), '{dna.ACCENTED}', '{dna.PLAIN}'), '[^a-z]', '', 'g'), '{dna.LETTERS}', '{dna.BASES}')"


def code_sql(w: str, k: int = K) -> str:
    kind = "HUGEINT" if k > 31 else "BIGINT"
    return "(" + " + ".join(f"strpos('CGT', substring({w}, {i + 1}, 1))::{kind} * {4 ** (k - 1 - i)}" for i in range(k)) + ")"


def reads_sql(source: str = "documents", sid: str = "doc_id", text: str = "text", extra: str = "source") -> str:
    return f"""dna AS (SELECT {sid} AS sid, {extra} AS source, {dna_sql(text)} AS s FROM {source}),
reads AS (SELECT sid * 10000 + i AS read_id, source, substring(s, i * 100 + 1, 100) AS seq FROM (SELECT *, unnest(range(0, (length(s) + 99) // 100)) AS i FROM dna))"""


def occ_sql(k: int = K, stranded: bool = False, reads: str = "reads", name: str = "occ") -> str:
    w = "f" if stranded else f"least(f, {RC.format('f')})"
    return f"""{name} AS (SELECT read_id, pos, {w} AS w FROM (SELECT read_id, pos, substring(seq, pos + 1, {k}) AS f FROM (SELECT *, unnest(range(0, length(seq) - {k - 1})) AS pos FROM {reads})) WHERE NOT regexp_matches(f, '[^ACGT]'))"""


def counts_sql(k: int = K) -> str:
    return f"""g AS (SELECT w, count(*) AS cnt FROM occ GROUP BY w),
counts AS (SELECT {code_sql('w', k)} AS kmer, cnt, w FROM g)"""


BASE = f"WITH {reads_sql()},\n{occ_sql()},\n{counts_sql()}"
BENCH_WORDS = f"""bench_dna AS (SELECT item_id AS read_id, {dna_sql('text')} AS seq FROM benchmark),
{occ_sql(reads='bench_dna', name='bench_occ')},
q AS (SELECT DISTINCT {code_sql('w')} AS kmer FROM bench_occ)"""


def cells_sql(name: str = "f10", counts: str = "counts", cap: int = 255) -> str:
    return ",\n".join(f"t{i} AS (SELECT kmer % {p} AS cell, least(sum(cnt), {cap})::BIGINT AS cnt FROM {counts} GROUP BY 1)" for i, p in enumerate(prime_table_sizes(SIZES[name], 4)))


def est_sql(keys: str, name: str = "f10", out: str = "est") -> str:
    primes = prime_table_sizes(SIZES[name], 4)
    joins = " ".join(f"LEFT JOIN t{i} ON t{i}.cell = k.kmer % {p}" for i, p in enumerate(primes))
    return f"{out} AS (SELECT k.*, least({', '.join(f'coalesce(t{i}.cnt, 0)' for i in range(4))}) AS est FROM {keys} k {joins})"


def sized_sql(f: float, counts: str = "counts", tables: int = 4, cap: int = 255) -> str:
    """The estimate of distinct words, the primes for error rate f, and the counters of a sketch of these sizes."""
    size = f"""sized AS (SELECT greatest({SAMPLE} * count(*), 1) AS n_estimate, greatest(floor(-greatest({SAMPLE} * count(*), 1) / ln(1 - pow({f}::DOUBLE, 1.0::DOUBLE / {tables}))), {3 * tables + 5})::BIGINT AS h FROM {counts} WHERE kmer % {SAMPLE} = 0),
candidates AS (SELECT unnest(range(greatest(h - 600, 2), h + 1)) AS c FROM sized),
primes AS (SELECT c, row_number() OVER (ORDER BY c DESC) - 1 AS i FROM candidates WHERE len(list_filter(range(2, floor(sqrt(c))::BIGINT + 1), lambda x: c % x = 0)) = 0)"""
    cells = (f"t{i} AS (SELECT kmer % (SELECT c FROM primes WHERE i = {i}) AS cell, least(sum(cnt), {cap})::BIGINT AS cnt FROM {counts} GROUP BY 1)" for i in range(tables))
    return ",\n".join([size, *cells])


def sized_est_sql(keys: str, tables: int = 4, out: str = "est") -> str:
    joins = " ".join(f"LEFT JOIN t{i} ON t{i}.cell = k.kmer % (SELECT c FROM primes WHERE i = {i})" for i in range(tables))
    return f"{out} AS (SELECT k.*, least({', '.join(f'coalesce(t{i}.cnt, 0)' for i in range(tables))}) AS est FROM {keys} k {joins})"


SKETCHED = f"{BASE},\n{cells_sql()},\n{est_sql('counts')}"

# -- kernel ---------------------------------------------------------------------------------------------------------


def _per_read(occ: DataFrame) -> DataFrame:
    """A row per read: its words counted, and folded so that each word and place matters."""
    return occ.groupBy("read_id").agg(F.count("*").alias("n"), F.sum(F.col("kmer") % 1_000_003 * (F.col("pos") + 1)).alias("fold"))


PER_READ = f"SELECT read_id, count(*) AS n, sum({code_sql('w')} % 1000003 * (pos + 1))::BIGINT AS fold FROM occ GROUP BY read_id"


@query(f"WITH {reads_sql()},\n{occ_sql()} {PER_READ}")
def kmers_positions(spark, d):
    return _per_read(explode_kmers(docs(spark, d), K))


@query(f"WITH {reads_sql()},\n{occ_sql()} {PER_READ}")
def kmers_canonical(spark, d):
    """The same through column functions only."""
    return _per_read(explode_kmers(docs(spark, d), K, impl="sql"))


@query(f"WITH {reads_sql()},\n{occ_sql(stranded=True)} {PER_READ}")
def kmers_stranded(spark, d):
    return _per_read(explode_kmers(docs(spark, d), K, stranded=True))


JUNK_DNA = f"""dna AS (SELECT doc_id AS sid, translate(regexp_replace(translate(translate(lower(text), '{dna.ACCENTED}', '{dna.PLAIN}'), '{dna.JUNK}', '{"N" * len(dna.JUNK)}'), '[^a-zN]', '', 'g'), '{dna.LETTERS}', '{dna.BASES}') AS s FROM documents),
reads AS (SELECT sid * 10000 + i AS read_id, substring(s, i * 100 + 1, 100) AS seq FROM (SELECT *, unnest(range(0, (length(s) + 99) // 100)) AS i FROM dna))"""


@query(f"WITH {JUNK_DNA},\n{occ_sql()} {PER_READ}")
def kmers_with_n(spark, d):
    return _per_read(explode_kmers(docs(spark, d, junk="N"), K))


@query(f"""WITH {JUNK_DNA}, m AS (SELECT read_id, seq, length(seq) AS n, length(seq) - length(replace(seq, 'N', '')) AS n_unknown FROM reads)
SELECT read_id, n, n_unknown FROM m WHERE n >= 31 AND n_unknown < 0.3 * n""")
def prepared_reads(spark, d):
    kept = R.prepare_reads(docs(spark, d, junk="N"))
    return kept.select("read_id", F.length("seq").cast("long").alias("n"), (F.length("seq") - F.length(F.replace("seq", F.lit("N"), F.lit("")))).cast("long").alias("n_unknown"))


@query(f"{BASE} SELECT kmer, w AS word FROM counts WHERE cnt >= 20")
def encode_decode(spark, d):
    frequent = words(spark, d).filter("cnt >= 20")
    word = dna.decode_kmer(F.col("kmer"), K)
    return frequent.select(dna.encode_kmer(word, K).alias("kmer"), word.alias("word"))


@query()
def cyclic_hash_k40(spark, d):
    """Windows of 40 bases by a rolling hash: how many distinct ones there are, and the most frequent count."""
    counts = hash_kmers(docs(spark, d), 40).groupBy("kmer").agg(F.count("*").alias("c"))
    return counts.agg(F.count("*").alias("n_distinct"), F.sum("c").alias("n_words"), F.max("c").alias("most"))


@query(f"WITH {reads_sql()},\n{occ_sql()} SELECT count(DISTINCT ('0x' || substr(md5(w), 1, 15))::BIGINT) AS n_distinct, count(*) AS n_words FROM occ")
def md5_hash_words(spark, d):
    return hash_kmers(docs(spark, d), K, "md5_60").agg(F.count_distinct("kmer").alias("n_distinct"), F.count("*").alias("n_words"))


EMB = " || ".join(f"CASE WHEN embedding[{2 * i + 1}] >= 0 THEN CASE WHEN embedding[{2 * i + 2}] >= 0 THEN 'T' ELSE 'G' END ELSE CASE WHEN embedding[{2 * i + 2}] >= 0 THEN 'C' ELSE 'A' END END" for i in range(32))


@query(f"""WITH w AS (SELECT vec_id, {EMB} AS f FROM embeddings), c AS (SELECT vec_id, least(f, {RC.format('f')}) AS w FROM w)
SELECT vec_id, w AS word, ({code_sql('w', 32)} % 1000003)::BIGINT AS cell FROM c""")
def full_width_codes(spark, d):
    """32 bases from the signs of 64 components: codes that need all 64 bits, unsigned."""
    pair = lambda i: F.when(F.col("embedding")[2 * i] >= 0, F.when(F.col("embedding")[2 * i + 1] >= 0, "T").otherwise("G")).otherwise(F.when(F.col("embedding")[2 * i + 1] >= 0, "C").otherwise("A"))
    word = dna.canonical(F.concat(*(pair(i) for i in range(32))))
    w = W.table(spark, d, "embeddings").select("vec_id", word.alias("word"))
    return w.select("vec_id", "word", dna.unsigned_mod(dna.encode_kmer(F.col("word"), 32), 1_000_003, 32).alias("cell"))


# -- sketch ---------------------------------------------------------------------------------------------------------

BLOCKS = "SELECT {i} AS table_id, cell // 65536 AS block, count(*) AS n_cells, sum(cnt)::BIGINT AS total, sum(cell % 65536 * cnt)::BIGINT AS fold FROM t{i} GROUP BY 2"


def _blocks(sketch: PrimeSketch) -> DataFrame:
    at = F.col("cell") % 65536
    return sketch.cells.groupBy(F.col("table_id").cast("int").alias("table_id"), F.floor(F.col("cell") / 65536).alias("block")).agg(F.count("*").alias("n_cells"), F.sum("cnt").alias("total"), F.sum(at * F.col("cnt")).alias("fold"))


@query(f"{BASE},\n{cells_sql()} " + " UNION ALL ".join(BLOCKS.format(i=i) for i in range(4)))
def sketch_cells(spark, d):
    return _blocks(PrimeSketch.build(docs(spark, d), spec()))


@query(SQL["sketch_cells"])
def sketch_dense_build(spark, d):
    """The same counters from dense arrays per task."""
    return _blocks(PrimeSketch.build_dense(docs(spark, d), spec()))


@query(SQL["sketch_cells"])
def sketch_merge_equals_whole(spark, d):
    reads = docs(spark, d)
    half = F.pmod(F.xxhash64("read_id"), F.lit(2)) == 0
    return _blocks(PrimeSketch.build(reads.filter(half), spec()).merge(PrimeSketch.build(reads.filter(~half), spec())))


LOOKUPS = f"{BASE},\n{BENCH_WORDS},\n{cells_sql()},\n{est_sql('q')} SELECT kmer, est FROM est"


@query(LOOKUPS)
def sketch_lookup(spark, d):
    return lookup(passages(spark, d), PrimeSketch.build(docs(spark, d), spec()), "broadcast")


@query(LOOKUPS)
def sketch_lookup_by_cells(spark, d):
    return lookup(passages(spark, d), PrimeSketch.build(docs(spark, d), spec()), "cells")


@query(f"{BASE},\n{BENCH_WORDS},\n{cells_sql()},\n{est_sql('q')} SELECT count(*) AS n, count_if(e.est > 0)::BIGINT AS n_positive FROM est e LEFT JOIN counts c ON c.kmer = e.kmer WHERE c.kmer IS NULL")
def sketch_lookup_absent(spark, d):
    reads, asked = docs(spark, d), stored(passages(spark, d))
    absent = asked.join(counts_of_few(reads, asked, K), "kmer", "left_anti")
    return lookup(absent, PrimeSketch.build(reads, spec())).agg(F.count("*").alias("n"), F.count_if(F.col("est") > 0).alias("n_positive"))


@query(f"{SKETCHED} SELECT count_if(cnt >= 255)::BIGINT AS n_frequent, count_if(est = 255)::BIGINT AS n_capped, max(est) AS most FROM est")
def sketch_cap255(spark, d):
    compared = lookup(words(spark, d), PrimeSketch.build(docs(spark, d), spec()))
    return compared.agg(F.count_if(F.col("cnt") >= 255).alias("n_frequent"), F.count_if(F.col("est") == 255).alias("n_capped"), F.max("est").alias("most"))


WIDTHS = (1, 2, 4, 8, 16, 32)


@query(" UNION ALL ".join(f"(WITH x AS ({BASE}, t AS (SELECT kmer % {prime_table_sizes(SIZES['f10'], 1)[0]} AS cell, least(sum(cnt), {2**b - 1})::BIGINT AS cnt FROM counts GROUP BY 1) SELECT * FROM t) SELECT {b} AS bits, count(*) AS n_cells, sum(cnt)::BIGINT AS total, max(cnt) AS most FROM x)" for b in WIDTHS))
def sketch_widths(spark, d):
    counts, out = stored(words(spark, d)), None
    for b in WIDTHS:
        own = PrimeSketch.of_counts(counts, SketchSpec(tuple(prime_table_sizes(SIZES["f10"], 1)), k=K, counter_bits=b)).cells
        row = own.agg(F.count("*").alias("n_cells"), F.sum("cnt").alias("total"), F.max("cnt").alias("most")).select(F.lit(b).alias("bits"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"{SKETCHED} SELECT kmer, cnt::BIGINT AS est FROM est WHERE est >= 255")
def sketch_overflow(spark, d):
    """Words at the counters' cap have their exact count in the overflow map."""
    reads = docs(spark, d)
    sketch = with_overflow(PrimeSketch.build(reads, spec()).stored(stored), PackedWords(reads, K).counts(), distinct=True)
    return sketch.overflow.select("kmer", F.col("cnt").alias("est"))


@query()
def sketch_single_array(spark, d):
    """One array and several hashes instead of several primes: the same errors."""
    reads = docs(spark, d)
    counts = PackedWords(reads, K).counts()
    single = PrimeSketch.build(reads, SketchSpec((4 * SIZES["f10"],) * 4, k=K, layout="single")).stored(stored)
    many = PrimeSketch.build(reads, spec()).stored(stored)
    one = acc.accuracy(acc.compare(counts, single, strategy="broadcast")).select(F.lit("single").alias("layout"), "*")
    return one.unionByName(acc.accuracy(acc.compare(counts, many)).select(F.lit("primes").alias("layout"), "*"))


ITEM_PRIMES = prime_table_sizes(4_000, 4)


@query("WITH counts AS (SELECT ('0x' || substr(md5(l_partkey::VARCHAR), 1, 15))::BIGINT AS kmer, l_partkey, count(*) AS cnt FROM lineitem GROUP BY ALL), " + ", ".join(f"t{i} AS (SELECT kmer % {p} AS cell, least(sum(cnt), 65535)::BIGINT AS cnt FROM counts GROUP BY 1)" for i, p in enumerate(ITEM_PRIMES)) + " SELECT l_partkey, k.cnt AS cnt, least(" + ", ".join(f"t{i}.cnt" for i in range(4)) + ") AS est FROM counts k " + " ".join(f"JOIN t{i} ON t{i}.cell = k.kmer % {p}" for i, p in enumerate(ITEM_PRIMES)))
def sketch_generic_items(spark, d):
    """Dense counts of integer keys, which are hashed first: the sketch's worst case."""
    items = W.table(spark, d, "lineitem").select("l_partkey")
    sketch = PrimeSketch.from_column(items, "l_partkey", SketchSpec(tuple(ITEM_PRIMES), counter_bits=16), portable=True)
    counts = items.groupBy("l_partkey").agg(F.count("*").alias("cnt")).withColumn("kmer", md5_60(F.col("l_partkey")))
    return lookup(counts, sketch).select("l_partkey", "cnt", "est")


# -- sizing ---------------------------------------------------------------------------------------------------------

RATES = (0.001, 0.01, 0.05, 0.1, 0.2, 0.5, 0.8)


@query("SELECT f, round(ln(f) / ln(0.5), 6) AS tables, round(ln(f) / -pow(ln(2), 2) * 50e9 / 1e9, 4) AS gigabytes, round(-50e9 / ln(1 - pow(f, 0.25)) / 1e9, 4) AS exact_table FROM (VALUES " + ", ".join(f"({f}::DOUBLE)" for f in RATES) + ") v(f)")
def sizing_fixed_fpr(spark, d):
    rows = [(f, round(s.tables, 6), round(s.memory / 1e9, 4), round(sizing.size_for_fpr(50e9, f, 4).table_size / 1e9, 4)) for f in RATES for s in (sizing.size_for_fpr(50e9, f),)]
    return spark.createDataFrame(rows, "f double, tables double, gigabytes double, exact_table double")


MEMORIES = (2, 5, 10, 20, 50)


@query("WITH z AS (SELECT m, z, pow(1 - exp(-z / m), z) AS fpr FROM (VALUES " + ", ".join(f"({m}::DOUBLE)" for m in MEMORIES) + ") a(m), range(1, 40) b(z)) SELECT m, arg_min(z, fpr)::INTEGER AS tables, round(min(fpr), 9) AS fpr FROM z GROUP BY m")
def sizing_fixed_memory(spark, d):
    """The best number of tables for memories of several counters a key: the closed form meets the search."""
    rows = [(float(m), z, round(sizing.expected_fpr(1.0, m / z, z), 9)) for m in MEMORIES for z in (sizing.optimal_tables(m, 1.0),)]
    return spark.createDataFrame(rows, "m double, tables int, fpr double")


@query("SELECT memory::BIGINT AS memory, tables::INTEGER AS tables, round(pow(1 - exp(-1e6 * tables / memory), tables), 9) AS fpr FROM (VALUES (1000000), (5000000), (10000000)) a(memory), range(1, 11) b(tables)")
def sizing_grid(spark, d):
    return sizing.sizing_grid(spark, 1e6, [10**6, 5 * 10**6, 10**7], list(range(1, 11))).withColumn("fpr", F.round("fpr", 9))


@query(f"WITH {reads_sql()},\n{occ_sql()} SELECT count(DISTINCT w) AS n FROM occ")
def distinct_exact(spark, d):
    return explode_kmers(docs(spark, d), K, with_pos=False).agg(F.count_distinct("kmer").alias("n"))


@query()
def distinct_hll(spark, d):
    return explode_kmers(docs(spark, d), K, with_pos=False).agg(F.approx_count_distinct("kmer", 0.02).alias("n"))


H0 = prime_table_sizes(SIZES["f10"], 1)[0]


@query(f"{BASE} SELECT round(-{H0} * ln(1 - count(DISTINCT kmer % {H0}) / {H0}))::BIGINT AS estimate, count(*) AS n FROM counts")
def distinct_from_load(spark, d):
    """Distinct words from the load of one table, beside the exact number."""
    counts = words(spark, d)
    cells = PrimeSketch.of_counts(counts, spec()).cells.filter("table_id = 0")
    h = spec().primes[0]
    got = cells.agg((F.round(-h * F.log(1 - F.count("*") / h))).cast("long").alias("estimate")).withColumn("_j", F.lit(1))
    return got.join(counts.agg(F.count("*").alias("n")).withColumn("_j", F.lit(1)), "_j").drop("_j")


@query("WITH m AS (SELECT 50e9::DOUBLE AS n, -50e9 * ln(0.01) / pow(ln(2), 2) / 1073741824 AS gib) SELECT n, round(gib, 3) AS gib, round(gib / 16, 3) AS part_gib FROM m")
def partitioned_memory(spark, d):
    m = sizing.partitioned_memory(50e9, 0.01, 16)
    return spark.createDataFrame([(50e9, round(m["memory"] / 2**30, 3), round(m["part_memory"] / 2**30, 3))], "n double, gib double, part_gib double")


@query()
def information_floor(spark, d):
    """Bits per word that any exact set needs, beside those of the sketch at three error rates."""
    n = words(spark, d).count()
    rows = [(f, round(sizing.information_floor(n, K), 4), round(8 * sizing.size_for_fpr(n, f).memory / n, 4)) for f in (0.01, 0.05, 0.2)]
    return spark.createDataFrame(rows, "f double, floor_bits double, sketch_bits double")


# -- spectrum -------------------------------------------------------------------------------------------------------

HIST = "SELECT {c}::BIGINT AS abundance, count(*) AS n_kmers FROM {t} GROUP BY 1"


@query(f"{BASE} {HIST.format(c='cnt', t='counts')}")
def abundance_exact(spark, d):
    return spectrum.abundance_exact(docs(spark, d), K)


def _abundance(name: str) -> None:
    def run(spark, d):
        reads = docs(spark, d)
        return spectrum.abundance_sketch(reads, PrimeSketch.build(reads, SketchSpec.for_reads(reads, RATE[name], k=K)))

    run.__name__ = f"abundance_sketch_{name}"
    query(f"{BASE},\n{sized_sql(RATE[name])},\n{sized_est_sql('counts')} {HIST.format(c='est', t='est')}")(run)


for _name in ("f01", "f05", "f20"):
    _abundance(_name)


def _rates(name: str) -> str:
    return f"""(WITH x AS ({BASE},\n{sized_sql(RATE[name])},\n{sized_est_sql('counts')} SELECT (SELECT n_estimate FROM sized) AS n_estimate, (SELECT max(c) FROM primes) AS largest, count(*) AS n_distinct, count_if(est <> least(cnt, 255)) / count(*) AS rate FROM est)
SELECT {RATE[name]}::DOUBLE AS target, n_estimate, largest, n_distinct, round(rate, 6) AS rate, abs(rate - {RATE[name]}) < 0.01 AS met FROM x)"""


@query(" UNION ALL ".join(map(_rates, RATE)))
def sized_rates(spark, d):
    """Sketches sized from an estimate of the distinct words: the rate that was asked for beside the measured one."""
    reads = docs(spark, d)
    counts, n = stored(words(spark, d)), estimate_distinct(reads, K)
    out = None
    for f in RATE.values():
        own = SketchSpec.for_fpr(n, f, k=K)
        found = acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, own)))
        row = found.select(F.lit(f).alias("target"), F.lit(n).cast("long").alias("n_estimate"), F.lit(own.primes[0]).cast("long").alias("largest"), F.col("n").alias("n_distinct"), F.col("fpr").alias("rate"), (F.abs(F.col("fpr") - f) < 0.01).alias("met"))
        out = row if out is None else out.unionByName(row)
    return out


@query()
def abundance_sketch_bloom(spark, d):
    """First sight of a word decided by filters per part instead of kept keys."""
    reads = docs(spark, d)
    return spectrum.abundance_sketch(reads, PrimeSketch.build(reads, SketchSpec.for_reads(reads, 0.01, k=K)), seen="bloom")


@query(f"""{BASE}, h AS ({HIST.format(c='cnt', t='counts')})
SELECT abundance, n_kmers, sum(n_kmers) OVER (ORDER BY abundance)::BIGINT AS cumulative, abundance * n_kmers AS n_words,
 round(n_kmers / sum(n_kmers) OVER (), 6) AS fraction, round(sum(n_kmers) OVER (ORDER BY abundance) / sum(n_kmers) OVER (), 6) AS cumulative_fraction FROM h""")
def spectrum_summary(spark, d):
    return spectrum.spectrum_summary(spectrum.abundance_exact(docs(spark, d), K))


@query()
def spectrum_coverage(spark, d):
    """Valley, peak and genome size of the deep read set."""
    at = spectrum.estimate_coverage(spectrum.abundance_exact(W.deep_reads(spark, d), K))
    return spark.createDataFrame([(at["valley"], at["peak"], float(at["genome_size"]))], "valley long, peak long, genome_size double")


@query(f"{SKETCHED} SELECT kmer, est FROM est WHERE est >= 50")
def repeats(spark, d):
    reads = docs(spark, d)
    return spectrum.repeat_kmers(reads, PrimeSketch.build(reads, spec()), 50)


@query(f"{BASE} SELECT kmer, cnt::BIGINT AS cnt FROM counts ORDER BY cnt DESC, kmer LIMIT 20")
def repeats_topk(spark, d):
    return words(spark, d).orderBy(F.desc("cnt"), "kmer").limit(20)


@query(f"""WITH {reads_sql(extra="lang || '/' || source")},\n{occ_sql()}, j AS (SELECT split_part(r.source, '/', 1) AS lang, split_part(r.source, '/', 2) AS source, o.w FROM occ o JOIN reads r USING (read_id))
SELECT lang, source, count(*) AS n_words, count(DISTINCT w) AS n_distinct FROM j GROUP BY ROLLUP(lang, source)""")
def abundance_by_lang_rollup(spark, d):
    rows = W.table(spark, d, "documents").select("doc_id", "text", F.concat("lang", F.lit("/"), "source").alias("source"))
    return rollup_by_source(R.from_documents(rows), K)


# -- accuracy -------------------------------------------------------------------------------------------------------


@query(f"{BASE}, n AS (SELECT count(*) AS n FROM counts) SELECT n, round({' * '.join(f'(1 - exp(-n / {p}))' for p in spec().primes)}, 6) AS fpr FROM n")
def fpr_analytic(spark, d):
    return words(spark, d).agg(F.count("*").alias("n")).withColumn("fpr", F.round(sum_product([1 - F.exp(-F.col("n") / p) for p in spec().primes]), 6))


def sum_product(factors):
    out = factors[0]
    for f in factors[1:]:
        out = out * f
    return out


@query(f"{BASE},\n{cells_sql()} SELECT round({' * '.join(f'((SELECT count(*) FROM t{i}) / {p})' for i, p in enumerate(spec().primes))}, 6) AS fpr")
def fpr_load(spark, d):
    sketch = PrimeSketch.build(docs(spark, d), spec()).stored(stored)
    return spark.createDataFrame([(round(sketch.load_fpr(), 6),)], "fpr double")


ACC = """SELECT {g}count(*) AS n, round(count_if(est <> t) / count(*), 6) AS fpr, round(sum(est - t) / count(*), 6) AS miscount,
 round(100 * sum((est - t) / t) / count(*), 4) AS pct, max(est - t)::BIGINT AS max_miscount, count_if(est < t)::BIGINT AS undercounts FROM (SELECT *, least(cnt, 255)::BIGINT AS t FROM est) {by}"""


@query(f"{SKETCHED} {ACC.format(g='', by='')}")
def miscount(spark, d):
    counts = stored(words(spark, d))
    return acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, spec())))


@query(f"{SKETCHED} {ACC.format(g='t AS truth, ', by='GROUP BY t')}")
def miscount_by_abundance(spark, d):
    counts = stored(words(spark, d))
    return acc.accuracy(acc.compare(counts, PrimeSketch.of_counts(counts, spec())), "truth")


@query(f"{BASE},\n{BENCH_WORDS},\n{sized_sql(0.2)},\n{sized_est_sql('q')} SELECT count(*) AS n, round(count_if(e.est > 0) / count(*), 6) AS fpr_absent FROM est e LEFT JOIN counts c ON c.kmer = e.kmer WHERE c.kmer IS NULL")
def fpr_absent(spark, d):
    reads, asked = docs(spark, d), stored(passages(spark, d))
    sketch = PrimeSketch.build(reads, SketchSpec.for_reads(reads, 0.2, k=K))
    return acc.absent_fpr(asked, stored(counts_of_few(reads, asked, K)), sketch)


@query(f"""{SKETCHED}, e AS (SELECT cnt AS a, count(*) AS n FROM counts GROUP BY 1), s AS (SELECT est AS a, count(*) AS n FROM est GROUP BY 1)
SELECT round(sum(abs(coalesce(e.n, 0) - coalesce(s.n, 0))) / sum(coalesce(e.n, 0)), 6) AS distance FROM e FULL JOIN s ON e.a = s.a""")
def histogram_distance(spark, d):
    counts = stored(words(spark, d))
    est = lookup(counts, PrimeSketch.of_counts(counts, spec()))
    return acc.histogram_distance(spectrum.histogram(counts), spectrum.histogram(est, "est"))


@query(f"{SKETCHED} SELECT quantile_cont(est - least(cnt, 255), 0.5) AS q50, quantile_cont(est - least(cnt, 255), 0.9) AS q90, quantile_cont(est - least(cnt, 255), 0.99) AS q99 FROM est")
def miscount_quantiles(spark, d):
    counts = stored(words(spark, d))
    return acc.miscount_quantiles(acc.compare(counts, PrimeSketch.of_counts(counts, spec())))


@query(f"{BASE}, m AS (SELECT avg(cnt) AS mu, stddev_pop(cnt) AS sd FROM counts) SELECT count(*) AS n, round(count_if(cnt = 1) / count(*), 6) AS unique_share, round(avg(pow((cnt - mu) / sd, 3)), 3) AS skewness FROM counts, m")
def skew_indicators(spark, d):
    return acc.skew(words(spark, d))


# -- baselines ------------------------------------------------------------------------------------------------------

PARTS = "SELECT ({c} % 97)::INTEGER AS slot, count(*) AS n_distinct, sum(cnt)::BIGINT AS n_words, sum(cnt * ({c} % 1000003))::BIGINT AS fold FROM counts {where} GROUP BY 1"


def _slots(counts: DataFrame) -> DataFrame:
    """Counts folded into slots, so that every word and its count matters."""
    return counts.groupBy((F.col("kmer") % 97).cast("int").alias("slot")).agg(F.count("*").alias("n_distinct"), F.sum("cnt").alias("n_words"), F.sum(F.col("cnt") * (F.col("kmer") % 1_000_003)).alias("fold"))


def _counter(name: str, make, where: str = "", sql: bool | str = True) -> None:
    def run(spark, d):
        return _slots(make().build(docs(spark, d)).counts)

    run.__name__ = name
    query(sql if isinstance(sql, str) else f"{BASE} {PARTS.format(c='kmer', where=where)}" if sql else None)(run)


_counter("count_hash", lambda: C.HashCounter(K))
_counter("count_hash_spill", lambda: C.SpillingHashCounter(K, max_keys=50_000))
_counter("count_suffix", lambda: C.SuffixOrderCounter(K))
_counter("count_bloom_gated", lambda: C.BloomGatedCounter(K), "WHERE cnt > 1")
_counter("count_partition_files", lambda: C.PartitionFileCounter(K))
_counter("count_bins_sort", lambda: C.SortedBinCounter(K))
_counter("count_bins_minimizer", lambda: C.MinimizerBinCounter(K))
_counter("count_containers_hash", lambda: C.ContainerCounter(K))
_counter("count_containers_bloom", lambda: C.ContainerCounter(K, kind="bloom_sort"), sql=f"{BASE},\n{sized_sql(0.1, tables=3, cap=3)},\n{sized_est_sql('counts', 3)} {PARTS.format(c='kmer', where='').replace('FROM counts', 'FROM est WHERE est >= 2')}")
_counter("count_containers_cache", lambda: C.ContainerCounter(K, kind="cache", cache_keys=50_000), sql=False)


@query(f"{BASE} {PARTS.format(c='kmer', where='')}")
def count_lcp(spark, d):
    """Suffix order in column functions: a run of equal words per count."""
    found = C.lcp_boundaries(docs(spark, d), K).filter("runs = 1")
    return _slots(found.select("kmer", "cnt"))


@query()
def count_builtin_sketch(spark, d):
    """The engine's count-min sketch: one-sided like ours, eight bytes a counter."""
    counts = stored(words(spark, d))
    raw = variants.builtin_sketch(counts)
    est = variants.builtin_lookup(spark, raw, counts)
    return acc.accuracy(counts.join(est, "kmer").select("kmer", F.col("cnt").alias("truth"), "est"))


@query()
def container_errors(spark, d):
    """Words that two inexact containers report wrongly or miss."""
    reads = docs(spark, d)
    truth = PackedWords(reads, K)
    wrong = lambda a, b: F.count_if((F.col(a) >= 2) & (F.col(b) < 2))
    gated = C.BloomGatedCounter(K).gated(truth).agg(wrong("est", "cnt").alias("false_positives"), wrong("cnt", "est").alias("false_negatives"))
    cached = C.ContainerCounter(K, kind="cache", cache_keys=50_000).build(reads).errors(truth.counts())
    return gated.select(F.lit("bloom_sort").alias("kind"), "*").unionByName(cached.select(F.lit("cache").alias("kind"), "*"))


MEMBERS = (0.05, 0.3)


def _members(f: float) -> str:
    return f"""(WITH x AS ({BASE},\n{BENCH_WORDS},\n{sized_sql(f, tables=3, cap=1)},\n{sized_est_sql('q', 3)} SELECT {f}::DOUBLE AS rate, count(*) AS n, count_if(c.kmer IS NOT NULL)::BIGINT AS n_present, count_if(e.est > 0)::BIGINT AS n_found FROM est e LEFT JOIN counts c ON c.kmer = e.kmer) SELECT * FROM x)"""


@query(" UNION ALL ".join(map(_members, MEMBERS)))
def bloom_membership(spark, d):
    """Plain Bloom filters for two rates: of the words asked, those present, and those that the filter lets through."""
    reads, asked = docs(spark, d), stored(passages(spark, d))
    n = estimate_distinct(reads, K)
    held = counts_of_few(reads, asked, K).select(F.col("kmer").alias("_k"))
    asked = stored(asked.join(held, F.col("kmer") == F.col("_k"), "left"))
    out = None
    for f in MEMBERS:
        found = lookup(asked, variants.bloom_filter_of_reads(reads, n, f, 3, K))
        row = found.agg(F.count("*").alias("n"), F.count("_k").alias("n_present"), F.count_if(F.col("est") > 0).alias("n_found")).select(F.lit(f).alias("rate"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def counting_bloom_removal(spark, d):
    """Half of the reads added and taken out again: what is left answers as if they had never been."""
    reads = docs(spark, d)
    half = F.pmod(F.xxhash64("read_id"), F.lit(2)) == 0
    a, b = exact_counts(reads.filter(half), K), exact_counts(reads.filter(~half), K)
    kept = variants.CountingBloom(8_000_000).add(a)
    again = kept.add(b).remove(b)
    return kept.cells.join(again.cells.withColumnRenamed("cnt", "again"), "cell", "full").agg(F.count("*").alias("n_cells"), F.count_if(~F.col("cnt").eqNullSafe(F.col("again"))).alias("n_different"))


@query()
def order_dependent_updates(spark, d):
    """Plain, conservative and recurring-minimum updates of the same tables, part by part."""
    reads, counts = docs(spark, d), stored(words(spark, d))
    own = SketchSpec(tuple(prime_table_sizes(SIZES["f20"] / 8, 4)), k=K, counter_bits=16)
    out = None
    for name, est in (("plain", par.sharded_estimates(reads, counts, own, 8)), ("conservative", variants.conservative_estimates(reads, own, 8)), ("recurring", variants.spectral_estimates(reads, own, 8))):
        row = acc.accuracy(counts.join(est, "kmer").select("kmer", F.col("cnt").alias("truth"), "est")).select(F.lit(name).alias("update"), "*")
        out = row if out is None else out.unionByName(row)
    return out


# -- profiles and trimming ------------------------------------------------------------------------------------------

PLACED = f"{SKETCHED}, found AS (SELECT o.read_id, o.pos, e.est FROM occ o JOIN est e ON o.w = e.w)"


@query(f"{PLACED} SELECT pos::INTEGER AS pos, count(*) AS n, count_if(est <= 1)::BIGINT AS n_rare, round(count_if(est <= 1) / count(*), 6) AS share FROM found GROUP BY pos")
def error_profile_documents(spark, d):
    reads = docs(spark, d)
    return error_profile(reads, PrimeSketch.build(reads, spec()))


@query(f"{PLACED}, p AS (SELECT f.est, coalesce(l.toxic, -1) AS toxic, length(r.seq) - 22 - f.pos AS end_pos FROM found f JOIN reads r USING (read_id) LEFT JOIN labels l ON l.doc_id = r.read_id // 10000) SELECT toxic, end_pos::INTEGER AS end_pos, count(*) AS n, count_if(est <= 1)::BIGINT AS n_rare, round(count_if(est <= 1) / count(*), 6) AS share FROM p GROUP BY ALL")
def error_profile_by_label(spark, d):
    labels = W.table(spark, d, "labels").select(F.col("doc_id").alias("_d"), "toxic")
    reads = docs(spark, d).join(labels, R.text_of(F.col("read_id")) == F.col("_d"), "left").withColumn("toxic", F.coalesce("toxic", F.lit(-1))).drop("_d")
    return error_profile(reads, PrimeSketch.build(reads, spec()), by="end_pos", group_cols=("toxic",))


FIRST = f"{PLACED}, first AS (SELECT read_id, min(pos) FILTER (est < 2) AS low, count(*) AS n, count_if(est < 2)::BIGINT AS n_low FROM found GROUP BY read_id)"


@query(f"{FIRST}, cut AS (SELECT r.read_id, CASE WHEN f.low IS NULL THEN length(r.seq) ELSE f.low + 21 END AS n FROM reads r JOIN first f USING (read_id)) SELECT read_id, n::BIGINT AS n FROM cut WHERE n >= 22")
def trim_once(spark, d):
    reads = docs(spark, d)
    return trim_reads(reads, PrimeSketch.build(reads, spec())).select("read_id", F.length("seq").cast("long").alias("n"))


@query(f"{FIRST}, cut AS (SELECT r.read_id, CASE WHEN f.low IS NULL THEN length(r.seq) ELSE f.low END AS n FROM reads r JOIN first f USING (read_id)) SELECT read_id, n::BIGINT AS n FROM cut WHERE n >= 22")
def trim_at_word_start(spark, d):
    reads = docs(spark, d)
    return trim_reads(reads, PrimeSketch.build(reads, spec()), cut="kmer_start").select("read_id", F.length("seq").cast("long").alias("n"))


@query(f"{FIRST} SELECT r.read_id FROM reads r LEFT JOIN first f USING (read_id) WHERE coalesce(f.n_low, 0) = 0")
def filter_low_reads(spark, d):
    reads = docs(spark, d)
    return filter_reads(reads, PrimeSketch.build(reads, spec())).select("read_id")


@query(f"{FIRST} SELECT r.read_id, coalesce(f.n, 0) AS n, coalesce(f.n_low, 0) AS n_low, f.low::INTEGER AS first_low FROM reads r LEFT JOIN first f USING (read_id)")
def read_window_counts(spark, d):
    reads = docs(spark, d)
    return window_counts(reads, PrimeSketch.build(reads, spec()), 2)


@query()
def trim_rounds(spark, d):
    return W.trimming_rounds(spark, d)


@query()
def trim_quality_1(spark, d):
    out, reads = None, W.deep_reads(spark, d)
    for limit in (0.05, 0.01, 0.001):
        row = qtrim_error_sum(reads, limit, K).agg(F.count("*").alias("n_reads"), F.sum(F.length("seq")).alias("n_bases")).select(F.lit(limit).alias("limit"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def trim_quality_2(spark, d):
    out, reads = None, W.deep_reads(spark, d)
    for q in (10, 20, 30):
        row = qtrim_tail(reads, q, K).agg(F.count("*").alias("n_reads"), F.sum(F.length("seq")).alias("n_bases")).select(F.lit(q).alias("min_q"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def trim_comparison(spark, d):
    return W.trimming_comparison(spark, d)


# -- normalization --------------------------------------------------------------------------------------------------


@query()
def normalize_by_methods(spark, d):
    return W.batch_sizes(spark, d)


@query()
def normalize_sweep(spark, d):
    return W.normalization_sweep(spark, d)


@query(f"""{BASE}, ranked AS (SELECT o.read_id, c.cnt, row_number() OVER (PARTITION BY o.read_id ORDER BY c.cnt) AS i, count(*) OVER (PARTITION BY o.read_id) AS n FROM occ o JOIN counts c ON o.w = c.w)
SELECT read_id FROM ranked WHERE i = n // 2 + 1 AND cnt <= 5""")
def normalize_batch_baseline(spark, d):
    reads = docs(spark, d)
    return normalize_batch(reads, words(spark, d), K, 5).select("read_id")


@query(f"""{BASE}, ranked AS (SELECT o.read_id, c.cnt, row_number() OVER (PARTITION BY o.read_id ORDER BY c.cnt) AS i, count(*) OVER (PARTITION BY o.read_id) AS n FROM occ o JOIN counts c ON o.w = c.w)
SELECT read_id FROM ranked WHERE i = n // 2 + 1 AND (cnt <= 5 OR ('0x' || substr(md5('n|42|' || read_id), 1, 15))::BIGINT % 1000000 < 5000000 // cnt)""")
def normalize_batch_by_chance(spark, d):
    reads = docs(spark, d)
    return normalize_batch(reads, words(spark, d), K, 5, "prob").select("read_id")


@query()
def normalize_documents(spark, d):
    """Documents normalized in batches: reads kept, and the load of the sketch that never saw the others."""
    reads = stored(R.with_arrival(docs(spark, d), batches=4))
    kept, sketch = normalize_batches(reads, spec(), stored, 5, 4)
    own = kept.agg(F.count("*").alias("n_kept"), F.sum(F.length("seq")).alias("n_bases"))
    return own.withColumn("load_fpr", F.lit(round(sketch.load_fpr(), 6)))


@query()
def normalize_strict_order(spark, d):
    return normalize_sequential(docs(spark, d), spec(), 5).agg(F.count("*").alias("n_kept"), F.sum(F.length("seq")).alias("n_bases"))


@query()
def large_reduction(spark, d):
    return W.large_reduction(spark, d)


# -- partitions -----------------------------------------------------------------------------------------------------


@query(f"{BASE} SELECT (kmer // {4 ** 20})::INTEGER AS part, count(*) AS n_distinct, sum(cnt)::BIGINT AS n_words, round({' * '.join(f'(1 - exp(-count(*) / {p}))' for p in spec().primes)}, 6) AS fpr FROM counts GROUP BY 1")
def prefix16_counts(spark, d):
    """Sixteen parts by the first two bases; canonical words crowd the first ones."""
    return par.part_report(par.partitioned_counts(docs(spark, d), K, "prefix"), spec())


@query(f"{BASE} {PARTS.format(c='kmer', where='')}")
def hash_parts_counts(spark, d):
    return _slots(par.partitioned_counts(docs(spark, d), K, "hash").select("kmer", "cnt"))


@query(f"{BASE} {PARTS.format(c='kmer', where='')}")
def minimizer_parts_counts(spark, d):
    return _slots(par.counts_of_bins(par.super_kmers(docs(spark, d), K), K).select("kmer", "cnt"))


@query()
def super_kmer_bytes(spark, d):
    """Bytes of super-k-mers beside those of separate words."""
    reads = docs(spark, d)
    packed = par.super_kmers(reads, K).agg(F.count("*").alias("n_runs"), F.sum(F.length("packed")).alias("packed_bytes")).withColumn("_j", F.lit(1))
    return packed.join(explode_kmers(reads, K, with_pos=False).agg((F.count("*") * 8).alias("word_bytes")).withColumn("_j", F.lit(1)), "_j").drop("_j")


@query()
def per_part_fpr(spark, d):
    return par.part_report(par.partitioned_counts(docs(spark, d), K, "hash"), spec())


@query()
def sharded_lookup(spark, d):
    """Each part counted and asked in one task: errors against the exact counts."""
    own = SketchSpec(tuple(prime_table_sizes(SIZES["f10"] / 16, 4)), k=K)
    est = par.sharded_words(PackedWords(docs(spark, d), K), own)
    return acc.accuracy(est.select("kmer", F.least("cnt", F.lit(255)).alias("truth"), "est"))


@query(f"{BASE} {PARTS.format(c='kmer', where='')}")
def parts_one_after_another(spark, d):
    return _slots(par.run_parts(docs(spark, d), shared_path(spark), K, 4, "iterative").select("kmer", "cnt"))


# -- graph ----------------------------------------------------------------------------------------------------------


@query()
def neighbors(spark, d):
    """Neighbours of the benchmark's words that the documents hold, by side."""
    reads = docs(spark, d)
    sketch = PrimeSketch.build(reads, SketchSpec.for_reads(reads, 0.01, k=K))
    return graph.neighbors(passages(spark, d), sketch).groupBy("side").agg(F.count("*").alias("n"), F.sum("est").alias("total"))


@query()
def components(spark, d):
    """Reads tied by shared words: groups by size."""
    groups = graph.graph_components(docs(spark, d), K, stored).groupBy("component").agg(F.count("*").alias("size"))
    return groups.groupBy("size").agg(F.count("*").alias("n"))


@query(f"""WITH {reads_sql()},\n{occ_sql()}, bench_dna AS (SELECT item_id AS read_id, {dna_sql('text')} AS seq FROM benchmark),
{occ_sql(reads='bench_dna', name='bench_occ')}, b AS (SELECT DISTINCT read_id AS contig_id, w FROM bench_occ), n AS (SELECT contig_id, count(*) AS n FROM b GROUP BY 1),
h AS (SELECT DISTINCT o.read_id // 10000 AS doc_id, b.contig_id, b.w FROM occ o JOIN b ON o.w = b.w)
SELECT doc_id, contig_id, count(*) AS shared, round(count(*) / any_value(n), 6) AS share FROM h JOIN n USING (contig_id) GROUP BY doc_id, contig_id""")
def containment_benchmark(spark, d):
    return graph.containment(docs(spark, d), R.genome_of(W.table(spark, d, "benchmark")), K)


@query()
def unitig_lengths(spark, d):
    return graph.unitigs(W.deep_reads(spark, d), K, stored, 3).agg(F.count("*").alias("n"), F.max("n_bases").alias("longest"), F.sum("n_bases").alias("total"))


# -- streams --------------------------------------------------------------------------------------------------------

BASES_SQL = "CASE event_type WHEN 'click' THEN 'A' WHEN 'view' THEN 'C' WHEN 'purchase' THEN 'G' WHEN 'signup' THEN 'T' ELSE 'N' END"


@query(f"WITH w AS (SELECT string_agg({BASES_SQL}, '') OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING) AS word FROM events) SELECT word, count(*) AS n FROM w WHERE length(word) = 3 AND NOT contains(word, 'N') GROUP BY word")
def stream_event_kmers(spark, d):
    found = online.event_words(W.table(spark, d, "events"), 3, R.event_bases(F.col("event_type")))
    return found.groupBy("word").agg(F.count("*").alias("n"))


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w_start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS w_end, event_type, count(*) AS n FROM events GROUP BY ALL")
def windows_tumbling(spark, d):
    return _naive(online.windowed_counts(W.table(spark, d, "events"), "1 hour"))


def _naive(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("w_start", "w_end")})


@query("WITH s AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - i * INTERVAL 30 MINUTE AS w_start, event_type FROM events, range(0, 2) t(i)) SELECT w_start, w_start + INTERVAL 1 HOUR AS w_end, event_type, count(*) AS n FROM s GROUP BY ALL")
def windows_sliding(spark, d):
    return _naive(online.windowed_counts(W.table(spark, d, "events"), "1 hour", "30 minutes"))


@query("""WITH o AS (SELECT event_type, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY event_type ORDER BY ts) + INTERVAL 5 MINUTE THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT event_type, ts, sum(new) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM o)
SELECT min(ts) AS w_start, max(ts) + INTERVAL 5 MINUTE AS w_end, event_type, count(*) AS n FROM s GROUP BY event_type, session""")
def windows_session(spark, d):
    return _naive(online.windowed_counts(W.table(spark, d, "events"), gap="5 minutes"))


@query("""WITH v AS (SELECT time_bucket(INTERVAL 6 HOUR, ts) AS at, count(*) AS version_rows FROM events GROUP BY 1)
SELECT e.event_id, max(v.at) AS version FROM events e LEFT JOIN v ON v.at <= e.ts GROUP BY e.event_id""")
def asof_sketch_version(spark, d):
    """For each event the latest version that began before it: an as-of join by one ordered pass per day.

    Events are cut into days, each day with the last version before it, so no task holds all of them.
    """
    events = W.table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    six = F.window("ts", "6 hours").start
    versions = events.select(six.alias("ts")).distinct()
    day = F.date_trunc("day", "ts")
    both = events.select("event_id", "ts", F.lit(None).cast("timestamp").alias("version"), day.alias("day")).unionByName(versions.select(F.lit(None).cast("long").alias("event_id"), "ts", F.col("ts").alias("version"), day.alias("day")))
    last = F.last("version", ignorenulls=True).over(Window.partitionBy("day").orderBy("ts", F.col("version").desc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("v", last).filter("event_id IS NOT NULL").select("event_id", F.col("v").cast("timestamp_ntz").alias("version"))


# -- workloads ------------------------------------------------------------------------------------------------------


@query()
def growing_subsets(spark, d):
    return W.growing_subsets(spark, d)


@query()
def miscount_sweep(spark, d):
    return W.miscount_sweep(spark, d)


@query()
def profile_by_position(spark, d):
    return W.profile_by_position(spark, d)


@query()
def retrieval_sets(spark, d):
    return W.retrieval_sets(spark, d)


@query()
def scaling_slope(spark, d):
    """Distinct words against words over the growing subsets: slope and R squared."""
    return acc.linear_fit(W.growing_subsets(spark, d), "n_words", "n_distinct").select(F.round("slope", 9).alias("slope"), F.round("r2", 9).alias("r2"))


@query()
def disk_use(spark, d):
    return costs.disk_use(docs(spark, d), spec())


@query()
def counter_times(spark, d):
    return costs.counter_times(docs(spark, d), K)


@query()
def lookup_cost(spark, d):
    return costs.lookup_cost(docs(spark, d), passages(spark, d), spec())


@query()
def partition_scaling(spark, d):
    return costs.partition_scaling(docs(spark, d), spec())


TURNS = f"""WITH t AS (SELECT conv_id * 100 + turn AS tid, role, text FROM conversations), {reads_sql('t', 'tid', 'text', 'role')},\n{occ_sql()},\n{counts_sql()},\n{cells_sql()} """


@query(TURNS + " UNION ALL ".join(BLOCKS.format(i=i) for i in range(4)))
def stream_sketch_equals_batch(spark, d):
    """Turns counted as a stream into a versioned sketch: the counters of a batch."""
    turns = W.table(spark, d, "conversations")
    stream = spark.readStream.schema(turns.schema).parquet(f"{d}/conversations.parquet*")
    sketch = online.VersionedSketch(spark, shared_path(spark), spec())
    online.count_stream(R.from_conversations(stream), sketch, shared_path(spark)).awaitTermination()
    return _blocks(sketch.current())


# -- relational surface ---------------------------------------------------------------------------------------------


@query(f"{BASE},\n{BENCH_WORDS} SELECT kmer, cnt::BIGINT AS cnt FROM counts SEMI JOIN q USING (kmer)")
def semi_true_kept(spark, d):
    return words(spark, d).join(passages(spark, d), "kmer", "left_semi")


@query(f"{BASE},\n{BENCH_WORDS} SELECT count(*) AS n, sum(cnt)::BIGINT AS total FROM counts ANTI JOIN q USING (kmer)")
def anti_erroneous(spark, d):
    return words(spark, d).join(passages(spark, d), "kmer", "left_anti").agg(F.count("*").alias("n"), F.sum("cnt").alias("total"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, count(DISTINCT l_partkey) AS n_items FROM lineitem GROUP BY CUBE(l_returnflag, l_linestatus)")
def cube_items(spark, d):
    return W.table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.count_distinct("l_partkey").alias("n_items"))


@query("""SELECT r_name, n_name, count(*) AS n, count(DISTINCT l_partkey) AS n_items FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP(r_name, n_name)""")
def rollup_region(spark, d):
    t = lambda n: W.table(spark, d, n)
    chain = t("lineitem").select("l_orderkey", "l_partkey").join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    chain = chain.join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    chain = chain.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return chain.rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.count_distinct("l_partkey").alias("n_items"))


@query("SELECT lang, source, count(*) AS n, sum(length(text))::BIGINT AS n_chars, grouping(lang, source) AS level FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
def grouping_sets_source(spark, d):
    W.table(spark, d, "documents").createOrReplaceTempView("_docs_gs")
    return spark.sql("SELECT lang, source, count(*) AS n, sum(length(text)) AS n_chars, grouping_id(lang, source) AS level FROM _docs_gs GROUP BY GROUPING SETS ((lang, source), (lang), ())")


RANKS = "row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, lag(n_chars) OVER w AS before, lead(n_chars) OVER w AS after, sum(n_chars) OVER (PARTITION BY source ORDER BY n_chars, doc_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS near, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS alike"


@query(f"SELECT doc_id, {RANKS} FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id)")
def window_functions(spark, d):
    w = Window.partitionBy("source").orderBy("n_chars", "doc_id")
    return W.table(spark, d, "documents").select(
        "doc_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("nt"), F.lag("n_chars").over(w).alias("before"), F.lead("n_chars").over(w).alias("after"),
        F.sum("n_chars").over(w.rowsBetween(-2, 0)).alias("near"), F.count("*").over(Window.partitionBy("source").orderBy("n_chars").rangeBetween(-100, 0)).alias("alike"),
    )


@query(f"""{BASE},\n{BENCH_WORDS} SELECT 'union' AS op, count(*) AS n FROM (SELECT kmer FROM counts UNION SELECT kmer FROM q) UNION ALL
SELECT 'intersect', count(*) FROM (SELECT kmer FROM counts INTERSECT SELECT kmer FROM q) UNION ALL SELECT 'except', count(*) FROM (SELECT kmer FROM q EXCEPT SELECT kmer FROM counts)""")
def set_operations(spark, d):
    a, b = words(spark, d).select("kmer"), passages(spark, d)
    rows = (("union", a.unionByName(b).distinct()), ("intersect", a.intersect(b)), ("except", b.exceptAll(a.distinct()).distinct()))
    out = None
    for name, df in rows:
        row = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS total, max((props->>'k')::BIGINT) AS most FROM events GROUP BY event_type")
def json_props(spark, d):
    k = F.from_json("props", "k long")["k"]
    return W.table(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("total"), F.max(k).alias("most"))


@query(f"""WITH p AS (SELECT page_id, regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '&[a-zA-Z#0-9]+;', ' ', 'g') AS t, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages),
{reads_sql('p', 'page_id', 't', 'host')},\n{occ_sql()} SELECT source, count(*) AS n_words, count(DISTINCT w) AS n_distinct FROM occ JOIN reads USING (read_id) GROUP BY source""")
def html_pages(spark, d):
    reads = R.from_pages(W.table(spark, d, "pages"))
    return counts_by_source(reads, K).groupBy("source").agg(F.sum("cnt").alias("n_words"), F.count("*").alias("n_distinct"))


@query(f"""WITH t AS (SELECT conv_id * 100 + turn AS tid, role, text FROM conversations), {reads_sql('t', 'tid', 'text', 'role')},\n{occ_sql()}
SELECT source AS role, count(*) AS n_words, count(DISTINCT w) AS n_distinct FROM occ JOIN reads USING (read_id) GROUP BY source""")
def conversation_turns(spark, d):
    reads = R.from_conversations(W.table(spark, d, "conversations"))
    return counts_by_source(reads, K).groupBy(F.col("source").alias("role")).agg(F.sum("cnt").alias("n_words"), F.count("*").alias("n_distinct"))


@query(f"{BASE} SELECT kmer, w AS word FROM counts WHERE cnt >= 30")
def udf_encode(spark, d):
    """Codes and words through the functions registered for SQL."""
    udf.register(spark)
    words(spark, d).filter("cnt >= 30").createOrReplaceTempView("_udf_words")
    return spark.sql(f"SELECT encode_kmer(word) AS kmer, word FROM (SELECT decode_kmer(kmer, {K}) AS word FROM _udf_words)")


@query(f"WITH bench_dna AS (SELECT item_id AS read_id, {dna_sql('text')} AS seq FROM benchmark),\n{occ_sql(reads='bench_dna')} SELECT read_id AS contig_id, pos::INTEGER AS pos, {code_sql('w')} AS kmer FROM occ")
def udtf_kmers(spark, d):
    udf.register(spark)
    R.genome_of(W.table(spark, d, "benchmark")).createOrReplaceTempView("_udtf_genome")
    return spark.sql(f"SELECT contig_id, pos, kmer FROM _udtf_genome, LATERAL kmers_of(seq, {K})")


@query(f"{BASE}, p AS (SELECT (kmer // {4 ** 20})::INTEGER AS part, kmer % {prime_table_sizes(SIZES['f20'], 1)[0]} AS cell FROM counts) SELECT part, count(DISTINCT cell) AS n_cells FROM p GROUP BY part")
def udaf_sketch(spark, d):
    """Counters in use by group, through a grouped Arrow aggregate."""
    prime = prime_table_sizes(SIZES["f20"], 1)[0]
    own = words(spark, d).select(par.part_of(F.col("kmer"), K, "prefix").alias("part"), "kmer")
    return own.groupBy("part").agg(udf.distinct_cells_udf("kmer", F.lit(prime)).alias("n_cells"))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Abundance histograms of the documents, exact and from a sketch at 1%, side by side."""
    reads = docs(spark, d)
    own = SketchSpec.for_reads(reads, 0.01, k=K)
    if spectrum.by_parts(own):
        both = PackedWords(reads, K).estimates(own)
    else:
        counts = stored(exact_counts(reads, K))
        both = lookup(counts, PrimeSketch.of_counts(counts, own))
    both = stored(both.groupBy("cnt", "est").agg(F.count("*").alias("n")))
    exact = both.groupBy(F.col("cnt").alias("abundance")).agg(F.sum("n").alias("n_exact"))
    sketched = both.groupBy(F.col("est").alias("abundance")).agg(F.sum("n").alias("n_sketch"))
    return exact.join(sketched, "abundance", "full").select("abundance", F.coalesce("n_exact", F.lit(0)).alias("n_exact"), F.coalesce("n_sketch", F.lit(0)).alias("n_sketch"))


@query(f"{BASE},\n{sized_sql(0.01)},\n{sized_est_sql('counts')}, e AS (SELECT cnt AS a, count(*) AS n FROM counts GROUP BY 1), s AS (SELECT est AS a, count(*) AS n FROM est GROUP BY 1) SELECT coalesce(e.a, s.a)::BIGINT AS abundance, coalesce(e.n, 0) AS n_exact, coalesce(s.n, 0) AS n_sketch FROM e FULL JOIN s ON e.a = s.a")
def histograms(spark, d):
    return flagship(spark, d)


__all__ = ["QUERIES", "SQL", "flagship", "trim_iterative"]
