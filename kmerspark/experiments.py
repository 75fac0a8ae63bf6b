"""Registered queries of the experiments that SQL can follow: simulated reads, trimming, normalization, subsets, look-ups.

The simulation draws from counters through whole-number mixes, so SQL makes the same reads, base by base.
"""

from __future__ import annotations

import re

from pyspark.sql import functions as F

from .operators import spectrum
from .operators.index import SortedIndex
from .operators.kmers import exact_counts, explode_kmers
from .operators.lookup import lookup, read_statistics
from .operators.normalize import keep_by_batches, normalize_sequential
from .operators.sketch import PrimeSketch, SketchSpec
from .operators.store import shared_path, stored
from .operators.trim import filter_reads, trim_iterative
from .plans import growing
from .plans import workloads as W
from .plans.sizing import prime_table_sizes
from .queries import BASE, BENCH_WORDS, K, QUERIES, RC, SIZES, SKETCHED, SQL, code_sql, counts_sql, dna_sql, docs, occ_sql, passages, query, reads_sql, sized_est_sql, sized_sql, spec, words
from .sources import reads as R
from .sources.generated import ReadsFromGenome
from .streaming.online import OnlineCounter


def register(name: str, sql: str) -> None:
    """SQL for a query that is registered elsewhere."""
    assert name in QUERIES and name not in SQL
    SQL[name] = sql


# -- simulated reads ------------------------------------------------------------------------------------------------

M = "18446744073709551616::UHUGEINT"
OFFSET = 42 * 0x9E3779B97F4A7C15 % 2**64


def _draw_sql(rows: str, stream: int) -> str:
    """read_id, pos and d: the simulation's number for each cell of a stream."""
    a = f"SELECT *, (cell * 4 + {stream - 1} + {OFFSET}::UHUGEINT) % {M} AS x FROM {rows}"
    b = f"SELECT *, (xor(x, x >> 30) * {0xBF58476D1CE4E5B9}::UHUGEINT) % {M} AS y FROM ({a})"
    c = f"SELECT *, (xor(y, y >> 27) * {0x94D049BB133111EB}::UHUGEINT) % {M} AS z FROM ({b})"
    return f"d{stream} AS (SELECT cell, xor(z, z >> 31) AS d FROM ({c}))"


def simulated_sql(coverage: int = 50, ppm: int = 10_000, read_len: int = 100) -> str:
    return f"""contigs AS (SELECT item_id, {dna_sql('text')} AS s FROM benchmark),
genome AS (SELECT string_agg(s, '' ORDER BY item_id) AS g FROM contigs WHERE length(s) > 0),
starts AS (SELECT i AS read_id, ('0x' || substr(md5('s|42|' || i), 1, 15))::BIGINT % (length(g) - {read_len} + 1) AS start, g FROM genome, range(0, {coverage} * length(g) // {read_len}) t(i)),
bases AS (SELECT read_id, pos, (read_id * {read_len} + pos)::UHUGEINT AS cell, substring(g, start + pos + 1, 1) AS drawn_from FROM starts, range(0, {read_len}) p(pos)),
{', '.join(_draw_sql('bases', i) for i in (1, 2, 3, 4))},
drawn AS (SELECT b.read_id, b.pos, b.drawn_from, d1.d % 1000000 < {4 * ppm} * pos * pos * pos // {read_len**3} AS wrong, substring('ACGT', ((strpos('ACGT', b.drawn_from) + (d2.d % 3)::INTEGER) % 4) + 1, 1) AS other, d3.d % 5 AS jitter, d4.d % 10 < 8 AS seen
 FROM bases b JOIN d1 USING (cell) JOIN d2 USING (cell) JOIN d3 USING (cell) JOIN d4 USING (cell)),
sim AS (SELECT read_id, pos, CASE WHEN wrong THEN other ELSE drawn_from END AS base, wrong, greatest(2, 40 - floor(36 * pow(pos / {read_len}.0::DOUBLE, 3))::INTEGER - jitter::INTEGER - CASE WHEN wrong AND seen THEN 20 ELSE 0 END) AS q FROM drawn),
reads AS (SELECT read_id, 'sim' AS source, string_agg(base, '' ORDER BY pos) AS seq FROM sim GROUP BY read_id)"""


DEEP = f"WITH {simulated_sql()}"
DEEP_COUNTS = f"{DEEP},\n{occ_sql()},\n{counts_sql()}"


def exactly_sized_sql(f: float) -> str:
    """As sized_sql, from the exact number of distinct words."""
    return sized_sql(f).replace("17 * count(*)", "count(*)").replace("WHERE kmer % 17 = 0", "")


@query(f"{DEEP} SELECT read_id, seq, (SELECT count(*) FROM sim s WHERE s.read_id = r.read_id AND s.wrong) AS n_errors, (SELECT sum(q * (pos + 1)) FROM sim s WHERE s.read_id = r.read_id)::BIGINT AS quality FROM reads r")
def simulated_reads(spark, d):
    """Deep reads with errors that rise to the 3' end, base by base, with their scores folded."""
    reads = W.deep_reads(spark, d)
    quality = F.aggregate(F.transform("qual", lambda q, i: q.cast("long") * (i + 1)), F.lit(0).cast("long"), lambda s, x: s + x)
    return reads.select("read_id", "seq", F.col("n_errors").cast("long").alias("n_errors"), quality.alias("quality"))


@query(f"{DEEP} SELECT read_id, substring(g, start + 1, 100) AS seq FROM starts")
def python_data_source(spark, d):
    """Reads without errors from a data source written in Python, at the places that the simulation draws."""
    genome = W.small_genome(spark, d)
    spark.dataSource.register(ReadsFromGenome)
    return spark.read.format("reads_from_genome").option("genome", genome).option("reads", 50 * len(genome) // 100).load()


register("spectrum_coverage", f"""{DEEP_COUNTS}, h AS (SELECT cnt AS a, count(*) AS n FROM counts GROUP BY 1), near AS (SELECT a, n, lead(n) OVER (ORDER BY a) AS after FROM h WHERE a < 1000),
v AS (SELECT coalesce(min(a) FILTER (after > n), max(a)) AS valley FROM near), p AS (SELECT arg_max(a, (n, -a)) AS peak FROM near, v WHERE a >= valley)
SELECT valley::BIGINT AS valley, peak::BIGINT AS peak, (SELECT sum(a * n) FROM h, v WHERE a >= valley)::DOUBLE / greatest(1, peak) AS genome_size FROM v, p""")

register("profile_by_position", f"{DEEP_COUNTS},\n{exactly_sized_sql(0.01)},\n{sized_est_sql('counts')} SELECT pos::INTEGER AS pos, count(*) AS n, count_if(est <= 1)::BIGINT AS n_rare, round(count_if(est <= 1) / count(*), 6) AS share FROM occ o JOIN est e ON o.w = e.w GROUP BY pos")

register("trim_quality_2", f"{DEEP}, kept AS (SELECT m.q AS min_q, read_id, max(pos) FILTER (sim.q >= m.q) + 1 AS n FROM sim, (VALUES (10), (20), (30)) m(q) GROUP BY ALL) SELECT min_q, count(*) AS n_reads, sum(n)::BIGINT AS n_bases FROM kept WHERE n >= {K} GROUP BY min_q")

register("trim_quality_1", f"""{DEEP}, l AS (SELECT * FROM (VALUES (0.05::DOUBLE, 50000), (0.01::DOUBLE, 10000), (0.001::DOUBLE, 1000)) v(l, ppm)),
steps AS (SELECT l, read_id, pos + 1 AS i, sum(ppm - round_even(1000000 * pow(10, -q / 10.0::DOUBLE), 0)::BIGINT) OVER (PARTITION BY l, read_id ORDER BY pos) AS s FROM sim, l UNION ALL SELECT l, read_id, 0, 0 FROM reads, l),
lows AS (SELECT *, min(s) OVER (PARTITION BY l, read_id ORDER BY i) AS low FROM steps), firsts AS (SELECT l, read_id, s, min(i) AS i FROM steps GROUP BY ALL),
ends AS (SELECT a.l, a.read_id, a.i AS e, f.i AS b, a.s - a.low AS gain, max(a.s - a.low) OVER (PARTITION BY a.l, a.read_id) AS top FROM lows a JOIN firsts f ON f.l = a.l AND f.read_id = a.read_id AND f.s = a.low),
best AS (SELECT l, read_id, arg_min(e - b, (b, -e)) AS n FROM ends WHERE gain = top AND top > 0 GROUP BY ALL) SELECT l AS "limit", count(*) AS n_reads, sum(n)::BIGINT AS n_bases FROM best WHERE n >= {K} GROUP BY l""")


def rounds_sql(head: str, rounds: int, size: str, primes: list[str], cutoff: int = 2) -> str:
    """Rounds of trimming, each with fresh counts and a sketch of the same size: reads{r} is left after round r."""
    out = [f"{head}, {size}reads0 AS (SELECT read_id, seq FROM reads)"]
    for r in range(1, rounds + 1):
        cells = ", ".join(f"t{i}_{r} AS (SELECT kmer % {p} AS cell, least(sum(cnt), 255)::BIGINT AS cnt FROM counts{r} GROUP BY 1)" for i, p in enumerate(primes))
        joins = " ".join(f"JOIN t{i}_{r} ON t{i}_{r}.cell = c.kmer % {p}" for i, p in enumerate(primes))
        least = ", ".join(f"t{i}_{r}.cnt" for i in range(len(primes)))
        out.append(f"""{occ_sql(reads=f'reads{r - 1}', name=f'occ{r}')}, counts{r} AS MATERIALIZED (SELECT {code_sql('w')} AS kmer, w, count(*) AS cnt FROM occ{r} GROUP BY w),
{cells}, est{r} AS MATERIALIZED (SELECT c.*, least({least}) AS est FROM counts{r} c {joins}),
cut{r} AS (SELECT read_id, min(pos) FILTER (est < {cutoff}) AS low FROM occ{r} o JOIN est{r} e ON o.w = e.w GROUP BY read_id),
reads{r} AS MATERIALIZED (SELECT read_id, s AS seq FROM (SELECT r.read_id, CASE WHEN low IS NULL THEN seq ELSE substring(seq, 1, low + {K - 1}) END AS s FROM reads{r - 1} r JOIN cut{r} USING (read_id)) WHERE length(s) >= {K})""")
    return ",\n".join(out)


def round_log_sql(r: int) -> str:
    """The log of one round, as trim_iterative gives it."""
    left = f"(SELECT sum(length(seq)) FROM reads{r})"
    words_left = f"""(SELECT w, count(*) AS cnt, count_if(pos = length(seq) - {K})::BIGINT AS at_end FROM ({occ_sql(reads=f'reads{r}', name='x').removeprefix('x AS (').removesuffix(')')}) JOIN reads{r} USING (read_id) GROUP BY w)"""
    return f"""SELECT {r} AS round, (SELECT round(count_if(est <> least(cnt, 255)) / count(*), 6) FROM est{r}) AS fpr, round(100 * ((SELECT sum(length(seq)) FROM reads{r - 1}) - {left}) / (SELECT sum(length(seq)) FROM reads0), 6) AS bases_removed,
 (SELECT count(*) FROM {words_left}) AS n_distinct, (SELECT count(*) FROM {words_left} WHERE cnt = 1) AS n_unique, (SELECT count(*) FROM {words_left} WHERE cnt = 1 AND at_end = 1) AS n_unique_3p"""


_P = [f"(SELECT c FROM primes WHERE i = {i})" for i in range(4)]
_SIZE = exactly_sized_sql(0.8).split(",\nt0 AS")[0]
register("trim_rounds", rounds_sql(DEEP_COUNTS, 6, f"{_SIZE},\n", _P) + "\n" + "\nUNION ALL ".join(round_log_sql(r) for r in range(1, 7)))


def _named(text: str, tag: str) -> str:
    """The tables of one round and of its sizing, under names of their own."""
    return re.sub(r"\b(sized|candidates|primes|reads0|reads1|occ1|counts1|est1|cut1|t\d_1)\b", rf"\1{tag}", text)


def _left_sql(name: str, rows: str) -> str:
    """A trimmer's row: bases removed, and the true and erroneous words that are left."""
    return f"""SELECT '{name}' AS trimmer, round(100 * (1 - (SELECT sum(length(seq)) FROM {rows}) / (SELECT sum(length(seq)) FROM reads)), 4) AS bases_removed, nb.t AS true_before, nb.e AS error_before, na.t AS true_after, na.e AS error_after,
 round(na.t / nb.t, 6) AS true_kept, round(1 - na.e / nb.e, 6) AS error_removed FROM nb, (SELECT count(truth.w) AS t, count(*) - count(truth.w) AS e FROM (SELECT DISTINCT w FROM ({occ_sql(reads=rows, name='x').removeprefix('x AS (').removesuffix(')')})) a LEFT JOIN truth ON truth.w = a.w) na"""


_QUALITY = f"""l AS (SELECT * FROM (VALUES (1, 50000), (2, 10000), (3, 1000)) v(l, ppm)),
steps AS (SELECT l, read_id, pos + 1 AS i, sum(ppm - round_even(1000000 * pow(10, -q / 10.0::DOUBLE), 0)::BIGINT) OVER (PARTITION BY l, read_id ORDER BY pos) AS s FROM sim, l UNION ALL SELECT l, read_id, 0, 0 FROM reads, l),
lows AS (SELECT *, min(s) OVER (PARTITION BY l, read_id ORDER BY i) AS low FROM steps), firsts AS (SELECT l, read_id, s, min(i) AS i FROM steps GROUP BY ALL),
ends AS (SELECT a.l, a.read_id, a.i AS e, f.i AS b, a.s - a.low AS gain, max(a.s - a.low) OVER (PARTITION BY a.l, a.read_id) AS top FROM lows a JOIN firsts f ON f.l = a.l AND f.read_id = a.read_id AND f.s = a.low),
best AS MATERIALIZED (SELECT l, read_id, min((b, -e)) AS x FROM ends WHERE gain = top AND top > 0 GROUP BY ALL),
""" + ",\n".join(f"sum{i} AS (SELECT read_id, substring(seq, x[1] + 1, -x[2] - x[1]) AS seq FROM best JOIN reads USING (read_id) WHERE l = {i} AND -x[2] - x[1] >= {K})" for i in (1, 2, 3)) + ",\n" + ",\n".join(
    f"tail{q} AS (SELECT read_id, substring(seq, 1, n) AS seq FROM (SELECT read_id, max(pos) + 1 AS n FROM sim WHERE q >= {q} GROUP BY 1) JOIN reads USING (read_id) WHERE n >= {K})" for q in (10, 20, 30))
_TRIMMED = {"none": "reads", "sketch_f01": "reads1_one", "sketch_f80": "reads1", "sketch_six_rounds": "reads6", "error_sum_0.05": "sum1", "error_sum_0.01": "sum2", "error_sum_0.001": "sum3", "tail_10": "tail10", "tail_20": "tail20", "tail_30": "tail30"}
_SIZE01 = exactly_sized_sql(0.01).split(",\nt0 AS")[0]
register("trim_comparison", rounds_sql(DEEP_COUNTS, 6, f"{_SIZE},\n", _P) + _named(rounds_sql("", 1, f"{_SIZE01},\n", _P), "_one") + f""",
{_QUALITY}, truth AS MATERIALIZED (SELECT DISTINCT least(f, {RC.format('f')}) AS w FROM (SELECT substring(g, i + 1, {K}) AS f FROM genome, range(0, length(g) - {K - 1}) t(i))),
nb AS (SELECT count(truth.w) AS t, count(*) - count(truth.w) AS e FROM (SELECT DISTINCT w FROM occ) a LEFT JOIN truth ON truth.w = a.w)
""" + "\nUNION ALL ".join(_left_sql(n, t) for n, t in _TRIMMED.items()))


@query(rounds_sql(f"WITH {reads_sql()}", 2, "", [str(p) for p in prime_table_sizes(SIZES["f10"], 4)]) + "\n" + "\nUNION ALL ".join(round_log_sql(r) for r in (1, 2)))
def trim_rounds_documents(spark, d):
    """Two rounds over the documents, with a sketch of fixed size."""
    return trim_iterative(docs(spark, d), spec(), stored, 2)[1]


@query(f"{SKETCHED}, found AS (SELECT o.read_id, e.est FROM occ o JOIN est e ON o.w = e.w), kept AS (SELECT read_id FROM found GROUP BY read_id HAVING count_if(est < 2) < count(*)) SELECT read_id FROM kept")
def filter_all_low_reads(spark, d):
    """Reads are dropped only if all their words are rare, or they have none."""
    reads = docs(spark, d)
    return filter_reads(reads, PrimeSketch.build(reads, spec()), mode="all").select("read_id")


@query(f"{SKETCHED}, found AS (SELECT o.read_id, e.est FROM occ o JOIN est e ON o.w = e.w) SELECT read_id, count(*) AS n, min(est) AS low, max(est) AS high, sum(est)::BIGINT AS total, list_sort(list(est))[count(*) // 2 + 1] AS median FROM found GROUP BY read_id")
def read_abundance(spark, d):
    """Least, greatest, total and upper-median count of each read's words."""
    reads = docs(spark, d)
    return read_statistics(explode_kmers(reads, K), PrimeSketch.build(reads, spec()))


@query(f"{DEEP_COUNTS}, truth AS (SELECT DISTINCT {code_sql('w')} AS kmer FROM (SELECT least(f, {RC.format('f')}) AS w FROM (SELECT substring(g, i + 1, {K}) AS f FROM genome, range(0, length(g) - {K - 1}) t(i)))) SELECT CASE WHEN cnt < 3 THEN 'error' ELSE 'true' END AS kind, count(*) AS n, count(t.kmer) AS n_true FROM counts c LEFT JOIN truth t USING (kmer) GROUP BY 1")
def classified_words(spark, d):
    """Words of deep reads called errors by their count, against the genome they came from."""
    counts = exact_counts(W.deep_reads(spark, d), K)
    called = spectrum.classify_kmers(counts, 3).join(W.true_words(spark, d).withColumn("_t", F.lit(1)), "kmer", "left")
    return called.groupBy("kind").agg(F.count("*").alias("n"), F.count("_t").alias("n_true"))


# -- normalization --------------------------------------------------------------------------------------------------


def batches_sql(n_batches: int, coverage: int, primes: list[int]) -> str:
    out = [f"WITH {reads_sql()},\n{occ_sql()},\nbatched AS MATERIALIZED (SELECT read_id, read_id // 10000 % {n_batches} AS batch, {code_sql('w')} AS kmer FROM occ),\nkept0 AS MATERIALIZED (SELECT DISTINCT read_id FROM batched WHERE batch = 0)"]
    for b in range(1, n_batches):
        cells = ", ".join(f"t{i}_{b} AS (SELECT kmer % {p} AS cell, least(count(*), 255) AS cnt FROM batched SEMI JOIN kept{b - 1} USING (read_id) GROUP BY 1)" for i, p in enumerate(primes))
        joins = " ".join(f"LEFT JOIN t{i}_{b} ON t{i}_{b}.cell = o.kmer % {p}" for i, p in enumerate(primes))
        est = f"least({', '.join(f'coalesce(t{i}_{b}.cnt, 0)' for i in range(len(primes)))})"
        out.append(f"{cells}, kept{b} AS MATERIALIZED (SELECT read_id FROM kept{b - 1} UNION ALL SELECT read_id FROM (SELECT o.read_id, {est} AS est FROM batched o {joins} WHERE batch = {b}) GROUP BY read_id HAVING count_if(est < {coverage}) >= count(*) // 2 + 1)")
    return ",\n".join(out)


@query(batches_sql(4, 3, prime_table_sizes(SIZES["f10"], 4)) + " SELECT r.read_id // 10000 % 4 AS batch, count(*) AS n_kept, sum(length(seq))::BIGINT AS n_bases FROM reads r SEMI JOIN kept3 USING (read_id) GROUP BY 1")
def normalize_documents_in_batches(spark, d):
    """Documents in four batches by id: a read is kept while the sketch of those kept before finds it rare."""
    reads = docs(spark, d).withColumn("batch", F.pmod(R.text_of(F.col("read_id")), F.lit(4)))
    kept = keep_by_batches(reads, spec(), stored, 3, 4)
    return kept.groupBy("batch").agg(F.count("*").alias("n_kept"), F.sum(F.length("seq")).alias("n_bases"))


STRICT = f"""WITH RECURSIVE bench AS (SELECT item_id AS sid, {dna_sql('text')} AS s FROM benchmark),
cut AS (SELECT (sid * 1000 + i) AS id, substring(s, i * 100 + 1, 100) AS seq FROM (SELECT *, unnest(range(0, (length(s) + 99) // 100)) AS i FROM bench)),
reads AS (SELECT id * 3 + c AS read_id, seq FROM cut, range(0, 3) t(c)), {occ_sql()},
listed AS MATERIALIZED (SELECT read_id, row_number() OVER (ORDER BY read_id) AS i FROM occ GROUP BY read_id),
placed AS MATERIALIZED (SELECT l.i, o.pos, o.w FROM occ o JOIN listed l USING (read_id)),
held AS MATERIALIZED (SELECT i, w, count(*) AS m FROM placed GROUP BY ALL),
earlier AS MATERIALIZED (SELECT p.i, list((p.pos, h.i, h.m)) AS met, count(DISTINCT p.pos) AS n FROM placed p LEFT JOIN held h ON h.w = p.w AND h.i < p.i GROUP BY p.i),
steps AS (SELECT 0::BIGINT AS i, []::BIGINT[] AS kept UNION ALL
 SELECT i, CASE WHEN n_low >= n // 2 + 1 THEN list_append(kept, i) ELSE kept END FROM (
  SELECT e.i, s.kept, e.n, e.n - len(list_filter(list_distinct(list_transform(e.met, lambda x: x[1])), lambda p: list_sum(list_transform(list_filter(e.met, lambda y: y[1] = p AND list_contains(s.kept, y[2])), lambda y: y[3])) >= 2)) AS n_low
  FROM steps s JOIN earlier e ON e.i = s.i + 1))"""


def benchmark_thrice(spark, d):
    """Every benchmark read three times, copies next to one another."""
    reads = R.cut_reads(W.table(spark, d, "benchmark"), "item_id", R.project_text(F.col("text")))
    number = R.text_of(F.col("read_id")) * 1000 + F.pmod("read_id", F.lit(R.READS_PER_TEXT))
    return reads.select("seq", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("_c"), number.alias("_n")).select((F.col("_n") * 3 + F.col("_c")).alias("read_id"), "seq")


@query(STRICT + " SELECT l.read_id FROM (SELECT kept FROM steps ORDER BY i DESC LIMIT 1) k, listed l WHERE list_contains(k.kept, l.i)")
def normalize_strict_small(spark, d):
    """Strict order over three copies of every benchmark read, to coverage 2: the third copy is never kept."""
    reads = stored(benchmark_thrice(spark, d))
    kept = normalize_sequential(reads, SketchSpec.for_fpr(1_000_000, 1e-6, k=K), 2)
    return kept.select("read_id")


# -- subsets, look-ups, costs ---------------------------------------------------------------------------------------

FIFTH = "read_id // 10000 % 5"


def subset_sql(i: int) -> str:
    return f"reads{i} AS (SELECT * FROM reads WHERE {FIFTH} < {i}), {occ_sql(reads=f'reads{i}', name=f'occ{i}')}, n{i} AS (SELECT {i} AS subset, count(*) AS n_words, count(DISTINCT w) AS n_distinct FROM occ{i})"


SUBSETS = f"WITH {reads_sql()},\n" + ",\n".join(map(subset_sql, range(1, 6))) + ", subsets AS (" + " UNION ALL ".join(f"SELECT * FROM n{i}" for i in range(1, 6)) + ")"


def _per_word(f: float) -> float:
    from .plans.sizing import size_for_fpr

    return size_for_fpr(1, f).memory


register("information_floor", f"""{BASE}, n AS (SELECT count(*)::DOUBLE AS n, pow(4::DOUBLE, {K}) AS t FROM counts)
SELECT f::DOUBLE AS f, round((lgamma(t + 1) - lgamma(n + 1) - lgamma(t - n + 1)) / ln(2) / n, 4) AS floor_bits, round(-8 * ln(f) / pow(ln(2), 2), 4) AS sketch_bits FROM n, (VALUES (0.01::DOUBLE), (0.05::DOUBLE), (0.2::DOUBLE)) v(f)""")

register("unitig_lengths", f"""WITH RECURSIVE {DEEP.removeprefix('WITH ')},\n{occ_sql(stranded=True)}, nodes AS MATERIALIZED (SELECT w FROM occ GROUP BY w HAVING count(*) >= 3),
outs AS (SELECT substring(w, 1, {K - 1}) AS mid, count(*) AS n_out, min(w) AS next FROM nodes GROUP BY 1), ins AS (SELECT substring(w, 2) AS mid, count(*) AS n_in, min(w) AS prev FROM nodes GROUP BY 1),
edges AS MATERIALIZED (SELECT prev, next FROM outs JOIN ins USING (mid) WHERE n_in = 1 AND n_out = 1 AND next <> prev),
walk AS (SELECT w AS first, w, 1 AS n FROM nodes ANTI JOIN edges ON nodes.w = edges.next UNION ALL SELECT first, e.next, n + 1 FROM walk JOIN edges e ON e.prev = walk.w),
runs AS (SELECT first, max(n) + {K - 1} AS n_bases FROM walk GROUP BY first) SELECT count(*) AS n, max(n_bases)::BIGINT AS longest, sum(n_bases)::BIGINT AS total FROM runs""")

register("growing_subsets", f"{SUBSETS} SELECT subset, n_words, n_distinct, n_distinct * 16 AS exact_bytes, " + ", ".join(f"ceil(n_distinct * {_per_word(f)!r}::DOUBLE)::BIGINT AS sketch_bytes_{int(100 * f):02d}" for f in W.RATES) + " FROM subsets")
register("scaling_slope", f"{SUBSETS} SELECT round(regr_slope(n_distinct, n_words), 9) AS slope, round(regr_r2(n_distinct, n_words), 9) AS r2 FROM subsets")

EXACT = ("exact_hash", "exact_hash_spill", "exact_suffix", "disk_partition", "disk_bins_sort", "disk_bins_minimizer", "frequent_containers")


@query(f"{SUBSETS} SELECT subset, unnest(['{chr(39).join(())}" + "','".join(EXACT) + "']) AS counter, n_distinct, n_words FROM subsets")
def counters_on_subsets(spark, d):
    """Every exact counter over five growing subsets: the same words and counts from all."""
    return W.counters_on_subsets(spark, d, EXACT, disk=False).select("subset", "counter", "n_distinct", "n_words")


@query()
def counter_costs_on_subsets(spark, d):
    """All counters, and the sketch at 1, 5 and 20 percent, over five growing subsets: seconds, bytes held, bytes on disk."""
    return W.counters_on_subsets(spark, d)


def _retrieval(i: int) -> str:
    primes = SketchSpec.for_memory(16 << 20, k=K).primes
    cells = ", ".join(f"t{j}_{i} AS (SELECT kmer % {p} AS cell, least(sum(cnt), 255)::BIGINT AS cnt FROM c{i} GROUP BY 1)" for j, p in enumerate(primes))
    joins = " ".join(f"LEFT JOIN t{j}_{i} ON t{j}_{i}.cell = q.kmer % {p}" for j, p in enumerate(primes))
    est = f"least({', '.join(f'coalesce(t{j}_{i}.cnt, 0)' for j in range(len(primes)))})"
    return f"""reads{i} AS (SELECT * FROM reads WHERE {FIFTH} < {i}), {occ_sql(reads=f'reads{i}', name=f'occ{i}')}, c{i} AS MATERIALIZED (SELECT {code_sql('w')} AS kmer, count(*) AS cnt FROM occ{i} GROUP BY w), {cells},
r{i} AS (SELECT {i} AS subset, count(*) AS n_queries, count_if(est > 0)::BIGINT AS n_found, sum(est)::BIGINT AS total FROM (SELECT q.kmer, {est} AS est FROM q {joins})),
x{i} AS (SELECT {i} AS subset, count(*) AS n_queries, count(c.kmer) AS n_found, coalesce(sum(c.cnt), 0)::BIGINT AS total FROM q LEFT JOIN c{i} c USING (kmer))"""


_ASKED = f"WITH {reads_sql()},\n{BENCH_WORDS},\n" + ",\n".join(map(_retrieval, range(1, 6)))
register("retrieval_sets", _ASKED + " " + " UNION ALL ".join(f"SELECT * FROM r{i}" for i in range(1, 6)))


@query(_ASKED + " " + " UNION ALL ".join(f"SELECT 'prime_sketch' AS structure, * FROM r{i} UNION ALL SELECT unnest(['exact_hash', 'sorted_index']), * FROM x{i}" for i in range(1, 6)))
def retrieval_by_structure(spark, d):
    """The same random look-ups in sketches, hash tables and sorted indexes of five growing subsets."""
    return W.retrieval_costs(spark, d).drop("load_seconds", "query_seconds")


@query()
def retrieval_costs(spark, d):
    """The same with the seconds to load each structure and to ask it."""
    return W.retrieval_costs(spark, d)


@query()
def disk_on_subsets(spark, d):
    """Bytes on disk of every structure over the five growing subsets."""
    return growing.disk_on_layers(W.fifths(spark, d), K, 0.01)


@query(f"{BASE},\n{BENCH_WORDS} SELECT q.kmer, coalesce(c.cnt, 0)::BIGINT AS est FROM q LEFT JOIN counts c USING (kmer)")
def sorted_index_lookup(spark, d):
    """Look-ups by range search in a kept sorted index."""
    path = shared_path(spark)
    SortedIndex.save(words(spark, d), path)
    return SortedIndex(spark, path).lookup(passages(spark, d))


register("neighbors", f"""{BASE},\n{BENCH_WORDS}, r AS (SELECT {code_sql("substring(w, 2) || b")} AS x, {code_sql(RC.format("(substring(w, 2) || b)"))} AS y, 'right' AS side FROM (SELECT DISTINCT w FROM bench_occ), (VALUES ('A'), ('C'), ('G'), ('T')) v(b)
 UNION ALL SELECT {code_sql("b || substring(w, 1, 21)")}, {code_sql(RC.format("(b || substring(w, 1, 21))"))}, 'left' FROM (SELECT DISTINCT w FROM bench_occ), (VALUES ('A'), ('C'), ('G'), ('T')) v(b)),
fan AS (SELECT least(x, y) AS kmer, side FROM r), {sized_sql(0.01)},\n{sized_est_sql('fan')} SELECT side, count(*) AS n, sum(est)::BIGINT AS total FROM est WHERE est > 0 GROUP BY side""")


TURN_BATCHES = f"WITH t AS (SELECT conv_id * 100 + turn AS tid, role, text, turn FROM conversations), {reads_sql('t', 'tid', 'text', 'role')},\n{occ_sql()},\nnumbered AS MATERIALIZED (SELECT read_id // 10000 % 3 AS batch, {code_sql('w')} AS kmer FROM occ)"


def _online(b: int) -> str:
    primes = prime_table_sizes(SIZES["f10"], 4)
    cells = ", ".join(f"t{i}_{b} AS (SELECT kmer % {p} AS cell, least(count(*), 255) AS cnt FROM numbered WHERE batch <= {b} GROUP BY 1)" for i, p in enumerate(primes))
    joins = " ".join(f"JOIN t{i}_{b} ON t{i}_{b}.cell = q.kmer % {p}" for i, p in enumerate(primes))
    return f"{cells}, a{b} AS (SELECT {b} AS batch, q.kmer, least({', '.join(f't{i}_{b}.cnt' for i in range(4))}) AS est FROM (SELECT DISTINCT kmer FROM numbered WHERE batch = {b}) q {joins})"


@query(TURN_BATCHES + ",\n" + ",\n".join(map(_online, range(3))) + " " + " UNION ALL ".join(f"SELECT * FROM a{b}" for b in range(3)))
def online_updates(spark, d):
    """Turns counted in three batches on one handle; after each, the counts so far of the batch's words."""
    reads = R.from_conversations(W.table(spark, d, "conversations"))
    occ = stored(explode_kmers(reads, K).select(F.pmod(R.text_of(F.col("read_id")), F.lit(3)).cast("int").alias("batch"), "kmer"))
    handle, out = OnlineCounter(spark, spec()), None
    for b in range(3):
        row = handle.update_and_get(occ.filter(F.col("batch") == b).select("kmer"), stored).select(F.lit(b).alias("batch"), "kmer", "est")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"{SKETCHED} SELECT kmer, est FROM est WHERE cnt >= 10")
def saved_and_loaded(spark, d):
    """A sketch that was saved, loaded and checked answers as before."""
    path = shared_path(spark)
    PrimeSketch.build(docs(spark, d), spec()).save(path, "gzip")
    sketch = PrimeSketch.load(spark, path)
    assert sketch.assess(1.0)["valid"]
    return lookup(words(spark, d).filter("cnt >= 10").select("kmer"), sketch)

