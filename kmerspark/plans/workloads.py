"""The experiments, over the given tables: each returns the rows of its figure or table."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.counters import COUNTERS
from ..baselines.trimmers import qtrim_error_sum, qtrim_tail
from ..operators import accuracy as acc
from ..operators.graph import assembly_proxy, n50, unitigs
from ..operators.kmers import exact_counts, explode_kmers
from ..operators.lookup import lookup
from ..operators.normalize import normalize_batch, normalize_batches, normalize_sequential
from ..operators.packed import PackedWords, tables_of
from ..operators.sketch import PrimeSketch, SketchSpec, cells_of
from ..operators.store import discard, passing, shared_path, stored
from ..operators.trim import error_profile, trim_iterative, trim_reads
from ..sources.reads import from_conversations, from_documents, from_pages, genome_of, text_of, with_arrival
from ..sources.simulate import genome_string, random_kmers, simulate_reads
from .sizing import size_for_fpr

K = 22
RATES = (0.01, 0.05, 0.2)
SWEEP = (0.01, 0.05, 0.1, 0.2, 0.5, 0.8, 0.9)
#: Bases of the documents that stand for a long genome, at most.
GENOME_BASES = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of a table for each core, below which its rows are dealt to all cores before anything is made of them.
DEAL_BYTES = 64 << 20


def spread(df: DataFrame, by: str) -> DataFrame:
    """A small table in a file or two would keep one core busy; it is dealt out. A large one is read where it lies."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores, by) if size < DEAL_BYTES * cores else df


def document_reads(spark: SparkSession, sf_dir: str, **kw) -> DataFrame:
    return from_documents(spread(table(spark, sf_dir, "documents").select("doc_id", "text", "source"), "doc_id"), **kw)


def small_genome(spark: SparkSession, sf_dir: str) -> str:
    return genome_string(genome_of(table(spark, sf_dir, "benchmark")))


def deep_reads(spark: SparkSession, sf_dir: str, coverage: int = 50) -> DataFrame:
    """Reads of high coverage with errors that rise to the 3' end."""
    return stored(simulate_reads(spark, small_genome(spark, sf_dir), coverage, 0.01, "rising"))


def subsets(spark: SparkSession, sf_dir: str) -> Iterator[tuple[int, DataFrame]]:
    """The reads of one to five fifths of the documents."""
    rows = spread(table(spark, sf_dir, "documents").select("doc_id", "text", "source"), "doc_id")
    for i in range(1, 6):
        yield i, from_documents(rows.filter(F.pmod(F.col("doc_id"), F.lit(5)) < i))


def fifths(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    """The reads of each fifth of the documents: what each of the growing subsets has more than the one before."""
    rows = spread(table(spark, sf_dir, "documents").select("doc_id", "text", "source"), "doc_id")
    return [from_documents(rows.filter(F.pmod(F.col("doc_id"), F.lit(5)) == i)) for i in range(5)]


def growing_subsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of five growing subsets, and the bytes of an exact table and of sketches at three error rates."""
    out = None
    for i, own in subsets(spark, sf_dir):
        found = exact_counts(own, K).agg(F.count("*").alias("n_distinct"), F.sum("cnt").alias("n_words")).select(F.lit(i).alias("subset"), "n_words", "n_distinct", (F.col("n_distinct") * 16).alias("exact_bytes"))
        for f in RATES:
            found = found.withColumn(f"sketch_bytes_{int(100 * f):02d}", F.ceil(F.col("n_distinct") * size_for_fpr(1, f).memory))
        out = found if out is None else out.unionByName(found)
    return out


def counters_on_subsets(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = (), disk: bool = True) -> DataFrame:
    """subset, counter, n_distinct, n_words, seconds, bytes_held, bytes_on_disk of counters over growing subsets.

    Seconds are from reads at rest to the structure and its counts. A structure holds its counters (sketch), 16
    bytes a word (tables) or 8 bytes an occurrence (suffixes); on disk it is what it writes by itself, and without
    `disk` nothing is written. By default all counters, and sketches for three error rates, whose words are those of
    their histogram. A sketch's tables are made and asked by parts, whatever their size: none comes to the driver.
    """
    from .costs import bytes_of, timed

    rows = []
    for i, own in subsets(spark, sf_dir):
        reads = stored(own.select("read_id", "seq"))
        for name in names or [n for n in COUNTERS if n != "prime_sketch"]:

            def count(path, name=name, reads=reads):
                counts = COUNTERS[name](K).build(reads).counts
                if disk:
                    counts.write.parquet(path)
                    counts = spark.read.schema(counts.schema).parquet(path)
                return counts.agg(F.count("*"), F.coalesce(F.sum("cnt"), F.lit(0))).first()

            with passing(spark):
                path = shared_path(spark)
                seconds, (n, total) = timed(lambda path=path: count(path))
                rows.append((i, name, n, total, seconds, 8 * total if name == "exact_suffix" else 16 * n, bytes_of(spark, path) if disk else None))
        for f in () if names else RATES:

            def sketch(path, f=f, reads=reads):
                spec = SketchSpec.for_reads(reads, f, k=K)
                words = PackedWords(reads, K)
                found = words.answered(spec, tables_too=True)
                dense = tables_of(found)
                PrimeSketch(spec, cells_of(dense, spec), dense=dense).save(path, "gzip")
                return spec.memory_bytes(), words.histogram(spec, found).agg(F.sum("n_kmers"), F.sum(F.col("abundance") * F.col("n_kmers"))).first()

            with passing(spark):
                path = shared_path(spark)
                seconds, (held, (n, total)) = timed(lambda path=path: sketch(path))
                rows.append((i, f"prime_sketch_{int(100 * f):02d}", n, total, seconds, held, bytes_of(spark, path)))
        discard(reads)
    return spark.createDataFrame(rows, "subset int, counter string, n_distinct long, n_words long, seconds double, bytes_held long, bytes_on_disk long")


def five_sets(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Counts of five read sets; the first five with as many distinct words as the smallest has, chosen by a hash of the word."""
    genome = genome_string(document_genome(spark, sf_dir), GENOME_BASES)
    deep = deep_reads(spark, sf_dir)
    sets = {
        "documents": document_reads(spark, sf_dir),
        "simulated_error_3pct": simulate_reads(spark, genome, 3, 0.03),
        "simulated_error_1pct": simulate_reads(spark, genome, 3, 0.01),
        "simulated_no_error": simulate_reads(spark, genome, 3, 0.0),
    }
    counts = {name: stored(exact_counts(reads, K)) for name, reads in sets.items()}
    equal = min(c.count() for c in counts.values())
    counts["random"] = stored(exact_counts(random_kmers(spark, equal + equal // 1000 + 10, K), K))
    alike = {name: stored(c.orderBy(F.xxhash64("kmer"), "kmer").limit(equal)) for name, c in counts.items()}
    return alike | {"deep": stored(exact_counts(deep, K))}


def document_genome(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.dna import project_text

    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("contig_id"), project_text(F.col("text")).alias("seq"))


def miscount_sweep(spark: SparkSession, sf_dir: str, rates: tuple[float, ...] = SWEEP) -> DataFrame:
    """Average miscount, absolute and in percent, of five sets over the error rate."""
    out = None
    for name, counts in five_sets(spark, sf_dir).items():
        n = counts.count()
        for f in rates:
            sketch = PrimeSketch.of_counts(counts, SketchSpec.for_fpr(n, f)).stored(stored)
            row = acc.accuracy(acc.compare(counts, sketch)).select(F.lit(name).alias("set"), F.lit(f).alias("target_fpr"), "*")
            out = row if out is None else out.unionByName(row)
    return out


def profile_by_position(spark: SparkSession, sf_dir: str, f: float = 0.01) -> DataFrame:
    reads = deep_reads(spark, sf_dir)
    counts = stored(exact_counts(reads, K))
    return error_profile(reads, PrimeSketch.of_counts(counts, SketchSpec.for_fpr(counts.count(), f)).stored(stored))


def trimming_rounds(spark: SparkSession, sf_dir: str, rounds: int = 6, f: float = 0.8) -> DataFrame:
    """Six rounds of unique-word trimming with a sketch that errs at 80% in the first."""
    reads = deep_reads(spark, sf_dir)
    n = exact_counts(reads, K).count()
    return trim_iterative(reads, SketchSpec.for_fpr(n, f), stored, rounds)[1]


def trimming_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Erroneous words removed and true words lost by each trimmer, at several stringencies, and by none."""
    reads = deep_reads(spark, sf_dir)
    truth = stored(true_words(spark, sf_dir))
    before = stored(explode_kmers(reads, K).select("kmer").distinct())
    counts = stored(exact_counts(reads, K))
    n = counts.count()
    runs = {"none": reads}
    for f in (0.01, 0.8):
        sketch = PrimeSketch.of_counts(counts, SketchSpec.for_fpr(n, f)).stored(stored)
        runs[f"sketch_f{int(100 * f):02d}"] = trim_reads(reads, sketch)
    runs["sketch_six_rounds"] = trim_iterative(reads, SketchSpec.for_fpr(n, 0.8), stored, 6)[0]
    for limit in (0.05, 0.01, 0.001):
        runs[f"error_sum_{limit}"] = qtrim_error_sum(reads, limit, K)
    for q in (10, 20, 30):
        runs[f"tail_{q}"] = qtrim_tail(reads, q, K)
    out = None
    total = reads.agg(F.sum(F.length("seq")).alias("b")).first()["b"]
    for name, left in runs.items():
        left = stored(left.select("read_id", "seq"))
        bases = left.agg(F.sum(F.length("seq")).alias("b")).first()["b"] or 0
        row = acc.retention(before, explode_kmers(left, K).select("kmer").distinct(), truth).select(F.lit(name).alias("trimmer"), F.lit(round(100 * (1 - bases / total), 4)).alias("bases_removed"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def whole_genome(spark: SparkSession, sf_dir: str) -> DataFrame:
    """contig_id and seq of the benchmark passages end to end: the genome that deep reads come from, held as one string."""
    return spark.createDataFrame([(0, small_genome(spark, sf_dir))], "contig_id long, seq string")


def true_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distinct words of the genome that deep reads come from."""
    return explode_kmers(whole_genome(spark, sf_dir).select(F.col("contig_id").alias("read_id"), "seq"), K).select("kmer").distinct()


def normalization_sweep(spark: SparkSession, sf_dir: str, coverage: int = 20, rates=(1e-4, 0.05, 0.2, 0.5, 0.8, 0.95, 0.999)) -> DataFrame:
    """Reads kept, true and erroneous words kept, completeness and unitigs after normalization, at seven sketch sizes."""
    whole = whole_genome(spark, sf_dir)
    truth = stored(true_words(spark, sf_dir))
    reads = deep_reads(spark, sf_dir).select("read_id", "source", "seq")
    before = stored(explode_kmers(reads, K).select("kmer").distinct())
    n_reads, n = reads.count(), before.count()
    out = None
    for f in rates:
        kept = stored(normalize_sequential(reads, SketchSpec.for_fpr(n, f), coverage))
        pieces = stored(unitigs(kept, K, stored, 3))
        words = acc.retention(before, explode_kmers(kept, K).select("kmer").distinct(), truth).first()
        row = assembly_proxy(kept, whole, K).withColumn("n_kept", F.lit(kept.count())).select(F.lit(f).alias("full_fpr"), "n_kept", F.round(1 - F.col("n_kept") / n_reads, 6).alias("dropped"), "recovered", "chimeric")
        row = row.withColumns({"true_kept": F.lit(words["true_kept"]), "errors_kept": F.lit(words["error_after"]), "n_unitigs": F.lit(pieces.count()), "n50": F.lit(n50(pieces))})
        out = row if out is None else out.unionByName(row)
    return out


def batch_sizes(spark: SparkSession, sf_dir: str, coverage: int = 20, sizes=(4, 16)) -> DataFrame:
    """Reads kept by strict order, by batches, and by the non-streaming baseline."""
    reads = deep_reads(spark, sf_dir).select("read_id", "source", "seq")
    counts = stored(exact_counts(reads, K))
    spec = SketchSpec.for_fpr(counts.count(), 0.01)
    rows = [("none", reads.count()), ("sequential", normalize_sequential(reads, spec, coverage).count())]
    for b in sizes:
        rows.append((f"batches_{b}", normalize_batches(with_arrival(reads, batches=b), spec, stored, coverage, b)[0].count()))
    rows += [(f"baseline_{m}", normalize_batch(reads, counts, K, coverage, m).count()) for m in ("deterministic", "prob")]
    return spark.createDataFrame(rows, "method string, n_kept long")


def large_reduction(spark: SparkSession, sf_dir: str, coverage: int = 20, f: float = 0.1, batches: int = 4) -> DataFrame:
    """Reads and bases of all text tables before and after normalization."""
    docs, pages, turns = document_reads(spark, sf_dir), from_pages(table(spark, sf_dir, "pages")), from_conversations(table(spark, sf_dir, "conversations"))
    reads = docs.withColumn("read_id", F.col("read_id") * 3).unionByName(pages.withColumn("read_id", F.col("read_id") * 3 + 1)).unionByName(turns.withColumn("read_id", F.col("read_id") * 3 + 2))
    reads = with_arrival(stored(reads), batches=batches)
    found = PackedWords(reads, K)
    n = found.sums(lambda code, _: (len(code),), 1)[0]
    found.discard()
    kept, _ = normalize_batches(reads, SketchSpec.for_fpr(n, f), stored, coverage, batches)
    size = lambda df, name: df.agg(F.count("*").alias(f"reads_{name}"), F.sum(F.length("seq")).alias(f"bases_{name}")).withColumn("_j", F.lit(1))
    both = size(reads, "before").join(size(kept, "after"), "_j").drop("_j")
    return both.select("*", F.round(F.col("reads_after") / F.col("reads_before"), 4).alias("reads_ratio"), F.round(F.col("bases_after") / F.col("bases_before"), 4).alias("bases_ratio"))


def retrieval_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A fixed set of words, present and absent, looked up in the sketches of the five growing subsets."""
    queries = stored(explode_kmers(genome_of(table(spark, sf_dir, "benchmark")).select(F.col("contig_id").alias("read_id"), "seq"), K).select("kmer").distinct())
    rows = document_reads(spark, sf_dir).withColumn("fifth", F.pmod(text_of(F.col("read_id")), F.lit(5)))
    spec = SketchSpec.for_memory(16 << 20, k=K)
    out = None
    for i in range(1, 6):
        sketch = PrimeSketch.build(rows.filter(F.col("fifth") < i), spec)
        row = lookup(queries, sketch).agg(F.count("*").alias("n_queries"), F.count_if(F.col("est") > 0).alias("n_found"), F.sum("est").alias("total")).select(F.lit(i).alias("subset"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def retrieval_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same random look-ups in three structures of the five growing subsets, with seconds to load and to ask.

    All three lie on disk: a sketch's blocks, a table of counts that is hashed for the look-up, and a sorted index.
    """
    from ..operators.index import SortedIndex
    from .costs import timed

    queries = stored(explode_kmers(genome_of(table(spark, sf_dir, "benchmark")).select(F.col("contig_id").alias("read_id"), "seq"), K).select("kmer").distinct())
    n, rows = queries.count(), []
    for i, reads in subsets(spark, sf_dir):
        counts, path = stored(exact_counts(reads, K)), shared_path(spark)
        PrimeSketch.of_counts(counts, SketchSpec.for_memory(16 << 20, k=K)).save(f"{path}/sketch")
        counts.write.parquet(f"{path}/hash")
        SortedIndex.save(counts, f"{path}/sorted")

        def load_sketch(path=path):
            sketch = PrimeSketch.load(spark, f"{path}/sketch")
            sketch.arrays()
            return lambda: lookup(queries, sketch)

        def load_hash(path=path):
            known = spark.read.parquet(f"{path}/hash")
            known.count()
            return lambda: queries.join(known.hint("shuffle_hash"), "kmer", "left").select("kmer", F.coalesce("cnt", F.lit(0)).alias("est"))

        def load_sorted(path=path):
            index = SortedIndex(spark, f"{path}/sorted")
            return lambda: index.lookup(queries)

        for name, load in (("prime_sketch", load_sketch), ("exact_hash", load_hash), ("sorted_index", load_sorted)):
            loaded, ask = timed(load)
            asked, (found, total) = timed(lambda ask=ask: ask().agg(F.count_if(F.col("est") > 0), F.sum("est")).first())
            rows.append((name, i, n, found, total, loaded, asked))
    return spark.createDataFrame(rows, "structure string, subset int, n_queries long, n_found long, total long, load_seconds double, query_seconds double")
