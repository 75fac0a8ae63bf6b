"""A corpus pipeline in five stages; each stage's table is written and read again as the next one's documents."""

from __future__ import annotations

import functools
from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kmerspark.llm._state import broadcast_if_small, stored
from kmerspark.llm.line_dedup import line_dedup
from kmerspark.llm.mixing import mix_sources, word_count
from kmerspark.llm.ngram_join import ngram_components
from kmerspark.llm.packing import harmonic_packing
from kmerspark.llm.toxicity import THRESHOLD, fit, score_documents

#: No SQL can state the scores of the first stage, or the packing; tests hold each stage against its own brute force.
ORACLE_SQL = None


COLUMNS = {"doc_id", "text", "lang", "source", "n_chars"}
Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def keeps_columns(stage: Stage) -> Stage:
    """Columns that documents have besides COLUMNS go through a stage under names that nothing in it uses."""

    @functools.wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        away = {c: f"_kept_{i}" if c not in COLUMNS else c for i, c in enumerate(docs.columns)}
        return stage(spark, docs.toDF(*away.values()), sf_dir).toDF(*docs.columns)

    return run


@keeps_columns
def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the models find toxic go."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    learnt = labels.filter(F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) != 2, F.lit(True)))
    return score_documents(docs, fit(docs, learnt)).filter(F.col("score") < THRESHOLD).select(*docs.columns)


@keeps_columns
def line_deduplication(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that several documents share stay in one of them."""
    out = line_dedup(docs).withColumn("text", F.col("kept_text")).withColumn("n_chars", F.length("kept_text").cast("long"))
    return out.select(*docs.columns)


@keeps_columns
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id stays. Rows without an id all stay."""
    groups = stored(ngram_components(docs).filter("doc_id IS NOT NULL AND doc_id <> component_id").select("doc_id").distinct())
    kept = docs.join(broadcast_if_small(groups), "doc_id", "left_anti").select(*docs.columns)
    again = stored(docs.filter("doc_id IS NOT NULL").groupBy("doc_id").count().filter("count > 1").select("doc_id"))
    if again.isEmpty():
        return kept
    return kept.join(again, "doc_id", "left_anti").select(*docs.columns).unionByName(kept.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(*docs.columns))


@keeps_columns
def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; those it leaves out, and those without words, go."""
    times = mix_sources(docs).filter("taken > 0").select("doc_id", F.col("source").alias("_source"), F.col("size").alias("_size"), F.expr("taken div size").alias("_times"))
    unnamed = docs.filter("doc_id IS NULL")
    some = not unnamed.isEmpty()
    if some:
        times = stored(times)
    ranked = times.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("_times").alias("_times"))
    taken = docs.join(ranked, "doc_id").select(*docs.columns, "_times")
    if some:  # rows without an id that have one source and one size can stand for each other
        nth = lambda by, order: F.row_number().over(Window.partitionBy(*by).orderBy(*order))
        own = times.filter("doc_id IS NULL").withColumn("_nth", nth(("_source", "_size"), (F.desc("_times"),)))
        rows = unnamed.withColumn("_words", word_count(F.col("text"))).withColumn("_i", nth(("source", "_words"), ("text",)))
        met = rows.join(own.drop("doc_id"), F.col("source").eqNullSafe(F.col("_source")) & (F.col("_words") == F.col("_size")) & (F.col("_i") == F.col("_nth")))
        taken = taken.unionByName(met.select(*docs.columns, "_times"))
    return taken.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_times")))).select(*(taken[c] for c in docs.columns))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 ids: a row per piece."""
    return harmonic_packing(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", toxicity),
    ("line_dedup", line_deduplication),
    ("ngram_jaccard_join", near_duplicates),
    ("mixing", source_mix),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
