"""How well estimates match exact counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lookup import lookup
from .sketch import PrimeSketch


def compare(counts: DataFrame, sketch: PrimeSketch, overflow: bool = False, strategy: str = "auto") -> DataFrame:
    """kmer, truth, est. Without an overflow map the truth ends at the counters' cap."""
    found = lookup(counts.select("kmer", "cnt"), sketch, strategy, overflow)
    truth = F.col("cnt") if overflow else F.least("cnt", F.lit(sketch.spec.cap))
    return found.select("kmer", truth.cast("long").alias("truth"), "est")


def accuracy(compared: DataFrame, *group: str) -> DataFrame:
    """n, fpr (share of wrong counts), miscount, pct (percent of the truth), max, and counts below the truth (none).

    Rates are ratios of whole numbers where they can be, rounded to six decimals.
    """
    d = F.col("est") - F.col("truth")
    n = F.count("*")
    return compared.groupBy(*group).agg(
        n.alias("n"),
        F.round(F.count_if(d != 0) / n, 6).alias("fpr"),
        F.round(F.sum(d) / n, 6).alias("miscount"),
        F.round(100 * F.sum(d / F.col("truth")) / n, 4).alias("pct"),
        F.max(d).alias("max_miscount"),
        F.count_if(d < 0).alias("undercounts"),
    )


def miscount_quantiles(compared: DataFrame, probabilities=(0.5, 0.9, 0.99)) -> DataFrame:
    return compared.agg(*(F.percentile(F.col("est") - F.col("truth"), F.lit(p)).alias(f"q{int(100 * p)}") for p in probabilities))


def absent_fpr(queries: DataFrame, counts: DataFrame, sketch: PrimeSketch) -> DataFrame:
    """Share of keys that were never counted but have a count; none where every key was counted."""
    absent = queries.select("kmer").distinct().join(counts.select("kmer"), "kmer", "left_anti")
    return lookup(absent, sketch).agg(F.count("*").alias("n"), F.round(F.try_divide(F.count_if(F.col("est") > 0), F.count("*")), 6).alias("fpr_absent"))


def histogram_distance(exact: DataFrame, sketched: DataFrame) -> DataFrame:
    """Sum of differences of two histograms over the number of distinct words."""
    e, s = exact.select("abundance", F.col("n_kmers").alias("e")), sketched.select("abundance", F.col("n_kmers").alias("s"))
    both = e.join(s, "abundance", "full").select(F.coalesce("e", F.lit(0)).alias("e"), F.coalesce("s", F.lit(0)).alias("s"))
    return both.agg(F.round(F.sum(F.abs(F.col("e") - F.col("s"))) / F.sum("e"), 6).alias("distance"))


def skew(counts: DataFrame) -> DataFrame:
    """Share of words that occur once, and the moment skewness of the counts."""
    return counts.agg(F.count("*").alias("n"), F.round(F.count_if(F.col("cnt") == 1) / F.count("*"), 6).alias("unique_share"), F.round(F.skewness(F.col("cnt").cast("double")), 3).alias("skewness"))


def retention(before: DataFrame, after: DataFrame, truth: DataFrame) -> DataFrame:
    """Distinct true and erroneous words before and after a step: words of (kmer) tables against the true ones."""
    def split(words: DataFrame, name: str) -> DataFrame:
        own = words.select("kmer").distinct()
        hit = truth.select(F.col("kmer").alias("_t")).distinct()
        flagged = own.join(hit, F.col("kmer") == F.col("_t"), "left")
        return flagged.agg(F.count("_t").alias(f"true_{name}"), (F.count("*") - F.count("_t")).alias(f"error_{name}"))

    both = split(before, "before").withColumn("_j", F.lit(1)).join(split(after, "after").withColumn("_j", F.lit(1)), "_j").drop("_j")
    return both.select("*", F.round(F.col("true_after") / F.col("true_before"), 6).alias("true_kept"), F.round(1 - F.col("error_after") / F.col("error_before"), 6).alias("error_removed"))


def linear_fit(points: DataFrame, x: str, y: str) -> DataFrame:
    """Slope and R squared of a series: 1 for a cost that grows in proportion."""
    return points.agg(F.regr_slope(y, x).alias("slope"), F.regr_r2(y, x).alias("r2"))
