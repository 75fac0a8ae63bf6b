"""Mixing sources to target weights by subset-sum budget fitting.

Each source's documents are first taken whole as often as its target allows. For the rest of the budget, documents
are counted by exact length; a proportional share of each length is taken, and a bounded-knapsack programme over
bit sets closes what is left. Which documents of a length are taken is decided by a seeded hash. Only counts travel
to the planning step; the documents themselves are never gathered.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._state import stored

MAX_REPEATS = 3
SEED = 42
#: Budget that the knapsack programme closes at most, in words; what is above is taken greedily.
KNAPSACK_WORDS = 200_000
#: Parts of the hash range; only the part in which a length's quota ends is ranked.
PARTS_BITS = 8


def fit_budget(sizes: np.ndarray, counts: np.ndarray, budget: int, seed: int = SEED, knapsack: int = KNAPSACK_WORDS) -> np.ndarray:
    """How many documents of each size to take, so that their sizes add up to at most `budget`, as near as can be."""
    sizes, counts = np.asarray(sizes, np.int64), np.asarray(counts, np.int64)
    total = int((sizes * counts).sum())
    if budget >= total:
        return counts.copy()
    take = np.array([int(c) * int(budget) // max(total, 1) for c in counts], np.int64)
    left = int(budget) - int((sizes * take).sum())
    order = np.random.default_rng(seed).permutation(len(sizes))
    for i in order.tolist():  # one more of a size, until the programme can close the rest
        s = int(sizes[i])
        if left <= knapsack:
            break
        n = min(int(counts[i] - take[i]), 1, (left - knapsack) // s if s else 0)
        take[i] += n
        left -= n * s
    for i in order.tolist():
        s = int(sizes[i])
        if left > knapsack and s:
            n = min(int(counts[i] - take[i]), (left - knapsack) // s)
            take[i] += n
            left -= n * s
    reach, steps = 1, []
    mask = (1 << (left + 1)) - 1
    for i in order.tolist():
        s, spare = int(sizes[i]), int(counts[i] - take[i])
        if not s or s > left or not spare:
            continue
        n = 1
        while spare > 0 and n * s <= left and not reach >> left & 1:
            n = min(n, spare)
            steps.append((i, n, reach))
            reach = (reach | reach << n * s) & mask
            spare -= n
            n *= 2
        if reach >> left & 1:
            break
    at = reach.bit_length() - 1
    for i, n, before in reversed(steps):
        if not before >> at & 1:
            take[i] += n
            at -= n * int(sizes[i])
    return take


def word_count(text):
    """Number of `[^\\x20\\x09-\\x0D]+` in a text; 0 for null."""
    spaced = F.trim(F.translate(F.coalesce(text.cast("string"), F.lit("")), "\t\n\x0b\x0c\r", "     "))
    return F.when(spaced == "", 0).otherwise(F.size(F.split(spaced, " +"))).cast("long")


def source_targets(sizes: DataFrame, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """source, source_size and target of each row of `sizes` (source, source_size): one row per source.

    Weights 1, 2, 3 repeat over the sources by code point, null last. The targets share the sum of all sizes by
    weight; one that would pass max_repeats times its source's size stops there, and the excess is shared by weight
    among the others until none is above.
    """
    ranked = sizes.withColumn("_n", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))  # a row per source
    ranked = ranked.select("source", "source_size", ((F.col("_n") - 1) % 3 + 1).cast("double").alias("weight"))
    cap = max_repeats * F.col("source_size").cast("double")
    total = ranked.agg(F.sum("source_size")).first()[0] or 0
    level, capped = 0.0, -1
    while True:  # each turn stops at least one more source, so there are few
        held = F.col("weight") * level >= cap if capped >= 0 else F.lit(False)
        r = ranked.agg(F.count_if(held).alias("n"), F.sum(F.when(held, cap)).alias("fixed"), F.sum(F.when(~held, F.col("weight"))).alias("open")).first()
        if r["n"] == capped or not r["open"]:
            level = level if r["open"] else float("inf")
            break
        capped, level = r["n"], (total - (r["fixed"] or 0.0)) / r["open"]
    share = F.when(F.col("weight") * level >= cap, cap).otherwise(F.col("weight") * level) if level != float("inf") else cap
    return ranked.select("source", "source_size", share.alias("target"))


def mix_sources(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", seed: int = SEED, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken (words, repeats counted).

    A document is taken a whole number of times, at most `max_repeats`. Null and empty texts have size 0 and nothing
    is taken of them; null sources are one source, the last. Repeated rows are documents of their own; which of them
    is taken makes no difference. A null id is taken like any other. An empty table gives an empty result.
    """
    base = docs.select(docs[id_col].alias("doc_id"), docs[source_col].cast("string").alias("source"), word_count(docs[text_col]).alias("size"))
    base = stored(base.withColumn("_h", F.xxhash64(F.lit(seed), "doc_id")).withColumn("_part", F.shiftrightunsigned("_h", 64 - PARTS_BITS)))
    targets = stored(source_targets(base.groupBy("source").agg(F.sum("size").alias("source_size")), max_repeats))
    plan = targets.withColumn("_times", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")).withColumn("_rest", (F.round("target") - F.col("_times") * F.col("source_size")).cast("long"))

    by_part = stored(base.filter("size > 0").groupBy("source", "size", "_part").agg(F.count("*").alias("_n")))
    by_size = by_part.groupBy("source", "size").agg(F.sum("_n").alias("n"))
    lists = by_size.groupBy("source").agg(F.sort_array(F.collect_list(F.struct("size", "n"))).alias("sizes"))
    budgets = lists.join(plan.select(F.col("source").alias("_s"), "_rest"), F.col("source").eqNullSafe(F.col("_s"))).filter("_rest > 0").select("source", "_rest", F.col("sizes.size").alias("sizes"), F.col("sizes.n").alias("counts"))

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for source, rest, sizes, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                take = fit_budget(np.array(sizes), np.array(counts), rest, seed)
                at = np.flatnonzero(take)
                yield pa.RecordBatch.from_arrays([pa.array([source] * len(at), pa.string()), pa.array(np.array(sizes, np.int64)[at]), pa.array(take[at])], names=["source", "size", "quota"])

    quotas = budgets.mapInArrow(fit, "source string, size long, quota long").select(F.col("source").alias("_qs"), F.col("size").alias("_qz"), "quota")
    before = F.sum("_n").over(Window.partitionBy("source", "size").orderBy("_part")) - F.col("_n")
    parts = by_part.withColumn("_before", before).join(quotas, F.col("source").eqNullSafe(F.col("_qs")) & (F.col("size") == F.col("_qz")))
    parts = parts.withColumn("_take", F.least("_n", F.col("quota") - F.col("_before"))).filter("_take > 0").select(F.col("source").alias("_qs"), F.col("size").alias("_qz"), F.col("_part").alias("_qp"), "_take", "_n")
    chosen = base.join(parts, base["source"].eqNullSafe(F.col("_qs")) & (F.col("size") == F.col("_qz")) & (F.col("_part") == F.col("_qp")), "left")
    rank = F.row_number().over(Window.partitionBy("source", "size", "_part").orderBy("_h", "doc_id"))
    chosen = chosen.withColumn("_more", F.when(F.coalesce("_take", F.lit(0)) == 0, 0).when(F.col("_take") == F.col("_n"), 1).when(rank <= F.col("_take"), 1).otherwise(0))
    t = plan.select(F.col("source").alias("_ts"), "source_size", "target", "_times")
    return chosen.join(t, F.col("source").eqNullSafe(F.col("_ts"))).select("doc_id", "source", "size", "source_size", "target", (F.col("size") * (F.col("_times") + F.col("_more"))).alias("taken"))
