"""Toxicity by class-conditional Kneser-Ney models over the letters of words.

Each class has its own top-order counts; all lower orders are continuation counts of both classes together, so a
rare expression falls back to the same estimate in either class and says nothing. A document's evidence is the
difference of its toxic and ordinary log-likelihoods, divided by the number of words: over the whole text, and over
its most toxic stretches, so that length does not dilute it. A logistic curve, fitted out of fold, maps that
evidence to a score between 0 and 1.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._state import stored
from ._text import Words, column, gram_hashes, mix64, text_blocks

ORDER = 5
DISCOUNT = 0.75
#: Labelled documents of each class that a model learns from at most, chosen by a seeded hash of their ids.
MAX_TRAIN = 6_000
#: Bytes of text of each class that it learns from at most: documents beyond, in the order of that hash, are not taken.
MAX_TRAIN_BYTES = 64 << 20
WINDOWS = (16, 128)
THRESHOLD = 0.3
FOLDS = 2
SEED = 42
_PAD = 1
_END = 2


def _letters(words: pa.Array, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Code points of all words, each after order-1 pads and before an end mark; where n-grams end; whose they are."""
    strings = [w.decode().lower() for w in words.to_pylist()]
    pad = chr(_PAD) * (order - 1)
    flat = np.frombuffer("".join([f"{pad}{s}{chr(_END)}" for s in strings]).encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
    sizes = np.fromiter(map(len, strings), np.int64, len(strings)) + order
    owner = np.repeat(np.arange(len(strings)), sizes)
    place = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    return flat, np.flatnonzero(place >= order - 1), owner


def _grams(flat: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n letters that end at each of `ends`."""
    return gram_hashes(mix64(flat), n)[ends - n + 1] if n else np.zeros(len(ends), np.uint64)


@dataclass
class ToxicModel:
    """Log-likelihood ratios of seen n-grams and of seen contexts, and the logistic curve over the evidence."""

    grams: np.ndarray
    gram_ratio: np.ndarray
    contexts: np.ndarray
    context_ratio: np.ndarray
    order: int = ORDER
    weights: np.ndarray = field(default_factory=lambda: np.zeros(1 + len(WINDOWS)))
    bias: float = 0.0
    centre: np.ndarray = field(default_factory=lambda: np.zeros(1 + len(WINDOWS)))
    scale: np.ndarray = field(default_factory=lambda: np.ones(1 + len(WINDOWS)))

    def word_ratios(self, words: pa.Array) -> np.ndarray:
        """Toxic minus ordinary log-likelihood of each word, its end included."""
        out = np.zeros(len(words))
        for a in range(0, len(words), 50_000):
            part = words.slice(a, 50_000)
            flat, ends, owner = _letters(part, self.order)
            value = _look_up(self.grams, self.gram_ratio, _grams(flat, ends, self.order))
            rest = np.isnan(value)
            value[rest] = _look_up(self.contexts, self.context_ratio, _grams(flat, ends[rest] - 1, self.order - 1))
            out[a : a + len(part)] = np.bincount(owner[ends], weights=np.nan_to_num(value), minlength=len(part))
        return out

    def evidence(self, text: pa.Array) -> np.ndarray:
        """For each text: the mean ratio of its words, and that of the highest run of each length in WINDOWS."""
        words = Words(text)
        ratio = self.word_ratios(words.distinct)[words.codes]
        sums = np.concatenate([[0.0], np.cumsum(ratio)])
        ends = words.ends()
        n = words.counts
        out = np.zeros((len(n), 1 + len(WINDOWS)))
        some = n > 0
        out[some, 0] = (sums[ends] - sums[ends - n])[some] / n[some]
        for k, w in enumerate(WINDOWS, 1):
            out[:, k] = out[:, 0]
            long = np.flatnonzero(n >= w)
            if len(long):
                runs = (sums[w:] - sums[:-w]) / w
                begins = np.stack([(ends - n)[long], ends[long] - w + 1], axis=1).ravel()
                out[long, k] = np.maximum.reduceat(np.append(runs, -np.inf), begins)[::2]
        return out

    def scores(self, text: pa.Array) -> np.ndarray:
        z = (self.evidence(text) - self.centre) / self.scale @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -500, 500)))


def _look_up(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    out = np.full(len(wanted), np.nan)
    if len(keys):
        at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
        hit = keys[at] == wanted
        out[hit] = values[at[hit]]
    return out


def _group(keys: np.ndarray, *sums: np.ndarray) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Distinct keys, the sums of each array by key, and each row's place among the keys."""
    distinct, at = np.unique(keys, return_inverse=True)
    return distinct, [np.bincount(at, weights=s, minlength=len(distinct)) for s in sums], at


def kneser_ney_ratios(grams: np.ndarray, toxic: np.ndarray, ordinary: np.ndarray, discount: float = DISCOUNT) -> ToxicModel:
    """The model of n-grams, given as rows of n letters, with their counts in the two classes."""
    order = grams.shape[1]
    hashed = [_rows(grams[:, order - n :]) for n in range(order + 1)]  # of the last n letters
    # Shared estimate of the last letter, order by order: distinct left neighbours in either class.
    letters = np.unique(grams[:, -1])
    shared = np.full(len(grams), 1.0 / max(1, len(letters)))
    for n in range(1, order):
        first = np.unique(hashed[n + 1], return_index=True)[1]
        own, (cont,), _ = _group(hashed[n][first], np.ones(len(first)))
        count = cont[np.searchsorted(own, hashed[n])]
        ctx = _rows(grams[:, order - n : -1])
        at = np.unique(hashed[n], return_index=True)[1]
        c_keys, (total, kinds), _ = _group(ctx[at], cont, np.ones(len(at)))
        c = np.searchsorted(c_keys, ctx)
        shared = (count - discount).clip(0) / total[c] + discount * kinds[c] / total[c] * shared
    ctx = _rows(grams[:, :-1])
    logs, weight = [], []
    for counts in (toxic, ordinary):
        keys, (total, kinds), c = _group(ctx, counts, counts > 0)
        with np.errstate(divide="ignore", invalid="ignore"):
            back = np.where(total > 0, discount * kinds / total, 1.0)
            p = np.where(total[c] > 0, (counts - discount).clip(0) / total[c], 0.0) + back[c] * shared
        logs.append(np.log(p))
        weight.append(np.log(back))
    order_g, order_c = np.argsort(hashed[order]), np.argsort(keys)
    return ToxicModel(hashed[order][order_g], (logs[0] - logs[1])[order_g], keys[order_c], (weight[0] - weight[1])[order_c], order)


def _rows(letters: np.ndarray) -> np.ndarray:
    """The hash that _grams gives to each row of letters."""
    out = np.zeros(len(letters), np.uint64)
    for i in range(letters.shape[1]):
        out = mix64(out + np.uint64(0x9E3779B97F4A7C15)) if i else out
        out += mix64(letters[:, i].astype(np.uint64))
    return mix64(out) if letters.shape[1] else out


def fit(docs: DataFrame, labels: DataFrame, text_col: str = "text", id_col: str = "doc_id", label_col: str = "toxic", order: int = ORDER, max_train: int = MAX_TRAIN) -> ToxicModel:
    """Learn from labelled documents: at most `max_train` of each class, the first by a seeded hash of their ids.

    All n-grams of these documents are counted. Labels other than 0 and 1 and null ids are left out; an id with both
    labels counts as toxic. If a class has no document, every score is the share of toxic labels.
    """
    known = labels.select(labels[id_col].cast("long").alias("id"), labels[label_col].cast("int").alias("y")).filter("id IS NOT NULL AND y IN (0, 1)").groupBy("id").agg(F.max("y").alias("y"))
    known = stored(known)
    shares = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    picked = None
    for y in (0, 1):
        part = known.filter(F.col("y") == y).orderBy(F.xxhash64(F.lit(SEED), "id"), "id").limit(max_train)
        picked = part if picked is None else picked.unionByName(part)
    picked = stored(picked)  # at most 2 * max_train rows of two numbers: small enough to broadcast
    texts = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].cast("string").alias("text"))
    train = texts.join(F.broadcast(picked), "id").withColumn("fold", F.pmod(F.xxhash64(F.lit(SEED + 1), "id"), F.lit(FOLDS)).cast("int"))
    train = stored(train.repartition(24))
    sizes = train.groupBy("id", "y").agg(F.sum(F.octet_length("text")).alias("n")).select("id", "y", "n", F.xxhash64(F.lit(SEED), "id").alias("h")).toPandas()  # 2 * max_train rows of four numbers
    sizes = sizes.sort_values(["y", "h", "id"])
    beyond = sizes[sizes.groupby("y").n.cumsum() - sizes.n >= MAX_TRAIN_BYTES]
    if len(beyond):
        train = train.filter(~F.col("id").isin(beyond.id.tolist()))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in text_blocks(batch, "text"):
                group = np.asarray(column(block, "y")) * FOLDS + np.asarray(column(block, "fold"))
                words = Words(column(block, "text"))
                of_word = np.repeat(group, words.counts)
                flat, ends, owner = _letters(words.distinct, order)
                uses = np.stack([np.bincount(words.codes[of_word == g], minlength=len(words.distinct)) for g in range(2 * FOLDS)], axis=1)[owner[ends]]
                hashed = _grams(flat, ends, order)
                _, first, at = np.unique(hashed, return_index=True, return_inverse=True)
                sums = [np.bincount(at, weights=uses[:, g], minlength=len(first)) for g in range(2 * FOLDS)]
                gram = np.stack([flat[ends[first] - order + 1 + i] for i in range(order)], axis=1).astype("<u4")
                raw = pa.FixedSizeBinaryArray.from_buffers(pa.binary(4 * order), len(first), [None, pa.py_buffer(np.ascontiguousarray(gram))]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([raw, *(pa.array(s.astype(np.int64)) for s in sums)], names=["gram", *(f"c{g}" for g in range(2 * FOLDS))])

    fields = [f"c{g}" for g in range(2 * FOLDS)]
    counts = train.mapInArrow(count, "gram binary, " + ", ".join(f"{c} long" for c in fields)).groupBy("gram").agg(*(F.sum(c).alias(c) for c in fields))
    rows = counts.toArrow()  # of MAX_TRAIN_BYTES of text a class
    grams = np.frombuffer(b"".join(rows["gram"].to_pylist()), dtype="<u4").reshape(-1, order)
    c = np.stack([rows[x].to_numpy() for x in fields], axis=1).astype(float) if rows.num_rows else np.zeros((0, 2 * FOLDS))

    prior = shares.get(1, 0) / max(1, sum(shares.values()))
    if not shares.get(0) or not shares.get(1) or not len(grams):
        empty = np.zeros(0)
        return ToxicModel(empty.astype(np.uint64), empty, empty.astype(np.uint64), empty, order, bias=float(np.log((prior + 1e-3) / (1 - prior + 1e-3))))

    # Out of fold: each fold's documents are judged by the counts of the others.
    folds = []
    for f in range(FOLDS):
        others = [g for g in range(FOLDS) if g != f]
        t, o = c[:, [FOLDS + g for g in others]].sum(axis=1), c[:, others].sum(axis=1)
        folds.append(kneser_ney_ratios(grams[t + o > 0], t[t + o > 0], o[t + o > 0]))
    models = docs.sparkSession.sparkContext.broadcast(folds)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in text_blocks(batch, "text"):
                fold = np.asarray(column(block, "fold"))
                found = np.choose(fold[:, None], [m.evidence(column(block, "text")) for m in models.value])
                yield pa.RecordBatch.from_arrays([column(block, "y"), *(pa.array(found[:, k]) for k in range(found.shape[1]))], names=["y", *(f"x{k}" for k in range(found.shape[1]))])

    judged = train.mapInArrow(judge, "y int, " + ", ".join(f"x{k} double" for k in range(1 + len(WINDOWS)))).toArrow()  # a row of four numbers per training document
    models.unpersist()
    x = np.stack([judged[f"x{k}"].to_numpy() for k in range(1 + len(WINDOWS))], axis=1)
    y = judged["y"].to_numpy().astype(float)
    model = kneser_ney_ratios(grams, c[:, FOLDS:].sum(axis=1), c[:, :FOLDS].sum(axis=1))
    importance = np.where(y == 1, shares[1] / max(1, (y == 1).sum()), shares[0] / max(1, (y == 0).sum()))
    model.centre, model.scale = x.mean(axis=0), x.std(axis=0) + 1e-9
    model.weights, model.bias = _logistic((x - model.centre) / model.scale, y, importance / importance.mean())
    return model


def _logistic(x: np.ndarray, y: np.ndarray, importance: np.ndarray, ridge: float = 1e-3, turns: int = 50) -> tuple[np.ndarray, float]:
    """Weights and bias by Newton's method, with a small ridge."""
    a = np.concatenate([x, np.ones((len(x), 1))], axis=1)
    w, hold = np.zeros(a.shape[1]), np.diag([ridge * len(x)] * x.shape[1] + [1e-9])
    for _ in range(turns):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (importance * p * (1 - p))[:, None]).T @ a + hold, a.T @ (importance * (p - y)) + hold @ w)
        w -= step
        if np.abs(step).max() < 1e-9:
            break
    return w[:-1], float(w[-1])


def score_documents(docs: DataFrame, model: ToxicModel, text_col: str = "text") -> DataFrame:
    """The columns of `docs` with score (0 to 1) added, or replaced. Null and empty texts get a score like any other.

    An empty table gives an empty result; repeated rows get equal scores.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # the n-grams of MAX_TRAIN_BYTES of text a class
    slim = docs.drop("score")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in text_blocks(batch, text_col):
                found = shared.value.scores(column(block, text_col))
                yield pa.RecordBatch.from_arrays([*block.columns, pa.array(found)], names=[*block.schema.names, "score"])

    return slim.mapInArrow(run, T.StructType([*slim.schema.fields, T.StructField("score", T.DoubleType())]))
