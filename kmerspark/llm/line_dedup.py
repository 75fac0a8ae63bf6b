"""Line deduplication by sharded cuckoo filters over exact reference-count tables.

The exact table holds, for each line key, in how many documents it stands and the largest of their ids. It is kept in
shards of the key space that grow in number with the input; a block of documents sends each of its distinct keys once
to the shard. There, keys over the threshold go into a cuckoo filter; what a block has sent is tested against the
filter, and the exact table decides on what passes. The block learns which of its lines go. No filter leaves its
shard, so none has to be small enough to be sent about. The filters support deletion: `ReversibleLineIndex` keeps
them and the counts up to date as documents come and go, and reads counts only where a filter knows the key.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import Blocks, read_payload
from ._state import stored
from ._text import column

MIN_CODE_POINTS = 20
MIN_DOCS = 3
LEAST = -(2**63)
CELL_BITS = 16


class CuckooFilter:
    """Set of 128-bit keys by 16-bit fingerprints in buckets of four; insertions, deletions and vectorised lookups."""

    SLOTS = 4

    def __init__(self, capacity: int, table: np.ndarray | None = None):
        size = 1 << max(1, int(np.ceil(np.log2(max(1, capacity) / (self.SLOTS * 0.85)))))
        self.table = np.zeros((size, self.SLOTS), np.uint16) if table is None else table

    def _places(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        mask = np.uint64(len(self.table) - 1)
        mark = (keys[:, 1] & np.uint64(0xFFFF)).astype(np.uint16)
        mark[mark == 0] = 1
        first = keys[:, 0] & mask
        return mark, first, self._other(first, mark)

    def _other(self, place, mark):
        step = (np.asarray(mark, np.uint64) * np.uint64(0x5BD1E9955BD1E995)) >> np.uint64(20)
        return (place ^ step) & np.uint64(len(self.table) - 1)

    def insert(self, keys: np.ndarray) -> np.ndarray:
        """Insert each key once more; the filter doubles as often as it must, from `keys` kept by the caller."""
        mark, one, two = self._places(keys)
        done = np.ones(len(keys), bool)
        for i, (m, a, b) in enumerate(zip(mark.tolist(), one.tolist(), two.tolist(), strict=True)):
            done[i] = self._put(m, a, b)
        return done

    def _put(self, mark: int, a: int, b: int) -> bool:
        trail = []
        for place in (a, b):
            free = np.flatnonzero(self.table[place] == 0)
            if len(free):
                self.table[place, free[0]] = mark
                return True
        place = b
        for turn in range(500):
            slot = (mark + turn) % self.SLOTS
            trail.append((place, slot, mark))
            mark, self.table[place, slot] = int(self.table[place, slot]), mark
            place = int(self._other(np.uint64(place), mark))
            free = np.flatnonzero(self.table[place] == 0)
            if len(free):
                self.table[place, free[0]] = mark
                return True
        for place, slot, put in reversed(trail):  # undo, so a refused key loses nobody else's
            mark, self.table[place, slot] = int(self.table[place, slot]), mark
            assert mark == put
        return False

    def delete(self, keys: np.ndarray) -> None:
        """Delete keys that were inserted."""
        mark, one, two = self._places(keys)
        for m, *places in zip(mark.tolist(), one.tolist(), two.tolist(), strict=True):
            for place in places:
                at = np.flatnonzero(self.table[place] == m)
                if len(at):
                    self.table[place, at[0]] = 0
                    break

    def contains(self, keys: np.ndarray) -> np.ndarray:
        mark, one, two = self._places(keys)
        m = mark[:, None]
        return (self.table[one] == m).any(axis=1) | (self.table[two] == m).any(axis=1)

    @classmethod
    def of(cls, keys: np.ndarray) -> CuckooFilter:
        """A filter that holds all of the keys."""
        capacity = len(keys)
        while not (out := cls(capacity)).insert(keys).all():
            capacity = 2 * len(out.table) * cls.SLOTS
        return out

    def to_bytes(self) -> bytes:
        return self.table.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> CuckooFilter:
        return cls(0, np.frombuffer(raw, np.uint16).reshape(-1, cls.SLOTS).copy())


def key_halves(keys: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(keys), dtype="<u8").reshape(-1, 2)


def cell_of(halves: np.ndarray) -> np.ndarray:
    """One of 2^CELL_BITS equal parts of the key space; shards are runs of cells."""
    return (halves[:, 1] >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def shard_of(halves: np.ndarray, shards: int) -> np.ndarray:
    return cell_of(halves) * shards >> CELL_BITS


def line_keys(lines: list[bytes], min_code_points: int = MIN_CODE_POINTS) -> list[bytes | None]:
    """A 128-bit hash of each line's key; None for keys that are too short to count.

    The key: ASCII white space stripped at both ends, A-Z lower-cased.
    """
    out: list[bytes | None] = []
    for line in lines:
        key = line.strip().lower()
        n = len(key)
        short = n < min_code_points or n < 4 * min_code_points and len(key.decode()) < min_code_points
        out.append(None if short else xxhash.xxh3_128_digest(key))
    return out


def _ids(batch: pa.RecordBatch, name: str) -> list[int]:
    return column(batch, name).cast(pa.int64()).fill_null(LEAST).to_pylist()


def _lines(text: str | None) -> list[bytes]:
    return (text or "").encode().split(b"\n")


def _block_keys(ids: list[int], texts: list[str | None], min_code_points: int) -> dict[bytes, list[int]]:
    """The distinct keys of a block's documents: how many of them hold it, and the largest of their ids."""
    found: dict[bytes, list[int]] = {}
    for doc, text in zip(ids, texts, strict=True):
        for key in set(line_keys(_lines(text), min_code_points)) - {None}:
            if at := found.get(key):
                at[0] += 1
                at[1] = max(at[1], doc)
            else:
                found[key] = [1, doc]
    return found


def _send_keys(shards: int, text: str, id_: str, min_code_points: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, raw in zip(column(batch, "block").to_pylist(), column(batch, "payload"), strict=True):
                docs = read_payload(raw.as_buffer())
                found = _block_keys(_ids(docs, id_), column(docs, text).to_pylist(), min_code_points)
                if not found:
                    continue
                halves, held = key_halves(list(found)), np.array(list(found.values()), np.int64)
                shard = shard_of(halves, shards)
                order = np.argsort(shard, kind="stable")
                edge = np.flatnonzero(np.concatenate([[True], np.diff(shard[order]) != 0, [True]]))
                parts = [order[a:b] for a, b in zip(edge[:-1], edge[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([
                    pa.array([int(shard[x[0]]) for x in parts], pa.int64()), pa.array([block] * len(parts), pa.int64()),
                    *(pa.array([f(x) for x in parts], pa.binary()) for f in (lambda x: halves[x].tobytes(), lambda x: held[x, 0].tobytes(), lambda x: held[x, 1].tobytes())),
                ], names=["shard", "block", "keys", "n", "top"])

    return run


class ReferenceCounts:
    """The exact table of one shard: keys in order, the documents that hold each, and the largest of their ids."""

    def __init__(self, halves: np.ndarray, n: np.ndarray, top: np.ndarray):
        order = np.lexsort((halves[:, 1], halves[:, 0]))
        halves = halves[order]
        start = np.flatnonzero(np.concatenate([[True], (halves[1:] != halves[:-1]).any(axis=1)])) if len(halves) else np.zeros(0, np.int64)
        self.keys = halves[start]
        self.n_docs = np.add.reduceat(n[order], start) if len(start) else n
        self.max_id = np.maximum.reduceat(top[order], start) if len(start) else top

    def at(self, halves: np.ndarray) -> np.ndarray:
        """The place of each key, or -1."""
        out = np.full(len(halves), -1)
        if len(self.keys):
            place = np.searchsorted(self.keys[:, 0], halves[:, 0])
            while True:  # keys that share their first half stand together
                live = place < len(self.keys)
                live &= np.where(live, self.keys[np.minimum(place, len(self.keys) - 1), 0] == halves[:, 0], False) & (out < 0)
                if not live.any():
                    break
                same = live & (self.keys[np.minimum(place, len(self.keys) - 1), 1] == halves[:, 1])
                out[same] = place[same]
                place = place + 1
        return out


def _judge(min_docs: int):
    """A shard: the exact counts of all keys, a filter of those over the threshold, and an answer to every block."""

    def run(table: pa.Table) -> pa.Table:
        sent = [key_halves([x]) for x in table["keys"].to_pylist()]
        n, top = (np.concatenate([np.frombuffer(x, np.int64) for x in table[c].to_pylist()]) for c in ("n", "top"))
        counts = ReferenceCounts(np.concatenate(sent), n, top)
        known = counts.n_docs >= min_docs
        known_filter = CuckooFilter.of(counts.keys[known])
        rows = []
        for block, halves in zip(table["block"].to_pylist(), sent, strict=True):
            halves = halves[known_filter.contains(halves)]
            at = counts.at(halves)
            at = at[(at >= 0) & known[np.maximum(at, 0)]]
            if len(at):
                rows.append((block, counts.keys[at].tobytes(), counts.max_id[at].tobytes()))
        kinds = (pa.int64(), pa.binary(), pa.binary())
        return pa.table({c: pa.array([r[i] for r in rows], t) for i, (c, t) in enumerate(zip(("block", "keys", "top"), kinds, strict=True))})

    return run


def line_dedup(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", min_code_points: int = MIN_CODE_POINTS, min_docs: int = MIN_DOCS) -> DataFrame:
    """Drop every line whose key stands in at least `min_docs` documents, except in the largest id that holds it.

    Returns the columns of `docs`, with n_lines (before dropping), n_dropped and kept_text; a column of such a name
    is replaced. A null or empty text is one empty line. Keys under `min_code_points` code points stay. Each row
    counts as a document; rows that share the largest id all keep the line; a null id is below every other. An empty
    table gives an empty result.
    """
    out = docs.drop("n_lines", "n_dropped", "kept_text")
    text, id_ = (f"c{out.columns.index(c)}" for c in (text_col, id_col))
    blocks = Blocks(out.toDF(*(f"c{i}" for i in range(len(out.columns)))), text)
    shards = min(2**CELL_BITS, 2**blocks.space.range_bits)
    sent = blocks.rows.mapInArrow(_send_keys(shards, text, id_, min_code_points), "shard long, block long, keys binary, n binary, top binary")
    answers = sent.groupBy("shard").applyInArrow(_judge(min_docs), "block long, keys binary, top binary")
    answers = answers.groupBy("block").agg(F.collect_list(F.struct("keys", "top")).alias("known"))
    schema = T.StructType([*out.schema.fields, T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType()), T.StructField("kept_text", T.StringType())])

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, known in zip(column(batch, "payload"), column(batch, "known").to_pylist(), strict=True):
                rows = read_payload(raw.as_buffer())
                last: dict[bytes, int] = {}
                for part in known or []:
                    last |= zip((part["keys"][i : i + 16] for i in range(0, len(part["keys"]), 16)), np.frombuffer(part["top"], np.int64).tolist(), strict=True)
                n_lines, n_dropped, kept = [], [], []
                for doc, t in zip(_ids(rows, id_), column(rows, text).to_pylist(), strict=True):
                    lines = _lines(t)
                    n_lines.append(len(lines))
                    if last:
                        left = [x for x, k in zip(lines, line_keys(lines, min_code_points), strict=True) if k is None or doc >= last.get(k, LEAST)]
                        if len(left) < len(lines):
                            lines, t = left, b"\n".join(left).decode()
                    n_dropped.append(n_lines[-1] - len(lines))
                    kept.append(t or "")
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(kept, pa.string())], names=schema.names)

    return blocks.with_rows(answers, "left").mapInArrow(apply, schema)


FILTERS = "shard long, filter binary, full boolean"


class ReversibleLineIndex:
    """Line reference counts that follow insertions and deletions of documents.

    The folder holds an append-only log of postings (key, id, +1 or -1) and, per shard, a cuckoo filter of the keys
    in use. A deletion appends the negated postings of the documents, so nothing is ever lost: the counts are exact
    at each moment, and an index after insert(x) and delete(x) answers as before. An update counts only the keys it
    touches, and of those inserted only the ones that a filter already knows; the filters stay where their shard is.
    """

    def __init__(self, spark: SparkSession, path: str, shards: int = 8, min_code_points: int = MIN_CODE_POINTS):
        self.spark, self.path, self.shards, self.min_code_points = spark, path, shards, min_code_points
        self.parts: list[str] = []
        self.filters = spark.createDataFrame([], FILTERS)

    def _append(self, docs: DataFrame, sign: int) -> DataFrame:
        """Log the documents' postings; returns their distinct keys (key, shard)."""
        part = f"{self.path}/postings-{uuid.uuid4().hex}"
        keys = docs.select("doc_id", "text").mapInArrow(_doc_keys(self.min_code_points, self.shards), "key binary, shard long, id long")
        keys.withColumn("sign", F.lit(sign)).write.parquet(part)
        self.parts.append(part)
        return self.spark.read.parquet(part).select("key", "shard").distinct()

    def insert(self, docs: DataFrame) -> None:
        before = self.parts[:]
        touched = stored(self._append(docs, 1))
        if before:
            known = self._probe(touched)
            live = self._count(self.spark.read.parquet(*before).join(known.filter("hit").select("key"), "key", "left_semi"))
            touched = touched.join(live.select("key"), "key", "left_anti")
        self._refilter(touched, 1)

    def delete(self, docs: DataFrame) -> None:
        """Take out documents that were inserted, with the texts they had."""
        touched = stored(self._append(docs, -1))
        live = self._count(self.spark.read.parquet(*self.parts).join(touched.select("key"), "key", "left_semi"))
        self._refilter(touched.join(live.select("key"), "key", "left_anti"), -1)

    @staticmethod
    def _count(log: DataFrame) -> DataFrame:
        live = log.groupBy("key", "shard", "id").agg(F.sum("sign").alias("n")).filter("n > 0")
        return live.groupBy("key", "shard").agg(F.sum("n").alias("n_docs"), F.max("id").alias("max_id"))

    def counts(self) -> DataFrame:
        """key, shard, n_docs and max_id over the documents that are in."""
        return self._count(self.spark.read.parquet(*self.parts))

    def _probe(self, keys: DataFrame) -> DataFrame:
        """The keys (key, shard), and whether their shard's filter knows them."""

        def probe(left: pa.Table, right: pa.Table) -> pa.Table:
            keys = left["key"].to_pylist()
            known = CuckooFilter.from_bytes(right["filter"][0].as_py()).contains(key_halves(keys)) if right.num_rows and keys else np.zeros(len(keys), bool)
            return pa.table({"key": pa.array(keys, pa.binary()), "hit": pa.array(known)})

        return keys.groupBy("shard").cogroup(self.filters.groupBy("shard")).applyInArrow(probe, "key binary, hit boolean")

    def _refilter(self, changed: DataFrame, sign: int) -> None:
        """Put the keys into their shards' filters, or take them out; a filter that is full is made anew from the counts."""

        def step(left: pa.Table, right: pa.Table) -> pa.Table:
            shard = (left if left.num_rows else right)["shard"][0].as_py()
            keys = key_halves(left["key"].to_pylist())
            f = CuckooFilter.from_bytes(right["filter"][0].as_py()) if right.num_rows else CuckooFilter(4 * len(keys))
            full = False
            if sign < 0:
                f.delete(keys)
            else:
                full = not f.insert(keys).all()
            return pa.table({"shard": pa.array([shard], pa.int64()), "filter": pa.array([f.to_bytes()], pa.binary()), "full": pa.array([full])})

        self.filters = stored(changed.groupBy("shard").cogroup(self.filters.groupBy("shard")).applyInArrow(step, FILTERS))
        if not self.filters.filter("full").isEmpty():
            full = self.counts().join(self.filters.filter("full").select("shard"), "shard", "left_semi")
            anew = full.select("shard", "key").groupBy("shard").applyInArrow(_build, FILTERS)
            self.filters = stored(self.filters.filter("NOT full").unionByName(anew))

    def may_hold(self, lines: list[str]) -> np.ndarray:
        """For each line, whether the filters let it through; False is certain."""
        keys = line_keys([x.encode() for x in lines], self.min_code_points)
        asked = [(k, int(shard_of(key_halves([k]), self.shards)[0])) for k in {*keys} - {None}]
        if not asked:
            return np.zeros(len(lines), bool)
        hits = {bytes(r["key"]) for r in self._probe(self.spark.createDataFrame(asked, "key binary, shard long")).filter("hit").collect()}  # of the given lines
        return np.array([k in hits for k in keys])


def _build(table: pa.Table) -> pa.Table:
    f = CuckooFilter.of(key_halves(table["key"].to_pylist()))
    return pa.table({"shard": table["shard"][:1], "filter": pa.array([f.to_bytes()], pa.binary()), "full": pa.array([False])})


def _doc_keys(min_code_points: int, shards: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys = [], []
            for doc, text in zip(_ids(batch, "doc_id"), column(batch, "text").to_pylist(), strict=True):
                own = list(set(line_keys(_lines(text), min_code_points)) - {None})
                ids += [doc] * len(own)
                keys += own
            shard = shard_of(key_halves(keys), shards) if keys else []
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(shard, pa.int64()), pa.array(ids, pa.int64())], names=["key", "shard", "id"])

    return run
