"""The prime-table sketch: Z arrays of saturating counters with distinct prime sizes, one hash per key.

A key's counter in a table is its code modulo the table's size; a count is the least of its Z counters, so it is
never below the truth (up to the counters' cap). The counters live in a DataFrame, sparse (a row per counter in
use) or dense (byte blocks); both merge by saturating addition, which may be done in any order.
"""

from __future__ import annotations

import json
import math
import warnings
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.dna import unsigned_mod, xxhash64_of
from ..plans.sizing import prime_table_sizes, size_for_fpr
from .kmers import combined_kmers, estimate_distinct, md5_60

#: Counters of a dense block.
BLOCK = 65_536
#: Bytes of dense tables up to which a probe may broadcast them; beyond it keys travel to the counters.
BROADCAST_BYTES = 64 << 20
#: Bytes of a task's own arrays up to which reads are counted in place rather than shuffled.
DENSE_BYTES = 64 << 20
#: Tasks whose copies of a block are summed first.
MERGE = 64
WIDTHS = (1, 2, 4, 8, 16, 32, 64)


@dataclass(frozen=True)
class SketchSpec:
    """All that two sketches must share to be merged, and what a saved one says of itself."""

    primes: tuple[int, ...]
    k: int = 22
    stranded: bool = False
    counter_bits: int = 8
    layout: str = "primes"
    hash_id: str = "pack2"
    extra: dict = field(default_factory=dict, compare=False)

    def __post_init__(self):
        if self.counter_bits not in WIDTHS:
            raise ValueError(f"counters have {WIDTHS} bits")
        if not self.primes or len(set(self.primes)) < len(self.primes) and self.layout == "primes":
            raise ValueError("tables need distinct sizes")

    @classmethod
    def for_fpr(cls, n: float, f: float, tables: int = 4, **kw) -> SketchSpec:
        """A sketch in which a share f of n distinct keys will be miscounted."""
        size = size_for_fpr(n, f, tables, exact=True).table_size
        return cls(tuple(prime_table_sizes(max(size, 3 * tables + 5), tables)), **kw)

    @classmethod
    def for_reads(cls, reads: DataFrame, f: float, tables: int = 4, k: int = 22, stranded: bool = False, **kw) -> SketchSpec:
        """A sketch in which about a share f of the reads' distinct words will be miscounted; one sampling pass."""
        return cls.for_fpr(max(1, estimate_distinct(reads, k, stranded)), f, tables, k=k, stranded=stranded, **kw)

    @classmethod
    def for_memory(cls, n_bytes: int, tables: int = 4, **kw) -> SketchSpec:
        """The largest sketch whose counters take at most n_bytes."""
        bits = kw.get("counter_bits", 8)
        return cls(tuple(prime_table_sizes(n_bytes * 8 / bits / tables, tables)), **kw)

    @property
    def cap(self) -> int:
        return min(2**self.counter_bits - 1, 2**63 - 1)

    def fits_a_task(self) -> bool:
        """Whether a task can hold the tables as arrays of its own."""
        return self.counter_bits <= 16 and self.memory_bytes() <= DENSE_BYTES

    @property
    def tables(self) -> int:
        return len(self.primes)

    def memory_bytes(self) -> int:
        """Bytes of all counters as they are held, in whole bytes each; fixed before the first key is counted."""
        sizes = self.primes[:1] if self.layout == "single" else self.primes
        return sum(sizes) * max(8, self.counter_bits) // 8

    def packed_bytes(self) -> int:
        """Bytes of all counters if those of less than a byte shared bytes."""
        sizes = self.primes[:1] if self.layout == "single" else self.primes
        return sum(-(-h * self.counter_bits // 8) for h in sizes)

    def check_memory(self, limit: int) -> SketchSpec:
        if self.memory_bytes() > limit:
            raise MemoryError(f"the sketch takes {self.memory_bytes()} bytes; the bound is {limit}")
        return self

    def cells(self, key: Column) -> Column:
        """An array of (table_id, cell), one for each table."""
        if self.layout == "single":
            size = self.primes[0]
            return F.array(*(F.struct(F.lit(i).cast("tinyint").alias("table_id"), F.pmod(F.xxhash64(key, F.lit(i)), F.lit(size)).alias("cell")) for i in range(len(self.primes))))
        k = self.k if self.hash_id == "pack2" else 31
        return F.array(*(F.struct(F.lit(i).cast("tinyint").alias("table_id"), unsigned_mod(key, p, k).alias("cell")) for i, p in enumerate(self.primes)))

    def positions(self, codes: np.ndarray) -> list[np.ndarray]:
        if self.layout == "single":
            return [xxhash64_of(codes, i) % self.primes[0] for i in range(len(self.primes))]
        return [(codes.view(np.uint64) % np.uint64(p)).astype(np.int64) for p in self.primes]

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @classmethod
    def from_json(cls, text: str) -> SketchSpec:
        raw = json.loads(text)
        return cls(**raw | {"primes": tuple(raw["primes"])})


class PrimeSketch:
    """A spec and its counters in use: table_id, cell, cnt (at most the cap)."""

    def __init__(self, spec: SketchSpec, cells: DataFrame, n_updates: int | None = None, overflow: DataFrame | None = None, dense: DataFrame | None = None):
        self.spec, self.cells, self.n_updates, self.overflow, self.dense = spec, cells, n_updates, overflow, dense
        #: Rows (kmer, cnt) that the counters add up, if they are known; a key may have several.
        self.counted: DataFrame | None = None
        #: The reads whose words were counted, if they are known.
        self.reads: DataFrame | None = None
        self._arrays: list[np.ndarray] | None = None
        self._broadcast = None

    # -- building --

    @classmethod
    def empty(cls, spark: SparkSession, spec: SketchSpec) -> PrimeSketch:
        return cls(spec, spark.createDataFrame([], "table_id tinyint, cell long, cnt long"), 0)

    @classmethod
    def of_counts(cls, counts: DataFrame, spec: SketchSpec) -> PrimeSketch:
        """From (kmer, cnt); repeated keys add up. Keys are combined before they fan out to the tables."""
        hits = counts.select(F.explode(spec.cells(F.col("kmer"))).alias("c"), "cnt").select("c.table_id", "c.cell", "cnt")
        if spec.layout == "single":
            hits = hits.withColumn("table_id", F.lit(0).cast("tinyint"))
        cells = hits.groupBy("table_id", "cell").agg(F.least(F.sum("cnt"), F.lit(spec.cap)).alias("cnt"))
        out = cls(spec, cells)
        out.counted = counts
        return out

    @classmethod
    def build(cls, reads: DataFrame, spec: SketchSpec) -> PrimeSketch:
        """From reads: dense arrays per task if they are small, else by shuffled words."""
        if spec.fits_a_task():
            out = cls.build_dense(reads, spec)
            out.reads = reads
            return out
        combined = combined_kmers(reads, spec.k, spec.stranded)
        out = cls.of_counts(combined.groupBy("kmer").agg(F.sum("cnt").alias("cnt")), spec)
        out.counted, out.reads = combined, reads
        return out

    @classmethod
    def build_dense(cls, reads: DataFrame, spec: SketchSpec) -> PrimeSketch:
        """The same counters from tasks that add into fixed arrays and emit the touched blocks, to be summed.

        No key is shuffled: each task sends at most the sketch's size, whatever it reads. Arrays have the counters'
        own width; copies of a block are summed in two rounds, so no task sees more than MERGE, or a MERGEth of all.
        """

        def codes(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            from ..functions.dna import windows_of
            from .kmers import read_blocks

            for batch in batches:
                for _, raw, ends in read_blocks(batch):
                    yield np.unique(windows_of(raw, ends, spec.k, spec.stranded)[2], return_counts=True)

        return cls._dense(reads.select("read_id", "seq"), codes, spec)

    @classmethod
    def dense_of_counts(cls, counts: DataFrame, spec: SketchSpec) -> PrimeSketch:
        """As `build_dense`, from (kmer, cnt); repeated keys add up."""

        def codes(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for batch in batches:
                if batch.num_rows:
                    yield np.asarray(batch.column(0)).view(np.uint64), np.asarray(batch.column(1))

        return cls._dense(counts.select("kmer", F.col("cnt").cast("long")), codes, spec)

    @classmethod
    def _dense(cls, rows: DataFrame, codes: Callable, spec: SketchSpec) -> PrimeSketch:
        width = f"<u{max(8, spec.counter_bits) // 8}"

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            single = [np.zeros(spec.primes[0], width)] if spec.layout == "single" else []
            tables = single * spec.tables or [np.zeros(p, width) for p in spec.primes]
            fresh = np.zeros(max(spec.primes), np.uint64 if spec.counter_bits > 32 else np.uint32)
            for code, cnt in codes(batches):
                for table, at in zip(tables, spec.positions(code), strict=True):
                    own = fresh[: len(table)]
                    own.fill(0)
                    np.add.at(own, at, np.minimum(cnt, spec.cap).astype(own.dtype))
                    room = spec.cap - table.astype(own.dtype)
                    table += np.minimum(own, room).astype(width)
            group = TaskContext.get().partitionId() // MERGE
            for i, table in enumerate(single or tables):
                for b in range(0, len(table), BLOCK):
                    if table[b : b + BLOCK].any():
                        yield pa.RecordBatch.from_arrays([pa.array([i], pa.int8()), pa.array([b // BLOCK], pa.int32()), pa.array([group], pa.int32()), pa.array([table[b : b + BLOCK].tobytes()], pa.binary())], names=["table_id", "block", "group", "counters"])

        blocks = rows.mapInArrow(run, "table_id tinyint, block int, group int, counters binary")
        some = blocks.groupBy("table_id", "block", "group").applyInArrow(_add_blocks(spec), "table_id tinyint, block int, group int, counters binary")
        dense = some.groupBy("table_id", "block").applyInArrow(_add_blocks(spec), "table_id tinyint, block int, counters binary")
        return cls(spec, cells_of(dense, spec), dense=dense)

    @classmethod
    def from_column(cls, df: DataFrame, column: str, spec: SketchSpec, portable: bool = False) -> PrimeSketch:
        """A sketch of any keys. They are mixed first: raw small integers modulo a prime would not be a hash."""
        key = md5_60(F.col(column)) if portable else F.xxhash64(column).bitwiseAND(F.lit(2**62 - 1))
        counts = df.filter(F.col(column).isNotNull()).groupBy(key.alias("kmer")).agg(F.count("*").alias("cnt"))
        return cls.of_counts(counts, SketchSpec(spec.primes, 31, True, spec.counter_bits, spec.layout, "md5_60" if portable else "xxhash64"))

    def increment(self, kmers: DataFrame) -> PrimeSketch:
        """A new sketch with the keys (kmer, or kmer and cnt) counted in."""
        counts = kmers if "cnt" in kmers.columns else kmers.groupBy("kmer").agg(F.count("*").alias("cnt"))
        return self.merge(PrimeSketch.of_counts(counts, self.spec))

    def merge(self, *others: PrimeSketch) -> PrimeSketch:
        """The sketch of all that was counted in any; dense ones are added block by block."""
        if any(o.spec != self.spec for o in others):
            raise ValueError("sketches of different specs can't be merged")
        if all(s.dense is not None for s in (self, *others)):
            blocks = self.dense
            for o in others:
                blocks = blocks.unionByName(o.dense)
            dense = blocks.groupBy("table_id", "block").applyInArrow(_add_blocks(self.spec), "table_id tinyint, block int, counters binary")
            return PrimeSketch(self.spec, cells_of(dense, self.spec), dense=dense)
        cells = self.cells
        for o in others:
            cells = cells.unionByName(o.cells)
        return PrimeSketch(self.spec, cells.groupBy("table_id", "cell").agg(F.least(F.sum("cnt"), F.lit(self.spec.cap)).alias("cnt")))

    def stored(self, store: Callable[[DataFrame], DataFrame]) -> PrimeSketch:
        if self.dense is not None:
            dense = store(self.dense)
            return PrimeSketch(self.spec, cells_of(dense, self.spec), self.n_updates, self.overflow, dense)
        return PrimeSketch(self.spec, store(self.cells), self.n_updates, self.overflow)

    # -- saving --

    def blocks(self) -> DataFrame:
        """table_id, block, counters: dense bytes (whole bytes a counter) of the blocks in use."""
        if self.dense is not None:
            return self.dense
        width = max(8, self.spec.counter_bits) // 8

        def pack(key: tuple, table: pa.Table) -> pa.Table:
            out = np.zeros(BLOCK, f"<u{width}")
            out[np.asarray(table["cell"]) % BLOCK] = np.asarray(table["cnt"])
            return pa.table({"table_id": pa.array([key[0].as_py()], pa.int8()), "block": pa.array([key[1].as_py()], pa.int32()), "counters": pa.array([out.tobytes()], pa.binary())})

        return self.cells.withColumn("block", F.floor(F.col("cell") / BLOCK).cast("int")).groupBy("table_id", "block").applyInArrow(pack, "table_id tinyint, block int, counters binary")

    def save(self, path: str, codec: str = "none") -> None:
        """Dense blocks as Parquet ('none' or 'gzip'), the spec as JSON beside them."""
        self.blocks().write.mode("overwrite").option("compression", codec).parquet(f"{path}/blocks")
        spark = self.cells.sparkSession
        spark.createDataFrame([(self.spec.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/spec")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> PrimeSketch:
        spec = SketchSpec.from_json(spark.read.text(f"{path}/spec").first()[0])
        blocks = spark.read.parquet(f"{path}/blocks").select("table_id", "block", "counters")
        return cls(spec, cells_of(blocks, spec), dense=blocks)

    # -- judging --

    def loads(self) -> dict[int, float]:
        """Share of counters in use, by table."""
        n = {r["table_id"]: r["n"] for r in self.cells.filter("cnt > 0").groupBy("table_id").agg(F.count("*").alias("n")).collect()}
        sizes = self.spec.primes[:1] if self.spec.layout == "single" else self.spec.primes
        return {i: n.get(i, 0) / p for i, p in enumerate(sizes)}

    def load_fpr(self) -> float:
        """Chance that an absent key meets only counters in use."""
        loads = list(self.loads().values())
        return loads[0] ** self.spec.tables if self.spec.layout == "single" else math.prod(loads)

    def assess(self, max_fpr: float = 0.1, on_bad: str = "warn") -> dict:
        """Whether the memory was enough for the data; warn, raise or only flag if not."""
        fpr = self.load_fpr()
        if fpr > max_fpr and on_bad == "raise":
            raise ValueError(f"the sketch errs at a rate of {fpr:.3f}; the bound is {max_fpr}")
        if fpr > max_fpr and on_bad == "warn":
            warnings.warn(f"the sketch errs at a rate of {fpr:.3f}; the bound is {max_fpr}", stacklevel=2)
        return {"fpr": fpr, "valid": fpr <= max_fpr}

    # -- local handle --

    def arrays(self) -> list[np.ndarray]:
        """The tables as arrays on the driver; only behind a check of their size."""
        if self._arrays is None:
            spec = self.spec
            if sum(spec.primes) * 8 > 8 * BROADCAST_BYTES or spec.memory_bytes() > BROADCAST_BYTES:
                raise MemoryError("the tables are too large for one process")
            width = max(8, spec.counter_bits) // 8
            sizes = spec.primes[:1] if spec.layout == "single" else spec.primes
            out = [np.zeros(p, f"u{width}") for p in sizes]
            if self.dense is not None:
                for r in self.dense.collect():  # within the bound that was checked above
                    own = np.frombuffer(r["counters"], f"<u{width}")
                    at = r["block"] * BLOCK
                    out[r["table_id"]][at : at + BLOCK] = own[: len(out[r["table_id"]]) - at]
                self._arrays = out
                return out
            rows = self.cells.toArrow()
            table, cell, cnt = (rows[c].to_numpy() for c in ("table_id", "cell", "cnt"))
            for i, a in enumerate(out):
                own = table == i
                a[cell[own]] = cnt[own]
            self._arrays = out
        return self._arrays

    def get_count(self, word: str | int) -> int:
        return int(probe_arrays(self.arrays(), self.spec, np.array([_code(word, self.spec)], np.uint64))[0])

    def increment_count(self, word: str | int) -> None:
        """Count one word in the local handle."""
        for a, at in zip(self.arrays(), self.spec.positions(np.array([_code(word, self.spec)], np.uint64)), strict=True):
            a[at] = min(int(a[at[0]]) + 1, self.spec.cap)


def _add_blocks(spec: SketchSpec) -> Callable:
    """Saturating sum of copies of a block, for groups by (table_id, block) and what else is in the key."""
    width = f"<u{max(8, spec.counter_bits) // 8}"

    def add(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            for raw in batch.column(batch.schema.get_field_index("counters")).to_pylist():
                own = np.frombuffer(raw, width)
                total = own.astype(np.uint64) if total is None else np.minimum(total + own, spec.cap)
        names = ["table_id", "block", *(["group"] if len(key) > 2 else []), "counters"]
        yield pa.RecordBatch.from_arrays([*(pa.array([k.as_py()], k.type) for k in key), pa.array([total.astype(width).tobytes()], pa.binary())], names=names)

    return add


def cells_of(blocks: DataFrame, spec: SketchSpec) -> DataFrame:
    """table_id, cell, cnt of the counters in use in dense blocks."""
    width = max(8, spec.counter_bits) // 8

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, b, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                own = np.frombuffer(raw, f"<u{width}")
                at = np.flatnonzero(own)
                yield pa.RecordBatch.from_arrays([pa.array([i] * len(at), pa.int8()), pa.array(at + b * BLOCK), pa.array(own[at].astype(np.int64))], names=["table_id", "cell", "cnt"])

    return blocks.select("table_id", "block", "counters").mapInArrow(unpack, "table_id tinyint, cell long, cnt long")


def _code(word: str | int, spec: SketchSpec) -> int:
    from ..functions.dna import windows_of

    if isinstance(word, int):
        return word
    raw = np.frombuffer(word.encode(), np.uint8)
    found = windows_of(raw, np.array([len(raw)]), spec.k, spec.stranded)[2]
    if len(raw) != spec.k or not len(found):
        raise ValueError(f"not a word of {spec.k} bases: {word}")
    return int(found[0])


def probe_arrays(tables: list[np.ndarray], spec: SketchSpec, codes: np.ndarray) -> np.ndarray:
    """The least counter of each key."""
    out = None
    for table, at in zip(tables * spec.tables if spec.layout == "single" else tables, spec.positions(codes), strict=True):
        out = table[at] if out is None else np.minimum(out, table[at])
    return out

