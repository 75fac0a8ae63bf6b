"""Documents in compressed blocks, and which of their hashed items other documents hold too.

1. Documents are written once as blocks, a row each, in a table bucketed by block. What is later found about a block
   joins it where it is: texts are never shuffled.
2. The items of a block (hashes of word grams) are sorted and sent, as gap-coded cells of a hash space, to the ranges
   of that space. A range adds up how often each cell occurs and answers every block with one bit a cell: whether it
   occurs twice at least. A cell that a block holds many times is sent once.
3. The block makes its items again, in the same order, and so knows which item each bit is for.

The hash space, the ranges and the blocks grow with the input, so the share of cells that meet by chance stays the
same; nothing is broadcast, and no task holds more than a block or a range.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._state import discard, shared_path, shuffles_released
from ._text import column, give_back, text_blocks

#: Bytes of text of a block, at least and at most; between them a block is BLOCK_SHARE of the input.
BLOCK_BYTES = 2 << 20
MOST_BLOCK_BYTES = 64 << 20
BLOCK_SHARE = 4096
#: The hash space has 2^SPARE_BITS to twice as many cells for each byte of input: of texts of five letters a word, one
#: cell in 24 or less is hit by chance.
SPARE_BITS = 2
#: Bytes of input for each range of the hash space; each partition of a shuffle has RANGES_EACH at least.
RANGE_BYTES = 16 << 20
RANGES_EACH = 1
#: Buckets of the table of blocks, at most (the engine's own bound is 100,000).
MOST_BUCKETS = 50_000

Items = Callable[[pa.RecordBatch], np.ndarray]


@dataclass(frozen=True)
class Space:
    """A hash space of 2^bits cells in 2^range_bits ranges."""

    bits: int
    range_bits: int

    @classmethod
    def of(cls, n_bytes: int, partitions: int, spare: int = SPARE_BITS) -> Space:
        ranges = max(1, -(-n_bytes // RANGE_BYTES), RANGES_EACH * partitions)
        range_bits = min(20, (ranges - 1).bit_length())
        return cls(min(range_bits + 31, max(range_bits + 8, max(n_bytes, 1).bit_length() + spare)), range_bits)

    def sort(self, items: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct cells in order, how often each occurs, the items' places in that order, and where the ranges end."""
        cells, order = sort_places(items >> np.uint64(64 - self.bits), self.bits)
        start = np.flatnonzero(np.concatenate([[True], cells[1:] != cells[:-1]])) if len(cells) else np.zeros(0, np.int64)
        cells = cells[start]
        count = np.diff(np.append(start, len(items)))
        edges = np.searchsorted(cells, np.arange(1, 2**self.range_bits + 1, dtype=np.uint64) << np.uint64(self.bits - self.range_bits))
        return cells, count, order, edges


def sort_places(values: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers below 2^bits in order, and their places; equal ones keep theirs."""
    wide = max(1, (len(values) - 1).bit_length())
    if bits + wide > 64:
        order = np.argsort(values, kind="stable")
        return values[order], order
    packed = (values << np.uint64(wide)) | np.arange(len(values), dtype=np.uint64)
    packed.sort()
    return packed >> np.uint64(wide), (packed & np.uint64((1 << wide) - 1)).astype(np.int64)


def encode_gaps(values: np.ndarray) -> bytes:
    """Ascending numbers below 2^32 as gaps of two bytes, with wide gaps aside; of as many as it takes, if many are wide.

    The bytes of a gap stand apart by rank, so that the high ones compress.
    """
    gaps = np.diff(values.astype(np.int64), prepend=0)
    wide = gaps >= 0xFFFF
    n = int(wide.sum())
    if 8 * n <= len(gaps):
        return b"\0" + np.uint32(n).tobytes() + gaps[wide].astype("<u4").tobytes() + np.where(wide, 0xFFFF, gaps).astype("<u2").tobytes()
    width = (int(gaps.max()).bit_length() + 7) // 8
    return bytes([width]) + b"".join((gaps >> 8 * i).astype(np.uint8).tobytes() for i in range(width))


def decode_gaps(raw: bytes) -> np.ndarray:
    if raw[0]:
        planes = np.frombuffer(raw, np.uint8, offset=1).reshape(raw[0], -1)
        return np.cumsum(sum(p.astype(np.int64) << 8 * i for i, p in enumerate(planes)))
    n = int(np.frombuffer(raw, "<u4", 1, 1)[0])
    gaps = np.frombuffer(raw, "<u2", offset=5 + 4 * n).astype(np.int64)
    gaps[gaps == 0xFFFF] = np.frombuffer(raw, "<u4", n, 5)
    return np.cumsum(gaps)


def encode_counts(count: np.ndarray) -> bytes:
    """Counts of which most are 1: a bit for each, a byte for those above, four for those from 255 on."""
    many = count > 1
    if not many.any():
        return b""
    above = count[many]
    return np.packbits(many).tobytes() + np.minimum(above, 255).astype(np.uint8).tobytes() + np.minimum(above[above >= 255], 2**32 - 1).astype("<u4").tobytes()


def decode_more(raw: bytes, n: int) -> np.ndarray:
    """How far each of n counts is above 1."""
    out = np.zeros(n, np.int64)
    if raw:
        many = np.flatnonzero(np.unpackbits(np.frombuffer(raw, np.uint8, -(-n // 8)), count=n))
        above = np.frombuffer(raw, np.uint8, len(many), -(-n // 8)).astype(np.int64)
        above[above == 255] = np.frombuffer(raw, "<u4", offset=-(-n // 8) + len(many))
        out[many] = above - 1
    return out


def _write(limit: int, text: str = "text"):
    def packed(parts: list[pa.RecordBatch], block: int) -> pa.RecordBatch:
        sink = pa.BufferOutputStream()
        table = pa.Table.from_batches(parts).combine_chunks()
        with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 1))) as out:
            out.write_table(table)
        return pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "payload"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, held, size = TaskContext.get().partitionId() << 32, [], 0
        for batch in batches:
            for part in text_blocks(batch, text, limit):
                held.append(part)
                size += part.nbytes
                if size >= 0.8 * limit:
                    yield packed(held, block)
                    block, held, size = block + 1, [], 0
        if held:
            yield packed(held, block)

    return run


def read_payload(raw: bytes) -> pa.RecordBatch:
    give_back()
    table = pa.ipc.open_stream(raw).read_all().combine_chunks()
    return table.to_batches()[0] if table.num_rows else pa.RecordBatch.from_pylist([], table.schema)


class Blocks:
    """The table of blocks (block, payload) of documents, and the hash space for their items. `text` names the column by whose bytes blocks are cut."""

    def __init__(self, docs: DataFrame, text: str = "text", spare: int = SPARE_BITS):
        spark = docs.sparkSession
        n_bytes = docs.agg(F.sum(F.octet_length(text))).first()[0] or 0
        partitions = int(spark.conf.get("spark.sql.shuffle.partitions"))
        limit = min(MOST_BLOCK_BYTES, max(BLOCK_BYTES, n_bytes // BLOCK_SHARE))
        buckets = min(MOST_BUCKETS, max(partitions, n_bytes // limit // 4))
        name = f"kmerspark_blocks_{uuid.uuid4().hex}"
        path = shared_path(spark)
        with shuffles_released(spark):
            docs.mapInArrow(_write(limit, text), "block long, payload binary").write.bucketBy(buckets, "block").option("path", path).option("compression", "none").saveAsTable(name)
        self.rows, self.space, self.n_bytes, self.name = spark.table(name), Space.of(n_bytes, partitions, spare), n_bytes, name
        self.rows._stored_at = path

    def discard(self) -> None:
        """Delete the table; what has been made of it must not be read again."""
        spark = self.rows.sparkSession
        discard(self.rows)
        spark.sql(f"DROP TABLE IF EXISTS {self.name}")

    def with_rows(self, rows: DataFrame, how: str = "inner") -> DataFrame:
        """block, payload and the columns of `rows`, which has a row a block at most. The blocks stay where they are."""
        return self.rows.join(rows.hint("shuffle_hash"), "block", how)

    def counted(self, items: Items) -> DataFrame:
        """block, range, n, payload: for each distinct cell of a block, range by range, a bit: it occurs elsewhere too."""
        space = self.space

        def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for block, raw in zip(column(batch, "block").to_pylist(), column(batch, "payload"), strict=True):
                    yield cell_rows(space, block, items(read_payload(raw.as_buffer())))

        return add_up(self.rows.mapInArrow(send, CELLS), space)


CELLS = "range int, block long, n int, cells binary, more binary"


def cell_rows(space: Space, block: int, items: np.ndarray) -> pa.RecordBatch:
    """What a block sends: for each range its distinct cells, and which of them it holds how often beyond once."""
    cells, count, _, edges = space.sort(items)
    cells &= np.uint64((1 << space.bits - space.range_bits) - 1)
    rows, a = [], 0
    for r, b in enumerate(edges.tolist()):
        if b > a:
            rows.append((r, block, b - a, encode_gaps(cells[a:b]), encode_counts(count[a:b])))
        a = b
    kinds = (pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], t) for i, t in enumerate(kinds)], names=[x.split()[0] for x in CELLS.split(", ")])


def add_up(sent: DataFrame, space: Space, level: int | None = None) -> DataFrame:
    """block, range, n, payload: the answers to the rows that blocks have sent.

    With `level`, also rows without a block: the cells that occur 2^level times or more (level, n, cells).
    """
    return sent.groupBy("range").applyInArrow(_add_up(level, space.bits - space.range_bits), "block long, range int, n int, payload binary")


def _add_up(level: int | None, bits: int):
    def run(table: pa.Table) -> pa.Table:
        n = table["n"].to_numpy()
        ends = np.cumsum(n)
        count = np.ones(int(ends[-1]), np.int64)
        for end, size, raw in zip(ends.tolist(), n.tolist(), table["more"].to_pylist(), strict=True):
            count[end - size : end] += decode_more(raw, size)
        cells, order = sort_places(np.concatenate([decode_gaps(x) for x in table["cells"].to_pylist()]).astype(np.uint64), bits)
        start = np.flatnonzero(np.concatenate([[True], cells[1:] != cells[:-1]]))
        total = np.add.reduceat(count[order], start)
        hit = np.empty(len(cells), bool)
        hit[order] = np.repeat(total > 1, np.diff(np.append(start, len(cells))))
        out = [(b, int(k), np.packbits(hit[end - k : end]).tobytes()) for b, end, k in zip(table["block"].to_pylist(), ends.tolist(), n.tolist(), strict=True)]
        rows = [(b, table["range"][0].as_py(), k, x) for b, k, x in out]
        if level is not None:
            own = np.log2(total).astype(np.int64)
            for v in np.unique(own[own >= level]).tolist():
                found = cells[start][own == v]
                rows.append((None, v, len(found), (np.uint64(table["range"][0].as_py() << bits) + found).astype("<u8").tobytes()))
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.binary())
        return pa.table({c: pa.array([r[i] for r in rows], t) for i, (c, t) in enumerate(zip(("block", "range", "n", "payload"), kinds, strict=True))})

    return run


def by_block(answers: DataFrame) -> DataFrame:
    """block, parts: the bits of each block's cells, in the order of the ranges."""
    own = answers.filter(F.col("block").isNotNull())
    return own.groupBy("block").agg(F.sort_array(F.collect_list(F.struct("range", "n", "payload"))).alias("parts"))


def repeated(space: Space, items: np.ndarray, parts: list[dict] | None) -> np.ndarray:
    """For each item of a block, whether its cell occurs more than once among all blocks."""
    out = np.zeros(len(items), bool)
    if len(items):
        _, count, order, _ = space.sort(items)
        bits = np.concatenate([np.unpackbits(np.frombuffer(p["payload"], np.uint8), count=p["n"]) for p in parts])
        out[order] = np.repeat(bits.astype(bool), count)
    return out
