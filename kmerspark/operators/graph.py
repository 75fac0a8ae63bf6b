"""The word graph kept in a sketch: neighbours, partition of reads, containment, and an assembly proxy."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.dna import decode_kmer, encode_kmer, reverse_complement, windows_of
from ..plans.sizing import table_bytes
from ..sources.reads import text_of
from .components import connected_components
from .kmers import explode_kmers, read_blocks
from .lookup import lookup
from .packed import _cut, decode_sorted, encode_sorted, expand, layout, mixed, spans, squeeze
from .packed import _batch as packed_batch
from .sketch import PrimeSketch
from .store import discard


def neighbor_codes(kmer: Column, k: int, stranded: bool = False) -> Column:
    """The eight words that overlap a word in k-1 bases: four to the right, four to the left (k up to 31)."""
    mask = F.lit(4 ** (k - 1) - 1).cast("long")
    right = [F.shiftleft(kmer.bitwiseAND(mask), 2).bitwiseOR(F.lit(b).cast("long")) for b in range(4)]
    left = [F.shiftrightunsigned(kmer, 2).bitwiseOR(F.lit(b * 4 ** (k - 1)).cast("long")) for b in range(4)]
    if stranded:
        return F.array(*right, *left)
    return F.array(*(F.least(c, encode_kmer(reverse_complement(decode_kmer(c, k)), k)) for c in (*right, *left)))


def neighbors(kmers: DataFrame, sketch: PrimeSketch) -> DataFrame:
    """kmer, side, neighbor, est: the neighbours of each word that the sketch has counted."""
    k = sketch.spec.k
    codes = neighbor_codes(F.col("kmer"), k, sketch.spec.stranded)
    fan = kmers.select(F.col("kmer").alias("src"), F.posexplode(codes).alias("i", "kmer"))
    found = lookup(fan, sketch).filter(F.col("est") > 0)
    return found.select(F.col("src").alias("kmer"), F.when(F.col("i") < 4, "right").otherwise("left").alias("side"), F.col("kmer").alias("neighbor"), "est")


#: Bytes of reads whose words are dealt to parts in a pass, and passes at most; parts whose ties are joined at first.
PASS_BYTES, MOST_PASSES, JOINED = 16 << 20, 8, 32
TIES = "part int, nodes binary, roots binary"


def settled(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For each of n nodes, the least that it is tied to, directly or over others."""
    label = np.arange(n)
    while True:
        a, b = label[u], label[v]
        open_ = a != b
        if not open_.any():
            return label
        u, v, a, b = u[open_], v[open_], a[open_], b[open_]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while (label[label] != label).any():
            label = label[label]


def encode_ids(ids: np.ndarray) -> bytes:
    """Whole numbers by the bytes above their least one, apart by rank."""
    low = ids.min()
    rest = (ids - low).view(np.uint64)
    width = max(1, (int(rest.max()).bit_length() + 7) // 8)
    return int(low).to_bytes(8, "little", signed=True) + bytes([width]) + squeeze(b"".join((rest >> np.uint64(8 * i)).astype(np.uint8).tobytes() for i in range(width)))


def decode_ids(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(expand(raw[9:]), np.uint8).reshape(raw[8], -1)
    rest = planes[0].astype(np.uint64)
    for i in range(1, raw[8]):
        rest |= planes[i].astype(np.uint64) << np.uint64(8 * i)
    return rest.view(np.int64) + int.from_bytes(raw[:8], "little", signed=True)


def _forest(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes that are tied to a lesser one, and the least of each."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    root = nodes[settled(len(nodes), at[: len(u)], at[len(u) :])]
    return nodes[root < nodes], root[root < nodes]


def _tied_blocks(batches: Iterator[pa.RecordBatch], k: int, stranded: bool) -> Iterator[tuple[np.ndarray, ...]]:
    """Of each block: its reads with words and the least read that each is tied to there; its distinct words and theirs."""
    for batch in batches:
        for rows, raw, ends in read_blocks(batch):
            ids, rank = np.unique(np.asarray(rows.column(0)), return_inverse=True)
            read, _, code = windows_of(raw, ends, k, stranded)
            if not len(code):
                continue
            order = np.argsort(code)
            code, who = code[order], rank[read[order]]
            same = code[1:] == code[:-1]
            root = ids[settled(len(ids), who[:-1][same], who[1:][same])]
            start = np.flatnonzero(np.concatenate([[True], ~same]))
            own = np.unique(who)
            yield ids[own], root[own], code[start], root[who[start]]


def block_roots(reads: DataFrame, k: int, stranded: bool) -> DataFrame:
    """read_id, root: the reads with words, and the least that each is tied to within its block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, root, _, _ in _tied_blocks(batches, k, stranded):
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(root)], names=["read_id", "root"])

    return reads.select("read_id", "seq").mapInArrow(run, "read_id long, root long")


def word_roots(reads: DataFrame, k: int, stranded: bool, size: int, within: tuple[int, int] | None = None) -> DataFrame:
    """part, words, roots: each block's distinct words and the least read that each is tied to there, by part of the words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, code, root in _tied_blocks(batches, k, stranded):
            code = mixed(code, 2 * k)
            order = np.argsort(code)
            code, root = code[order], root[order]
            cuts = [x for x in _cut(code, size) if not within or within[0] <= x[0] < within[1]]
            yield packed_batch([(p, encode_sorted(code[a:b] - np.uint64(p * size)), encode_ids(root[a:b])) for p, a, b in cuts], "part int, words binary, roots binary")

    return reads.select("read_id", "seq").mapInArrow(run, "part int, words binary, roots binary")


def tie_words(table: pa.Table) -> pa.Table:
    """TIES of a part: reads that share a word of it, each with the least of its kind."""
    code = np.concatenate([decode_sorted(x) for x in table["words"].to_pylist()])
    root = np.concatenate([decode_ids(x) for x in table["roots"].to_pylist()])
    order = np.argsort(code)
    code, root = code[order], root[order]
    at = np.flatnonzero((code[1:] == code[:-1]) & (root[1:] != root[:-1]))
    nodes, roots = _forest(root[at], root[at + 1])
    return pa.Table.from_batches([packed_batch([(table["part"][0].as_py(), encode_ids(nodes), encode_ids(roots))] if len(nodes) else [], TIES)])


def join_ties(table: pa.Table) -> pa.Table:
    """src, dst of the TIES of several parts: no more than their reads."""
    found = [np.concatenate([decode_ids(x) for x in table[c].to_pylist()]) for c in ("nodes", "roots")]
    nodes, roots = _forest(*found)
    return pa.table({"src": roots, "dst": nodes})


def graph_components(reads: DataFrame, k: int, store: Callable[[DataFrame], DataFrame], stranded: bool = False) -> DataFrame:
    """read_id, component: reads that share words, directly or over others, have the same component.

    Reads are tied by words where they are, then where the words of a part meet, then over some parts; only the least
    read of each kind goes on, so what is left for the rounds is a row for a read and group of parts at most.
    """
    own = store(reads.filter("read_id IS NOT NULL").select("read_id", "seq"))
    _, part_bits, size = layout(own, k)
    found, ties = store(block_roots(own, k, stranded)), None
    for within in spans(2**part_bits, max(1, min(MOST_PASSES, table_bytes(own) // PASS_BYTES))):
        own_ties = store(word_roots(own, k, stranded, size, within).groupBy("part").applyInArrow(tie_words, TIES))
        ties = own_ties if ties is None else ties.unionByName(own_ties)
    every = store(found.groupBy("read_id").agg(F.min("root").alias("root"), F.max("root").alias("_top")))
    discard(own, found)
    again = every.filter("root <> _top").select(F.col("root").alias("src"), F.col("_top").alias("dst"))  # ids of several rows
    fewer = ties.withColumn("part", F.floor(F.col("part") / JOINED).cast("int")).groupBy("part").applyInArrow(join_ties, "src long, dst long")
    labels = connected_components(fewer.unionByName(again), store)
    return every.join(labels, F.col("root") == F.col("node"), "left").select("read_id", F.coalesce("component", "root").alias("component"))


def containment(reads: DataFrame, passages: DataFrame, k: int = 22) -> DataFrame:
    """doc_id, contig_id, shared, share: how many of a passage's distinct words a text holds.

    `reads` cut from texts carry the text in their id; `passages` are (contig_id, seq). The passages' words are a
    bounded set and are broadcast by size only.
    """
    own = explode_kmers(passages.select(F.col("contig_id").alias("read_id"), "seq"), k).select(F.col("read_id").alias("contig_id"), "kmer").distinct()
    sizes = own.groupBy("contig_id").agg(F.count("*").alias("n"))
    doc = text_of(F.col("read_id"))
    hits = explode_kmers(reads, k).select(doc.alias("doc_id"), "kmer").join(own, "kmer").distinct()
    shared = hits.groupBy("doc_id", "contig_id").agg(F.count("*").alias("shared"))
    return shared.join(sizes, "contig_id").select("doc_id", "contig_id", "shared", F.round(F.col("shared") / F.col("n"), 6).alias("share"))


def assembly_proxy(reads: DataFrame, genome: DataFrame, k: int = 22) -> DataFrame:
    """Share of the genome's words that the reads still hold, and of the reads' adjacent word pairs that it has not.

    The first stands for completeness, the second for misassembly.
    """
    contigs = genome.select(F.col("contig_id").alias("read_id"), "seq")
    truth, own = explode_kmers(contigs, k).select("kmer").distinct(), explode_kmers(reads, k).select("kmer").distinct()
    pairs = explode_kmers(reads, k + 1).select("kmer").distinct()
    true_pairs = explode_kmers(contigs, k + 1).select("kmer").distinct()
    a = truth.join(own.withColumn("_h", F.lit(1)), "kmer", "left").agg(F.count("*").alias("n_true"), F.count("_h").alias("n_recovered"))
    b = pairs.join(true_pairs.withColumn("_h", F.lit(1)), "kmer", "left").agg(F.count("*").alias("n_pairs"), (F.count("*") - F.count("_h")).alias("n_chimeric"))
    both = a.withColumn("_j", F.lit(1)).join(b.withColumn("_j", F.lit(1)), "_j").drop("_j")
    return both.select("*", F.round(F.col("n_recovered") / F.col("n_true"), 6).alias("recovered"), F.round(F.col("n_chimeric") / F.col("n_pairs"), 6).alias("chimeric"))


def unitigs(reads: DataFrame, k: int, store: Callable[[DataFrame], DataFrame], min_count: int = 1) -> DataFrame:
    """unitig, n_kmers, n_bases: maximal runs of words with one neighbour on either side (strands told apart).

    Inner edges join words whose only successor has no other predecessor; the runs are the components of those.
    """
    counts = explode_kmers(reads, k, stranded=True).groupBy("kmer").agg(F.count("*").alias("c")).filter(F.col("c") >= min_count).select("kmer")
    mask = F.lit(4 ** (k - 1) - 1).cast("long")
    nodes = store(counts.select("kmer", F.shiftrightunsigned("kmer", 2).alias("head"), F.col("kmer").bitwiseAND(mask).alias("tail")))
    ins = nodes.groupBy(F.col("head").alias("at")).agg(F.count("*").alias("n_out"), F.min("kmer").alias("next"))
    outs = nodes.groupBy(F.col("tail").alias("at")).agg(F.count("*").alias("n_in"), F.min("kmer").alias("prev"))
    edges = ins.join(outs, "at").filter("n_in = 1 AND n_out = 1 AND next <> prev").select(F.col("prev").alias("src"), F.col("next").alias("dst"))
    labels = connected_components(edges, store)
    runs = nodes.join(labels, F.col("kmer") == F.col("node"), "left").groupBy(F.coalesce("component", "kmer").alias("unitig")).agg(F.count("*").alias("n_kmers"))
    return runs.withColumn("n_bases", F.col("n_kmers") + k - 1)


def n50(lengths: DataFrame, column: str = "n_bases") -> int:
    """The length such that pieces of at least it hold half of all bases; from the counts by length."""
    rows = lengths.groupBy(column).agg(F.count("*").alias("n")).orderBy(F.desc(column)).collect()  # a row per length
    half, seen = sum(r[0] * r["n"] for r in rows) / 2, 0
    for r in rows:
        seen += r[0] * r["n"]
        if seen >= half:
            return r[0]
    return 0
