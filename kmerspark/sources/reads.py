"""Reads (read_id, source, seq) from the given tables and from sequence files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.dna import project_bytes, project_text

READ_LEN = 100
#: The first reads of a text have the ids text id * READS_PER_TEXT + number. Those of longer texts lie in a range of
#: their own, below LATER, by text (32 bits) and number (30 bits).
READS_PER_TEXT = 10_000
LATER, LATER_BITS = -(2**62), 30
#: Likewise for turns of a conversation: conv_id * 100 + turn, and from LATER_TURN for later ones (19 bits).
TURNS, LATER_TURN, LATER_TURN_BITS = 100, -(2**48), 19


def read_id_of(text_id: Column, number: Column) -> Column:
    """A read's id, different for any two reads of any texts; an error where a long has no room for it."""
    number = number.cast("long")
    first = text_id * READS_PER_TEXT + number
    later = F.shiftleft(text_id, LATER_BITS) + (number - READS_PER_TEXT) - 2**62 - 2**61
    room = (text_id >= -(2**31)) & (text_id < 2**31) & (number < READS_PER_TEXT + 2**LATER_BITS)
    refused = F.raise_error(F.concat(F.lit("no read id for text "), text_id.cast("string"), F.lit(", read "), number.cast("string"))).cast("long")
    return F.when(text_id.isNull(), F.lit(None).cast("long")).when(number < READS_PER_TEXT, F.when(text_id >= LATER // READS_PER_TEXT + 1, first).otherwise(refused)).when(room, later).otherwise(refused)


def text_of(read_id: Column) -> Column:
    """The id of the text that a read was cut from."""
    later = F.shiftright(read_id + 2**62 + 2**61, LATER_BITS)
    per = F.lit(READS_PER_TEXT)
    return F.when(read_id < LATER, later).otherwise(F.call_function("div", read_id - F.pmod(read_id, per), per))


def cut_reads(df: DataFrame, id_col: str, seq: Column, source: Column | None = None, read_len: int = READ_LEN, stride: int | None = None) -> DataFrame:
    """Substrings of `read_len` bases at each stride; an empty sequence gives no read."""
    stride = stride or read_len
    base = df.select(F.col(id_col).cast("long").alias("_id"), (source if source is not None else F.lit(None).cast("string")).alias("source"), seq.alias("_s")).filter(F.length("_s") > 0)
    at = F.explode(F.sequence(F.lit(0), F.floor((F.length("_s") - 1) / stride).cast("int")))
    cut = base.select("_id", "source", "_s", at.alias("_i"))
    return cut.select(read_id_of(F.col("_id"), F.col("_i")).alias("read_id"), "source", F.substr("_s", F.col("_i") * stride + 1, F.lit(read_len)).alias("seq"))


def cut_texts(df: DataFrame, id_col: str, text: Column, source: Column | None = None, junk: str = "drop", **cut) -> DataFrame:
    """`cut_reads` of projected texts. Reads that neither overlap nor leave gaps are cut from a block's bases as they lie."""
    size = cut.get("read_len", READ_LEN)
    if cut.get("stride") not in (None, size):
        return cut_reads(df, id_col, project_text(text, junk), source, **cut)
    from ..operators.kmers import read_blocks

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, raw, ends in read_blocks(batch, "_text"):
                data, ends = project_bytes(raw, ends, junk)
                first = np.concatenate([[0], ends[:-1]])
                n = -(-(ends - first) // size)
                owner = np.repeat(np.arange(len(n)), n)
                number = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
                offsets = np.append(first[owner] + number * size, len(data)).astype(np.int32)
                seq = pa.StringArray.from_buffers(len(owner), pa.py_buffer(offsets), pa.py_buffer(data))
                own = pa.array(owner)
                yield pa.RecordBatch.from_arrays([rows.column(0).take(own), pa.array(number.astype(np.int32)), rows.column(1).take(own), seq], names=["_id", "_i", "source", "seq"])

    base = df.select(F.col(id_col).cast("long").alias("_id"), (source if source is not None else F.lit(None)).cast("string").alias("source"), text.cast("string").alias("_text"))
    found = base.mapInArrow(run, "_id long, _i int, source string, seq string")
    return found.select(read_id_of(F.col("_id"), F.col("_i")).alias("read_id"), "source", "seq")


def from_documents(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", junk: str = "drop", **cut) -> DataFrame:
    """Reads of texts; only the id, the text and the source are scanned."""
    source = F.col("source") if "source" in df.columns else None
    return cut_texts(df, id_col, F.col(text_col), source, junk, **cut)


def from_pages(df: DataFrame, **cut) -> DataFrame:
    """Reads of web pages, tags and entities taken out."""
    plain = F.regexp_replace(F.regexp_replace(F.col("html"), "<[^>]*>", " "), "&[a-zA-Z#0-9]+;", " ")
    return cut_texts(df, "page_id", plain, F.expr("parse_url(url, 'HOST')"), **cut)


def from_conversations(df: DataFrame, **cut) -> DataFrame:
    """Reads of turns; a turn's id is conv_id * 100 + turn, and one of a range of its own from the hundredth turn on."""
    conv, number = F.col("conv_id").cast("long"), F.col("turn").cast("long")
    room = (conv >= 0) & (conv < 2**28) & (number < TURNS + 2**LATER_TURN_BITS)
    refused = F.raise_error(F.concat(F.lit("no id for turn "), number.cast("string"), F.lit(" of conversation "), conv.cast("string"))).cast("long")
    later = F.when(room, F.shiftleft(conv, LATER_TURN_BITS) + (number - TURNS) + LATER_TURN).otherwise(refused)
    turn = df.withColumn("_turn", F.when(number >= TURNS, later).otherwise(conv * TURNS + number))
    return cut_texts(turn, "_turn", F.col("text"), F.col("role"), **cut)


def genome_of(benchmark: DataFrame) -> DataFrame:
    """contig_id, seq: a reference genome, one contig per item."""
    return benchmark.select(F.col("item_id").alias("contig_id"), project_text(F.col("text")).alias("seq")).filter(F.length("seq") > 0)


def event_bases(event_type: Column) -> Column:
    """The event alphabet: four types as bases, errors and anything else as N."""
    return F.coalesce(F.element_at(F.create_map(*(F.lit(x) for kv in zip(("click", "view", "purchase", "signup"), "ACGT", strict=True) for x in kv)), event_type), F.lit("N"))


def prepare_reads(reads: DataFrame, max_n_frac: float = 0.3, min_len: int = 31) -> DataFrame:
    """Reads with less than the given share of N and at least `min_len` bases."""
    n = F.length("seq")
    return reads.filter((n >= min_len) & (n - F.length(F.replace("seq", F.lit("N"), F.lit(""))) < max_n_frac * n))


def read_fasta(spark: SparkSession, path: str) -> DataFrame:
    """read_id, source (the header), seq from FASTA text; sequences may span lines.

    Records are the pieces between header marks, so a file splits between records and no order of lines is needed.
    """
    pieces = spark.read.option("lineSep", ">").text(path).filter(F.trim("value") != "")
    seq = F.upper(F.regexp_replace(F.regexp_replace("value", r"^[^\n]*(\n|$)", ""), r"\s", ""))
    return pieces.select(F.monotonically_increasing_id().alias("read_id"), F.regexp_extract("value", r"^([^\n]*)", 1).alias("source"), seq.alias("seq"))


def read_fastq(spark: SparkSession, path: str, offset: int = 33) -> DataFrame:
    """read_id, source, seq, qual from four-line FASTQ records; whole files stay together, one task each."""
    files = spark.read.text(path, wholetext=True)
    lines = F.split(F.rtrim("value"), "\n")
    records = files.select(lines.alias("l")).filter(F.size("l") >= 4).select("l", F.explode(F.sequence(F.lit(0), (F.size("l") / 4).cast("int") - 1)).alias("i"))
    line = lambda k: F.element_at("l", F.col("i") * 4 + k)
    qual = F.transform(F.filter(F.split(line(4), ""), lambda c: c != ""), lambda c: (F.ascii(c) - offset).cast("tinyint"))
    return records.select(F.monotonically_increasing_id().alias("read_id"), F.substr(line(1), F.lit(2)).alias("source"), line(2).alias("seq"), qual.alias("qual"))


def read_counts(spark: SparkSession, path: str) -> DataFrame:
    """kmer and cnt from tab-separated text."""
    return spark.read.csv(path, sep="\t", schema="kmer string, cnt long")


def write_counts(counts: DataFrame, path: str) -> None:
    """Dump of counted words as tab-separated text."""
    counts.write.mode("overwrite").csv(path, sep="\t")


def write_fasta(reads: DataFrame, path: str) -> None:
    reads.select(F.concat(F.lit(">"), F.col("read_id").cast("string"), F.lit("\n"), F.col("seq"))).write.mode("overwrite").text(path)


def with_arrival(reads: DataFrame, order: str = "read_id", batches: int = 10) -> DataFrame:
    """A batch number by order of arrival: equal ranges of ids, cut at quantiles, without a global sort."""
    cuts = reads.approxQuantile(order, [i / batches for i in range(1, batches)], 0.001)
    number = sum((F.when(F.col(order) > c, 1).otherwise(0) for c in cuts), F.lit(0))
    return reads.withColumn("batch", number)

