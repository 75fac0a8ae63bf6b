"""Registered queries of the training-data operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .packing import harmonic_packing

    return harmonic_packing(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def _every_50th(vectors: DataFrame) -> DataFrame:
    return vectors.filter(F.pmod("vec_id", F.lit(50)) == 0)


def op2_kmeans_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .kmeans_tree import nearest

    vectors = _table(spark, sf_dir, "embeddings")
    return nearest(vectors, _every_50th(vectors))


def op3_size_tiered_compaction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .compaction import compact_documents

    return compact_documents(_table(spark, sf_dir, "documents"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .line_dedup import line_dedup

    out = line_dedup(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import THRESHOLD, fit, score_documents

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    remainder = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4))
    held_out = F.coalesce(remainder == 2, F.lit(False))
    model = fit(docs, _table(spark, sf_dir, "labels").filter(~held_out))
    out = score_documents(docs, model)
    return out.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_ngram_links(spark, sf_dir).drop("n_links")  # the columns that the SQL states


def op6_ngram_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ngram_join import ngram_join

    return ngram_join(_table(spark, sf_dir, "documents"))


def op7_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_array_dedup import repeated_passages

    return repeated_passages(_table(spark, sf_dir, "documents"))


def op8_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ball_tree import exact_top_k

    vectors = _table(spark, sf_dir, "embeddings")
    return exact_top_k(vectors, _every_50th(vectors))


def op9_mixing_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix_sources

    return mix_sources(_table(spark, sf_dir, "documents"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import substring_dedup

    return substring_dedup(_table(spark, sf_dir, "documents")).drop("kept_text")


OP4_SQL = """
WITH lines AS (
  SELECT doc_id, i, line, trim(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS k
  FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents)
), held AS (
  SELECT k, max(doc_id) AS m FROM lines WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3
), marked AS (
  SELECT l.doc_id, l.i, l.line, (h.k IS NOT NULL AND l.doc_id <> h.m) AS gone FROM lines l LEFT JOIN held h ON l.k = h.k
)
SELECT doc_id, count(*)::BIGINT AS n_lines, count_if(gone)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""


OP8_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0
), ranked AS (
  SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM scored
)
SELECT * FROM ranked WHERE rank <= 5
"""


_WORDS = r"list_filter(regexp_split_to_array({0}, '[\x20\x09-\x0D]+'), lambda x: x <> '')"
_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

OP6_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format(f"translate(coalesce(text, ''), '{_UP}', '{_LOW}')")} AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(list_slice(ws, i, i + 4), ' ') AS g
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM w WHERE len(ws) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pairs AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
links AS (SELECT x, y FROM pairs JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * k >= 75 * (p.n + q.n - k)),
sides AS (SELECT x, y FROM links UNION SELECT y, x FROM links),
reach AS (SELECT doc_id, doc_id AS c FROM documents UNION SELECT r.doc_id, b.y FROM reach r JOIN sides b ON b.x = r.c)
SELECT r.doc_id, any_value(coalesce(n.n, 0)) AS n_shingles, min(r.c) AS component_id FROM reach r LEFT JOIN n ON n.doc_id = r.doc_id GROUP BY r.doc_id
"""

_WINDOWS = f"""w AS (SELECT doc_id, {_WORDS.format("coalesce(text, '')")} AS ws FROM documents),
win AS (SELECT doc_id, s, array_to_string(list_slice(ws, s, s + 49), ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS s FROM w)),
held AS (SELECT k, min(doc_id) AS lo, max(doc_id) AS hi FROM win GROUP BY k)"""

OP7_SQL = f"""
WITH {_WINDOWS},
marked AS (SELECT doc_id, s, lo FROM win JOIN held USING (k) WHERE lo < hi),
runs AS (SELECT *, CASE WHEN s <= lag(s) OVER (PARTITION BY doc_id ORDER BY s) + 50 THEN 0 ELSE 1 END AS new FROM marked),
spans AS (SELECT *, sum(new) OVER (PARTITION BY doc_id ORDER BY s ROWS UNBOUNDED PRECEDING) AS span FROM runs)
SELECT doc_id, min(s) - 1 AS start, max(s) + 50 - min(s) AS length, min(lo) AS first_doc, any_value(len(ws)) AS n_words FROM spans JOIN w USING (doc_id) GROUP BY doc_id, span
"""

OP10_SQL = f"""
WITH {_WINDOWS},
gone AS (SELECT DISTINCT doc_id, s + i AS p FROM (SELECT doc_id, s FROM win JOIN held USING (k) WHERE lo < doc_id), range(0, 50) t(i)),
placed AS (SELECT doc_id, unnest(ws) AS x, generate_subscripts(ws, 1) AS p FROM w),
left_over AS (SELECT a.doc_id, count(*) AS n, count(g.p) AS n_gone, string_agg(a.x, ' ' ORDER BY a.p) FILTER (g.p IS NULL) AS kept FROM placed a LEFT JOIN gone g ON g.doc_id = a.doc_id AND g.p = a.p GROUP BY a.doc_id)
SELECT w.doc_id, coalesce(n, 0) AS n_words, coalesce(n_gone, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM w LEFT JOIN left_over l ON l.doc_id = w.doc_id
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_harmonic_packing, op2_kmeans_tree, op3_size_tiered_compaction, op4_line_dedup, op5_toxicity, op6_ngram_join, op6_ngram_links, op7_suffix_array_dedup, op8_exact_top_k, op9_mixing_sources, op10_substring_dedup)}


def oracle_sql() -> dict[str, str]:
    return {"op4_line_dedup": OP4_SQL, "op6_ngram_join": OP6_SQL, "op7_suffix_array_dedup": OP7_SQL, "op8_exact_top_k": OP8_SQL, "op10_substring_dedup": OP10_SQL}
