"""The registered queries of the training-data operators, with their production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, langid, linededup, lm, packing, pieces, quality, rules, simhash, suffixdedup
from .common import held_out


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"), vocabulary("byte_bpe_50k.tiktoken"))


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    out = quality.score(docs, quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return out.select("doc_id", held_out(5).alias("held_out"), "score", F.when(F.col("score") >= 0.3, 1).otherwise(0).alias("predicted"), "n_passages", "top_passage")


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.codec_report(documents(spark, sf_dir), vocabulary("piece_bpe_32k.model"))


def op4_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.dedup_lines(documents(spark, sf_dir))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


def op6_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return lm.score(docs, lm.fit(docs))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    forest, cut = rules.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return rules.judge(docs, forest, cut)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.detect(documents(spark, sf_dir)).select("doc_id", held_out(5).alias("held_out"), "lang_pred", "score")


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixdedup.remove_repeats(documents(spark, sf_dir))


def op10_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), lambda i: i % 20 == 0)


OP5_SQL = """
WITH lines AS (
  SELECT doc_id, i, string_split(coalesce(text, ''), chr(10))[i] AS line
  FROM documents, LATERAL (SELECT unnest(range(1, len(string_split(coalesce(text, ''), chr(10))) + 1)) AS i)
), keyed AS (
  SELECT doc_id, i, line, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), firsts AS (SELECT k, min(doc_id) AS first_id FROM keyed WHERE length(k) >= 10 GROUP BY k)
SELECT d.doc_id, count(*)::BIGINT AS n_lines,
  count(*) FILTER (WHERE f.first_id < d.doc_id)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(d.line, chr(10) ORDER BY d.i) FILTER (WHERE f.first_id IS NULL OR f.first_id >= d.doc_id), '')) AS kept_sha256
FROM keyed d LEFT JOIN firsts f ON d.k = f.k AND length(d.k) >= 10
GROUP BY d.doc_id
"""

# a text's bytes as hex digits, cut into blocks of 200 bytes: a 200-byte string lies in a block and the next
OP9_SQL = """
WITH docs AS (
  SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents
), blocks AS (
  SELECT r, b, blocks[b] || coalesce(blocks[b + 1], '') AS pair, length(blocks[b]) // 2 AS n
  FROM (SELECT r, regexp_extract_all(x, '.{1,400}') AS blocks FROM docs), LATERAL (SELECT unnest(range(1, len(blocks) + 1)) AS b)
), strings AS (
  SELECT r, 200 * (b - 1) + o AS p, md5_number(substr(pair, 2 * o + 1, 400)) AS k
  FROM blocks, LATERAL (SELECT unnest(range(0, n)) AS o) WHERE length(pair) >= 2 * o + 400
), twice AS (SELECT k FROM strings GROUP BY k HAVING count(*) > 1),
starts AS (
  SELECT r, p, lag(p) OVER (PARTITION BY r ORDER BY p) AS before, lead(p) OVER (PARTITION BY r ORDER BY p) AS after
  FROM strings JOIN twice USING (k)
), spans AS (
  SELECT r, min(p) AS a, max(p) + 200 AS z
  FROM (SELECT r, p, sum(CASE WHEN before IS NULL OR p > before + 200 THEN 1 ELSE 0 END) OVER (PARTITION BY r ORDER BY p) AS s FROM starts)
  GROUP BY r, s
), kept AS (
  SELECT d.r, string_agg(substr(d.x, 2 * e.a + 1, 2 * (coalesce(e.z, length(d.x) // 2) - e.a)), '' ORDER BY e.a) AS x
  FROM docs d JOIN (
    SELECT r, z AS a, lead(a) OVER (PARTITION BY r ORDER BY a) AS z FROM spans
    UNION ALL SELECT r, 0, min(a) FROM spans GROUP BY r
  ) e ON d.r = e.r GROUP BY d.r
)
SELECT d.doc_id, (length(d.x) // 2)::BIGINT AS n_bytes, coalesce(s.n, 0)::BIGINT AS n_removed, coalesce(s.c, 0)::BIGINT AS n_spans,
  sha256(unhex(coalesce(k.x, d.x))) AS kept_sha256
FROM docs d LEFT JOIN (SELECT r, sum(z - a) AS n, count(*) AS c FROM spans GROUP BY r) s ON d.r = s.r LEFT JOIN kept k ON d.r = k.r
"""

QUERIES = {
    "op1_best_fit_packing": op1_best_fit_packing,
    "op2_quality_classifier": op2_quality_classifier,
    "op3_sentencepiece": op3_sentencepiece,
    "op4_simhash_dedup": op4_simhash_dedup,
    "op5_line_dedup": op5_line_dedup,
    "op6_lm_scoring": op6_lm_scoring,
    "op7_quality_rules": op7_quality_rules,
    "op8_language_id": op8_language_id,
    "op9_suffix_dedup": op9_suffix_dedup,
    "op10_nearest_neighbours": op10_nearest_neighbours,
}
SQL = {"op5_line_dedup": OP5_SQL, "op9_suffix_dedup": OP9_SQL}
