"""The queries of this subpackage over the given tables, and SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chroma, html, license, minhash, mixing, ppm, quality, substring, toxicity


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_chroma_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of conversations, rendered as tones (no table holds audio): those of every hundredth conversation in all."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    found = chroma.search(turns, F.struct("conv_id", "turn"), F.col("text"), F.col("conv_id") % 100 == 0, rendered=True)
    named = lambda c: (F.col(f"{c}_id.conv_id").alias(f"{c}_conv_id"), F.col(f"{c}_id.turn").alias(f"{c}_turn"))
    return found.select("id.conv_id", "id.turn", "n_prints", *named("class"), "n_matches", *named("best"), "best_offset", "best_errors")


def op2_minmax_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(documents(spark, sf_dir))


def crc_mod(n: int) -> Column:
    """crc32 of the id as text, modulo n."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def op3_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return html.main_text(pages, html.fit(pages), keep=("url",))


def op4_ppm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.score_documents(documents(spark, sf_dir), crc_mod(7) == 2)


def op7_fuzzy_notices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license.scan(documents(spark, sf_dir)).drop("spans")


def op8_lexicon_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.fit(docs, labels, F.crc32(F.col("id").cast("string").cast("binary")) % 4 != 2)
    return toxicity.score_documents(docs, model).select("doc_id", (crc_mod(4) == 2).alias("held_out"), "score", "predicted")


def op5_pivotal_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "source", "copies")


def op6_quality_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = quality.apply_policy(quality.ledger(documents(spark, sf_dir)))
    base = F.col("failed").bitwiseAND(F.lit(quality.BASE.mask)) != 0
    return book.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), "kept", "failed")


def bpe_digests(docs: DataFrame) -> DataFrame:
    coded = bpe.encode_and_decode(docs, vocabulary_path())
    return coded.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op9_backtracking_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_digests(documents(spark, sf_dir))


def op10_anchor_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring.remove_repeats(documents(spark, sf_dir))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


QUERIES = {
    "op1_chroma_search": op1_chroma_search,
    "op2_minmax_near_duplicates": op2_minmax_near_duplicates,
    "op3_main_text": op3_main_text,
    "op4_ppm_scores": op4_ppm_scores,
    "op5_pivotal_mixing": op5_pivotal_mixing,
    "op6_quality_ledger": op6_quality_ledger,
    "op7_fuzzy_notices": op7_fuzzy_notices,
    "op8_lexicon_toxicity": op8_lexicon_toxicity,
    "op9_backtracking_bpe": op9_backtracking_bpe,
    "op10_anchor_substring_dedup": op10_anchor_substring_dedup,
}

_WORDS = r"""words AS (
  SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w
  FROM documents)"""

SQL = {
    "op6_quality_ledger": f"""
WITH {_WORDS}, places AS (
  SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS p FROM words WHERE len(w) >= 3),
windows AS (
  SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, w[p], w[p + 1], w[p + 2]) AS n FROM places),
covered AS (
  SELECT doc_id, count(DISTINCT q) AS n FROM (SELECT doc_id, unnest([p, p + 1, p + 2]) AS q FROM windows WHERE n > 1) GROUP BY doc_id),
measured AS (
  SELECT d.doc_id, len(w) AS n_words,
    CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
    CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines,
    coalesce(c.n, 0) AS n_repeat_words
  FROM words d LEFT JOIN covered c USING (doc_id)),
judged AS (
  SELECT *, len(lines) AS n_lines, len(lines) - len(list_distinct(lines)) AS n_dup_lines FROM measured),
bits AS (
  SELECT *, (CASE WHEN n_words < 50 THEN 1 ELSE 0 END) + (CASE WHEN 100 * n_repeat_words > 50 * n_words THEN 2 ELSE 0 END)
    + (CASE WHEN 10 * n_symbols > n_words THEN 4 ELSE 0 END) + (CASE WHEN 2 * n_dup_lines > n_lines THEN 8 ELSE 0 END)
    + (CASE WHEN word_chars > 15 * n_words THEN 16 ELSE 0 END) + (CASE WHEN n_words = 0 THEN 32 ELSE 0 END)
    + (CASE WHEN n_words > 1000000 THEN 64 ELSE 0 END) AS failed FROM judged)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, word_chars, n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines,
  CAST(n_repeat_words AS BIGINT) AS n_repeat_words, failed % 4 <> 0 AS base_failed, failed % 32 = 0 AS kept, CAST(failed AS BIGINT) AS failed
FROM bits""",
    "op10_anchor_substring_dedup": f"""
WITH {_WORDS}, places AS (
  SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS p FROM words WHERE len(w) >= 13),
windows AS (
  SELECT doc_id, p, array_to_string(w[p:p + 12], ' ') AS k FROM places),
judged AS (
  SELECT doc_id, p, doc_id > min(doc_id) OVER (PARTITION BY k) AS gone FROM windows),
removed AS (
  SELECT DISTINCT doc_id, unnest(range(p, p + 13)) AS p FROM judged WHERE gone),
lists AS (
  SELECT doc_id, list(p) AS ps FROM removed GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(len(ps), 0) AS BIGINT) AS n_removed,
  sha256(array_to_string(CASE WHEN ps IS NULL THEN w ELSE list_filter(w, lambda x, i: NOT list_contains(ps, i)) END, ' ')) AS kept_sha256
FROM words d LEFT JOIN lists l USING (doc_id)""",
    "op2_minmax_near_duplicates": r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
places AS (
  SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS p FROM words WHERE len(w) > 0),
shingles AS (
  SELECT DISTINCT doc_id, array_to_string(w[p:p + 4], ' ') AS s FROM places),
sizes AS (
  SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
both_in AS (
  SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS n FROM shingles a JOIN shingles b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (
  SELECT u, v FROM both_in x JOIN sizes a ON a.doc_id = u JOIN sizes b ON b.doc_id = v WHERE 100 * x.n >= 85 * (a.n + b.n - x.n)),
either AS (
  SELECT u, v FROM links UNION ALL SELECT v, u FROM links),
reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.v FROM reach r JOIN either e ON e.u = r.b)
SELECT d.doc_id, CAST(coalesce(s.n, 0) AS BIGINT) AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept
FROM documents d LEFT JOIN sizes s USING (doc_id) JOIN (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a) c USING (doc_id)""",
}
