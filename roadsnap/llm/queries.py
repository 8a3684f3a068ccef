"""One query per operator, over its whole table with production parameters, and SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import exact, fingerprint, lattice, linedup, nearcopy, packing, private, quality, substrings, tokens

#: Rows of one Arrow batch: bounds what a kernel holds at once, whatever the table's size.
BATCH_ROWS = "1000"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_line_dedup(spark, sf_dir):
    return linedup.dedup(table(spark, sf_dir, "documents"))


def op3_quality_classifier(spark, sf_dir):
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_fingerprints(spark, sf_dir):
    return fingerprint.against(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_sentencepiece(spark, sf_dir):
    return lattice.encode(table(spark, sf_dir, "documents"))


def op6_exact_dedup(spark, sf_dir):
    """Texts of src0 are the history; the other sources' texts are looked up in it."""
    return exact.dedup_by_history(table(spark, sf_dir, "documents"), "source = 'src0'")


def op7_suffix_dedup(spark, sf_dir):
    return substrings.dedup(table(spark, sf_dir, "documents"))


def op8_minhash_dedup(spark, sf_dir):
    return nearcopy.dedup(table(spark, sf_dir, "documents"))


def op9_token_codes(spark, sf_dir):
    return tokens.write_codes(table(spark, sf_dir, "documents"))


def op10_private_data(spark, sf_dir):
    return private.redact(table(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_packing, op2_line_dedup, op3_quality_classifier, op4_fingerprints, op5_sentencepiece,
        op6_exact_dedup, op7_suffix_dedup, op8_minhash_dedup, op9_token_codes, op10_private_data,
    )
}

ORACLE_SQL = {
    "op2_line_dedup": """
WITH lines AS (
  SELECT doc_id, unnest(range(len(parts))) AS ln, parts FROM (SELECT doc_id, string_split(text, chr(10)) AS parts FROM documents)),
pairs AS (SELECT doc_id, ln, 2 AS n, parts[ln + 1] AS a, parts[ln + 2] AS b FROM lines WHERE ln + 2 <= len(parts)
  UNION ALL SELECT doc_id, ln, 1, parts[ln + 1], NULL FROM lines WHERE len(regexp_extract_all(parts[ln + 1], '[^\x00-\x20]+')) >= 50),
firsts AS (SELECT doc_id, ln, n, first_value(struct_pack(d := doc_id, l := ln)) OVER (PARTITION BY n, a, b ORDER BY doc_id, ln) AS f FROM pairs),
copies AS (SELECT * FROM firsts WHERE doc_id <> f.d OR ln >= f.l + n),
gone AS (SELECT doc_id, array_agg(DISTINCT g) AS g FROM (SELECT doc_id, unnest(range(ln, ln + n)) AS g FROM copies) GROUP BY doc_id),
src AS (SELECT doc_id, list_sort(array_agg(DISTINCT f.d)) AS s FROM copies GROUP BY doc_id),
cut AS (
  SELECT d.*, coalesce(len(g), 0) AS n_gone, coalesce(s, []::BIGINT[]) AS s, g,
         CASE WHEN g IS NULL THEN text ELSE coalesce(array_to_string(list_transform(list_filter(range(len(string_split(text, chr(10)))), lambda i: NOT list_contains(g, i)), lambda i: string_split(text, chr(10))[i + 1]), chr(10)), '') END AS left_text
  FROM documents d LEFT JOIN gone USING (doc_id) LEFT JOIN src USING (doc_id))
SELECT doc_id, left_text AS text, lang, source, CASE WHEN g IS NULL THEN n_chars ELSE length(left_text) END AS n_chars,
       CAST(n_gone AS INTEGER) AS removed_lines, s AS copied_from FROM cut""",
    "op6_exact_dedup": """
SELECT doc_id, text, lang, source, n_chars FROM (
  SELECT *, row_number() OVER (PARTITION BY text ORDER BY source IS DISTINCT FROM 'src0', doc_id) AS turn FROM documents)
WHERE text IS NULL OR turn = 1""",
    "op7_suffix_dedup": """
WITH w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\\x00-\\x20]+') AS words FROM documents),
win AS (SELECT doc_id, p, md5(array_to_string(words[p + 1 : p + 50], ' ')) AS h FROM (SELECT doc_id, words, unnest(range(len(words) - 49)) AS p FROM w WHERE len(words) >= 50)),
firsts AS (SELECT doc_id, p, min(struct_pack(d := doc_id, p := p)) OVER (PARTITION BY h) AS f FROM win),
copies AS (SELECT doc_id, p FROM firsts WHERE doc_id <> f.d OR p >= f.p + 50)
SELECT doc_id, count(DISTINCT q) AS removed FROM (SELECT doc_id, unnest(range(p, p + 50)) AS q FROM copies) GROUP BY doc_id""",
}
#: The SQL of op7 tells how many words each text loses, which a test compares; the texts themselves are held against brute force.
OP7_REMOVED_SQL = ORACLE_SQL.pop("op7_suffix_dedup")
