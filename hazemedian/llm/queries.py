"""The registered queries of the corpus operators: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .chunks import repeated_passages
from .jaccard import linked_components
from .langid import languages
from .lines import line_components
from .mixing import schedule
from .syncmers import fingerprints
from .tiling import contaminated_pairs
from .token_files import token_file_digests
from .tokens import count_tokens
from .toxicity import toxicity


def _table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated_pairs(_table(spark, sf_dir, "documents", "doc_id", "text"), _table(spark, sf_dir, "benchmark", "item_id", "text"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(_table(spark, sf_dir, "documents", "doc_id", "text"), _table(spark, sf_dir, "labels", "doc_id", "toxic"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_passages(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linked_components(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return languages(_table(spark, sf_dir, "documents", "doc_id", "text", "lang"))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_file_digests(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_components(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return schedule(_table(spark, sf_dir, "documents", "doc_id", "text", "source"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(_table(spark, sf_dir, "documents", "doc_id", "text"))


QUERIES = {
    f.__name__: f
    for f in (op1_decontamination, op2_toxicity, op3_substring_dedup, op4_ngram_jaccard, op5_language_id, op6_fingerprints, op7_token_files, op8_line_dedup, op9_mixing, op10_token_counts)
}
#: The join on all shared shingles, and the closure of its links.  Trained models, rolling hashes, minimum hashes and
#: tokenizers are out of SQL's reach; their tests are brute force.
SQL: dict[str, str] = {
    "op4_ngram_jaccard": r"""WITH RECURSIVE
 words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
 sets AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_distinct([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, len(w) - 3)]) END AS s FROM words),
 sizes AS (SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM sets),
 items AS (SELECT doc_id, unnest(s) AS item FROM sets),
 shared AS (SELECT doc_id, item FROM items WHERE item IN (SELECT item FROM items GROUP BY item HAVING count(*) > 1)),
 met AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM shared a JOIN shared b USING (item) WHERE a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
 links AS (SELECT a, b FROM met JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
 reach AS (SELECT doc_id AS a, doc_id AS b FROM sizes UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a)
 SELECT s.doc_id, s.n AS n_shingles, r.c AS component_id, coalesce(l.n, 0) AS n_links FROM sizes s
 JOIN (SELECT a, min(b) AS c FROM reach GROUP BY a) r ON r.a = s.doc_id LEFT JOIN (SELECT a, count(*) AS n FROM links GROUP BY a) l ON l.a = s.doc_id""",
}
