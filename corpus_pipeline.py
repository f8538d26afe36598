"""The corpus pipeline: toxic documents go, one of each group of near copies stays, contaminated documents go,
sources are mixed to target weights, and the mixture is written as token-ID files and read back.

The first stage gives every row a row_key, by which later stages name rows, so that null and repeated doc_ids are rows
like others; the mixing stage takes it off again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hazemedian.llm.common import ROW_KEY, Scratch, keyed, narrow
from hazemedian.llm.jaccard import ngram_components
from hazemedian.llm.mixing import mixed
from hazemedian.llm.tiling import contaminated_pairs
from hazemedian.llm.token_files import token_file_digests
from hazemedian.llm.toxicity import score_column, train


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """`docs` without the rows of `gone(row_key)`."""
    return docs.join(narrow(Scratch(docs.sparkSession).keep(gone.select(ROW_KEY).distinct(), "gone")), ROW_KEY, "left_anti").select(docs.columns)


def _by_key(docs: DataFrame) -> DataFrame:
    """The texts of `docs` with the row's key as their doc_id."""
    return docs.select(F.col(ROW_KEY).alias("doc_id"), "text")


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the rows whose text scores below 0.5, and gives them a row_key; null and empty texts stay; without usable labels all stay."""
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    silent = F.coalesce(F.length("text"), F.lit(0)) == 0
    return docs.where(silent | (score_column(model, F.col("text"), spark) < 0.5)).withColumn(ROW_KEY, F.monotonically_increasing_id())


def near_copies_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the row of the smallest doc_id (null last, then by row_key) of each component of near copies; empty texts stand alone and stay."""
    docs, scratch = keyed(docs), Scratch(spark)
    parts = scratch.keep(ngram_components(_by_key(docs)).select(F.col("doc_id").alias(ROW_KEY), "component_id"), "parts")
    groups = parts.join(parts.where(F.col("component_id") != F.col(ROW_KEY)).select("component_id").distinct(), "component_id", "left_semi")
    groups = scratch.keep(groups.join(docs.select(ROW_KEY, "doc_id"), ROW_KEY), "groups")
    first = groups.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", ROW_KEY)).alias("first"))
    return _without(docs, groups.join(first, "component_id").where(F.col(ROW_KEY) != F.col(f"first.{ROW_KEY}")))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents that cover no benchmark item by half or more."""
    docs = keyed(docs)
    return _without(docs, contaminated_pairs(_by_key(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(F.col("doc_id").alias(ROW_KEY)))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as its source's weight asks for, at least once; rows with null and repeated doc_ids too."""
    return mixed(docs).drop(ROW_KEY)


def token_files_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture's token files, read back: doc_id, start, n_tokens, ids_crc32 of each taken document."""
    return token_file_digests(docs)


STAGES = [
    ("toxicity", toxicity_stage),
    ("near copies", near_copies_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
    ("token files", token_files_stage),
]

#: A trained classifier and a tokenizer are out of SQL's reach.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.keep(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
