"""A corpus pipeline of five stages: each is written as Parquet and read again as the documents of the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.llm import common, langid, lines, mixing, packing, queries, simhash


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told stay; null texts, texts without letters and undecided ones go."""
    return langid.keep_determined(docs, langid.train(docs))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that stay elsewhere are cut; a document that loses all its lines goes.  n_chars follows the new text."""
    d = lines.deduplicate_lines(docs).where((F.col("n_dropped") == 0) | (F.trim(F.replace(F.col("text"), F.lit("\n"), F.lit(""))) != ""))
    return d.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.deduplicate(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, queries.tokenizer_path())


STAGES = [("language ID", language), ("line dedup", line_dedup), ("SimHash near-dedup", near_dedup), ("mixing", mix), ("packing", pack)]

#: SQL cannot express a trained network, MinHash or tokenizers; tests/llm compare the operators with brute force and check what each stage keeps.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs, _ = common.staged(stage(spark, docs, sf_dir), f"stage-{k}")
    return docs
