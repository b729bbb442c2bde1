"""A corpus pipeline: quality, line dedup, near-dedup, substring dedup, packing; each stage is written and read again."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from signgraph.llm import lines, packing, quality, simhash, suffix
from signgraph.llm.common import settle

PASSAGE = 240


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the byte network rejects go."""
    return quality.keep_good(docs, quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that match an earlier line go."""
    return lines.without_repeats(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similar texts stays (five words, 0.8)."""
    return simhash.one_of_each(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Strings of PASSAGE bytes that stand twice go: passages of over 50 words are longer, also in the languages of short words."""
    return suffix.without_repeats(docs, PASSAGE)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with their sequences."""
    import public_tokenizers

    return packing.packed(packing.pieces(docs, str(public_tokenizers.path("byte_bpe_50k.json"))))


STAGES = [("quality", quality_stage), ("lines", line_stage), ("near_duplicates", near_stage), ("substrings", substring_stage), ("packing", packing_stage)]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        df = settle(stage(spark, df, sf_dir), f"stage-{name}")
    return df
