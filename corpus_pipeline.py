"""A pipeline over ``documents``: quality, near duplicates, repeated passages, benchmark leaks, mixing.

Each stage takes all that its predecessor kept; between stages the rows are written as Parquet and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from chaincores.llm import decontaminate, mixing, neardup, quality, suffixes
from chaincores.llm.common import table
from chaincores.session import materialise

#: Bytes of a passage that counts as repeated: somewhat less than fifty words take.
PASSAGE = 240


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal quality model doesn't reject."""
    return quality.select(docs, table(spark, sf_dir, "labels"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the smallest id, of each group linked by five-word shingles at a similarity of 0.8 or more."""
    return neardup.keep_one(docs)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages that occur more than once."""
    return suffixes.cut_repeats(docs, PASSAGE)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of ten words (or whole shorter item) of the benchmark."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark").select("item_id", "text"), min_words=1)


def mix_to_targets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them."""
    return mixing.mix(docs)


STAGES = [("quality", keep_quality), ("near_duplicates", drop_near_duplicates), ("repeats", cut_repeated_passages), ("benchmark", drop_benchmark_leaks), ("mix", mix_to_targets)]
#: Trained models and suffix sorting are beyond SQL; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return docs
