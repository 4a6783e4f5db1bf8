"""The corpus pipeline: quality, near duplicates, contamination, mixture, shards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from roundmm.llm import decontam, mixing, neardup, quality, sharding
from roundmm.llm.common import remainder, stored, table
from roundmm.ship import shipped

SHARDS = 40


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality model accepts. Null and empty texts are scored as empty ones; an empty table stays empty."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"), remainder(5) != 0)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the smallest id. Documents without words, and null ids, stay."""
    return neardup.keep_one(docs)


def without_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no region within the edit budget of a benchmark item."""
    return decontam.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def target_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated by Poisson counts, in a global random order; copies keep their id."""
    return mixing.replicated(docs)


def shard_plan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shard and slot of every row that the mixture holds."""
    return sharding.stratified_shards(docs, SHARDS)


STAGES = [
    ("quality classifier", shipped(good_documents)),
    ("minhash near-dedup", shipped(one_of_each_group)),
    ("benchmark decontamination", shipped(without_benchmarks)),
    ("mixing sources to target weights", shipped(target_mixture)),
    ("sharding", shipped(shard_plan)),
]

#: A fitted classifier isn't SQL; the pipeline is tested against its operators' brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
