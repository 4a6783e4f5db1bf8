"""The thin contract queries ``opN_<name>`` over whole tables; each gets its rows through its operator."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.llm import quality, toxicity
from roundmm.llm.common import remainder, table
from roundmm.llm.decontam import contamination
from roundmm.llm.licences import licence_report
from roundmm.llm.linededup import line_report
from roundmm.llm.media import media_report
from roundmm.llm.mixing import replicated
from roundmm.llm.neardup import near_duplicates
from roundmm.llm.sharding import stratified_shards
from roundmm.llm.urls import judged


def op1_noisy_channel(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels, remainder(3) != 1)
    scored = toxicity.scored(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", (remainder(3) == 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op2_stratified_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = stratified_shards(table(spark, sf_dir, "documents"), shards=40)
    return plan.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source"
    )


def op6_poisson_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = replicated(table(spark, sf_dir, "documents").select("doc_id", "source", "text"), report=True)
    return mixed.select("doc_id", "source", F.col("copy").cast("int").alias("copy"), F.col("n_copies").cast("int").alias("n_copies"), F.round("rate", 9).alias("rate"), "shuffle_key")


def op3_qgram_lemma(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_licence_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licence_report(table(spark, sf_dir, "documents"))


def op5_segment_edit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_report(table(spark, sf_dir, "documents"))


def op7_payload_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_report(table(spark, sf_dir, "documents"))


def op8_nbsvm_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = quality.train(docs, labels, remainder(5) != 0)
    scored = quality.scored(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", (remainder(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op9_url_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "pages"))


def op10_chosen_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_noisy_channel": op1_noisy_channel,
    "op2_stratified_shards": op2_stratified_shards,
    "op3_qgram_lemma": op3_qgram_lemma,
    "op4_licence_votes": op4_licence_votes,
    "op5_segment_edit": op5_segment_edit,
    "op6_poisson_mix": op6_poisson_mix,
    "op7_payload_chunks": op7_payload_chunks,
    "op8_nbsvm_quality": op8_nbsvm_quality,
    "op9_url_terms": op9_url_terms,
    "op10_chosen_path": op10_chosen_path,
}
