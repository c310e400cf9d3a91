"""The operators' queries over whole tables, and DuckDB SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import cotraining, decontamination, hilbert, hmm, line_dedup, packing, quality_rules, secrets, simhash, toxicity
from .common import documents


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir))


def op2_crf_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find_secrets(documents(spark, sf_dir))


def op3_line_first_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(documents(spark, sf_dir))


def op4_cotraining_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cotraining.score(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_template_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.drop_recurring_lines(documents(spark, sf_dir), report=True)


def op6_hidden_markov_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hmm.score_documents(documents(spark, sf_dir))


def op7_latent_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_leaks(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op8_ordinal_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op9_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert.shard_documents(documents(spark, sf_dir))


def op10_simhash_bit_sliced(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


QUERIES = {
    f.__name__: f
    for f in (
        op1_best_fit_packing,
        op2_crf_secrets,
        op3_line_first_rules,
        op4_cotraining_quality,
        op5_template_line_dedup,
        op6_hidden_markov_scores,
        op7_latent_decontamination,
        op8_ordinal_toxicity,
        op9_hilbert_shards,
        op10_simhash_bit_sliced,
    )
}
ORACLES: dict[str, str] = {"op3_line_first_rules": quality_rules.oracle()}
