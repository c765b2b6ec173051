"""Queries of this subpackage over the given tables, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import hamming, minhash, mixing, packing, pfp, pii, secrets, sharding, simhash, toxicity
from .common import documents

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pfp.remove_repeats(documents(spark, sf_dir), length=400, words=50, with_text=True)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return toxicity.score(docs, toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir))


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), tokenizer_path())


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(documents(spark, sf_dir), 24)


def op6_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hamming.top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), 10, 20)


def op7_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find_secrets(documents(spark, sf_dir))


def op8_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace(documents(spark, sf_dir))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


def op10_minhash_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.compare_edited(documents(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (
    op1_suffix_dedup, op2_toxicity, op3_mix_sources, op4_best_fit_packing, op5_sharding, op6_exact_top_k, op7_secrets, op8_pii_surrogates, op9_simhash, op10_minhash_fingerprints, pipeline)}
ORACLES: dict[str, str] = {}
