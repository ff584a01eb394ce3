"""The queries of the corpus operators, each over its whole table, and their SQL where there is some."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relgraph.llm import embeddings, linededup, media, mixing, packing, quality, secrets, simhash, suffix, toxicity
from relgraph.llm.common import table

#: File of the word vocabulary; None asks the installed package of public tokenizers for its place.
WORD_VOCABULARY: str | None = None


def word_vocabulary() -> str:
    if WORD_VOCABULARY:
        return WORD_VOCABULARY
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_gif_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.text_media(table(spark, sf_dir, "documents"))


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), word_vocabulary())


def op5_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.digest(table(spark, sf_dir, "documents"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.repeats(table(spark, sf_dir, "documents"))


def op4_toxicity_fm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_quality_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_duplicates(table(spark, sf_dir, "embeddings"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secrets(table(spark, sf_dir, "documents"))


def op2_hierarchical_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_gif_media, op3_best_fit_packing, op5_simhash_near_dedup, op6_line_dedup, op8_suffix_dedup, op4_toxicity_fm, op10_quality_cnn, op7_embedding_near_dedup, op9_secret_scan, op2_hierarchical_mix)}


def oracle_sql() -> dict[str, str]:
    return {"op2_hierarchical_mix": mixing.mix_sql()}
