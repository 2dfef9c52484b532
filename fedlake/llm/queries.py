"""The ``opN_<name>`` queries of the text operators over their whole tables, and their SQL where it exists."""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedlake.llm import chat_format, language_id, license_scan, lm_scoring, mixing, piece_codec, quality_classifier, quality_rules, simhash, vector_join
from fedlake.llm.runtime import table

VOCABULARY = "piece_bpe_32k.model"


@lru_cache(maxsize=2)
def vocabulary(path: str | None = None) -> piece_codec.Vocabulary:
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(VOCABULARY)
    return piece_codec.Vocabulary.load(path)


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.train_and_score(table(spark, sf_dir, "documents"))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_documents(table(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.train_and_predict(table(spark, sf_dir, "documents"), vocabulary().pieces)


def op4_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.encode_digests(table(spark, sf_dir, "documents"), vocabulary())


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(table(spark, sf_dir, "documents"))


def op6_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(table(spark, sf_dir, "documents"))


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_classifier.score(docs, quality_classifier.fit(docs, table(spark, sf_dir, "labels")))


def op8_vector_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_join.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_groups(table(spark, sf_dir, "documents"))


def op10_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format.chat_digests(chat_format.with_probe(table(spark, sf_dir, "conversations")))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_lm_scoring": op1_lm_scoring,
        "op2_license_scan": op2_license_scan,
        "op3_language_id": op3_language_id,
        "op4_piece_codec": op4_piece_codec,
        "op5_quality_rules": op5_quality_rules,
        "op6_source_mix": op6_source_mix,
        "op7_quality_classifier": op7_quality_classifier,
        "op8_vector_join": op8_vector_join,
        "op9_simhash": op9_simhash,
        "op10_chat_format": op10_chat_format,
    }


def oracle_sql() -> dict[str, str]:
    return {"op6_source_mix": mixing.oracle_sql(), "op8_vector_join": vector_join.oracle_sql(), "op10_chat_format": chat_format.oracle_sql()}
