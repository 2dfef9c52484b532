"""A training corpus from raw documents: classify, identify language, drop near copies, mix sources, encode.

Each stage takes (spark, docs, sf_dir), works on everything its predecessor
kept and returns a DataFrame, which is written as Parquet and read again as the
next stage's documents. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedlake.llm import language_id, mixing, near_copies, piece_codec, quality_classifier
from fedlake.llm.queries import vocabulary
from fedlake.llm.runtime import ensure_checkpoint_dir, table

#: A language is accepted at this posterior probability.
LANGUAGE_SCORE = 0.5
ORACLE_SQL = None


def classify_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose probability of the top grade reaches the classifier's tail stay."""
    model = quality_classifier.fit(docs, table(spark, sf_dir, "labels"))
    return quality_classifier.select(docs, model)


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the learned languages stay."""
    model = language_id.fit(docs.where(~language_id.held_out(F.col("doc_id"))).select("text", "lang"), vocabulary().pieces)
    return language_id.select(docs, model, LANGUAGE_SCORE)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of linked near copies stays."""
    return near_copies.one_per_group(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix of sources takes it."""
    return mixing.apply_mix(docs)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The corpus as piece ids with digests of ids and of the text decoded from them."""
    return piece_codec.encode_digests(docs, vocabulary(), with_ids=True)


STAGES = [
    ("quality_classifier", classify_quality),
    ("language_id", identify_language),
    ("simhash_near_dedup", drop_near_copies),
    ("source_mix", mix_sources),
    ("piece_codec", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what passes between them lies in the shared checkpoint folder until the next stage is written."""
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before is not None:  # what the next stage has replaced
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(before)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        before = f"{folder}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
