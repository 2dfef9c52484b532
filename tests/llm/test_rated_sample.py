"""The sample of ratings is the first rows by hash, however they are found; scores equal a plain sum of weights."""

import numpy as np
from pyspark.sql import functions as F

from fedlake.llm import quality_classifier as C


def test_sample_is_the_first_by_hash(spark):
    labels = spark.range(5000).select(F.col("id").alias("doc_id"), (F.col("id") % 2).cast("int").alias("quality"), F.lit(0).alias("toxic"))
    want = [r.doc_id for r in labels.orderBy(F.xxhash64("doc_id"), "doc_id").limit(40).collect()]
    assert sorted(r.doc_id for r in C.rated_sample(labels, 40).collect()) == sorted(want)
    assert C.rated_sample(labels, 10_000).count() == 5000 and C.rated_sample(labels.limit(0), 10).count() == 0


def test_scores_equal_plain_sums(spark, folder):
    docs, labels = (spark.read.parquet(f"{folder}/{t}.parquet") for t in ("documents", "labels"))
    model = C.fit(docs, labels)
    weights = dict(zip(model.buckets.tolist(), model.weights.tolist(), strict=True))
    got = {r.doc_id: r for r in C.score(docs, model).collect()}
    for r in docs.collect():
        words = (r.text or "").split()
        buckets = {b for w in set(words) for b in C.token_buckets(w)} | {C.variety_bucket(len(words), len(set(words)))}
        latent = sum(weights.get(b, 0.0) for b in buckets)
        assert abs(got[r.doc_id].latent - latent) < 1e-3
        tails = 1 / (1 + np.exp(-(latent - model.thresholds)))
        assert abs(got[r.doc_id].tail_probability - tails[-1]) < 1e-3 and got[r.doc_id].kept == (got[r.doc_id].tail_probability >= C.TAIL)
