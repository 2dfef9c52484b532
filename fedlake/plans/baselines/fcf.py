"""Federated collaborative filtering: clients solve their own factor, the server steps on item gradients."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import sampling, scoring
from fedlake.plans import data as D
from fedlake.plans import rounds as R

DIM, REG, CONF = 16, 0.1, 40.0


def user_factor(q: np.ndarray, label: np.ndarray, conf: np.ndarray, reg: float = REG) -> np.ndarray:
    """Confidence-weighted ridge regression of a client's labels on its items' factors."""
    weighted = q * conf[:, None]
    return np.linalg.solve(q.T @ weighted + reg * np.eye(q.shape[1]), weighted.T @ label)


def item_gradient(q: np.ndarray, x: np.ndarray, label: np.ndarray, conf: np.ndarray) -> np.ndarray:
    return (conf * (label - q @ x))[:, None] * x[None, :]


def fit(prep: D.Prepared, rounds: int = 5, clients: int = 20, rate: float = 0.01, dim: int = DIM, reg: float = REG, conf: float = CONF, seed: int = 42) -> np.ndarray:
    """Item factors (items by dim) after rounds over training users."""
    train, _ = D.splits(prep)
    ids = train.select("client_id").distinct()
    draw = sampling.draw_fixed(ids, clients, rounds, f"fcf-{seed}")
    packed = train.join(draw.select("client_id").distinct(), "client_id", "left_semi").groupBy("client_id").agg(F.sort_array(F.collect_list(F.struct("item_no", "label", "stars"))).alias("items")).join(draw, "client_id").persist()
    spark = packed.sparkSession
    q = np.random.default_rng(seed).standard_normal((prep.n_items, dim)) * 0.1
    for r in range(rounds):
        shared = spark.sparkContext.broadcast(q)

        def kernel(row, shared=shared):
            i, y = np.array([x["item_no"] for x in row["items"]]), np.array([x["label"] for x in row["items"]], float)
            c, mine = 1 + conf * np.array([x["stars"] for x in row["items"]], float), shared.value[i]
            x = user_factor(mine, y, c, reg)
            return R.row_places(i, dim), (item_gradient(mine, x, y, c) - reg * mine).ravel()

        total, _, _ = R.summed_deltas(packed.where(F.col("round") == r), kernel, q.size)
        q = q + rate * total.reshape(q.shape) / clients
        shared.destroy()
    packed.unpersist()
    return q


def rank(prep: D.Prepared, q: np.ndarray, reg: float = REG, conf: float = CONF) -> DataFrame:
    """Ranks of test users' positives: each solves its factor on its tuning half."""
    test = D.splits(prep)[1].select("client_id", F.col("item_no").alias("item_id"), "label", "stars", "row_split")
    tune = test.where("row_split = 'tune'").groupBy("client_id").agg(F.collect_list(F.struct("item_id", "label", "stars")).alias("tuned"))
    cases = scoring.test_cases(test).join(tune, "client_id")
    shared = cases.sparkSession.sparkContext.broadcast(q)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def factor(row: dict) -> np.ndarray:
            at, y, stars = (np.array([x[c] for x in row["tuned"]]) for c in ("item_id", "label", "stars"))
            return user_factor(shared.value[at], y.astype(float), 1 + conf * stars, reg)

        yield from scoring.ranked(batches, lambda rows: np.array([factor(r) for r in rows]) @ shared.value.T, np.arange(len(shared.value)))

    return D.dealt(cases).mapInArrow(run, "client_id long, item_id long, rank long")


def als_model(prep: D.Prepared, rank_: int = 8, iterations: int = 5):
    """The library's implicit-feedback factor model; what is ranked isn't fitted."""
    from pyspark.ml.recommendation import ALS

    train, test = D.splits(prep)
    used = train.select("client_id", "item_no", "label", "stars").unionByName(test.where("row_split = 'tune'").select("client_id", "item_no", "label", "stars"))
    rows = used.where("label = 1").select(F.col("client_id").cast("int").alias("user"), F.col("item_no").cast("int").alias("item"), F.col("stars").cast("float").alias("rating"))
    return ALS(rank=rank_, maxIter=iterations, regParam=REG, implicitPrefs=True, alpha=1.0, userCol="user", itemCol="item", ratingCol="rating", seed=42).fit(rows)


def central_als(prep: D.Prepared, rank_: int = 8, iterations: int = 5) -> DataFrame:
    """(client_id, rank, item_id): ten items a client by the factor model, the centralised reference, over its whole catalogue by falling norm instead of all pairs."""
    model = als_model(prep, rank_, iterations)
    return scoring.top_by_norm(model.userFactors, model.itemFactors, 10)
