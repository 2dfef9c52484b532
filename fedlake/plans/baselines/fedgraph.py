"""Client graphs with local differential privacy.

A client sees its own items and, through a keyed hash of its items, the mean of
its anonymised co-users' vectors: over its items, the mean over all other users
of the item, summed without forming pairs. Its vector is the mean of both; scores
are dot products with item vectors. It uploads gradients clipped in the L1 norm
with Laplace noise, together with noise on hash-chosen pseudo items so that
touched ids aren't disclosed. The graph holds training users' rows and the tested
users' tuning halves; what is ranked isn't in it. The keyed hash reproduces the
data flow of encrypted matching, not its security.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import sampling, scoring
from fedlake.operators.dp import clip_vector_l1, generator
from fedlake.operators.graph import co_user_means
from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.nets import sigmoid

def graph_rows(prep: D.Prepared) -> DataFrame:
    """(client_id, item_id) of the positives that the graph may use."""
    train, test = D.splits(prep)
    liked = train.select("client_id", "item_no", "label").unionByName(test.where("row_split = 'tune'").select("client_id", "item_no", "label"))
    return liked.where("label = 1").select("client_id", F.col("item_no").alias("item_id"))


def around(graph: DataFrame, q: np.ndarray, clients: DataFrame) -> DataFrame:
    """(client_id, around): the mean of the co-users' vectors under item vectors ``q``, for the given clients."""
    shared = graph.sparkSession.sparkContext.broadcast(q)
    columns = [f"v{k}" for k in range(q.shape[1])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            means = np.array([shared.value[np.array(x, np.int64)].mean(axis=0) for x in batch.column("liked").to_pylist()]).reshape(-1, len(columns))
            yield pa.RecordBatch.from_arrays([batch.column("client_id"), *[pa.array(means[:, k]) for k in range(len(columns))]], ["client_id", *columns])

    lists = graph.groupBy("client_id").agg(F.sort_array(F.collect_list("item_id")).alias("liked"))
    vectors = lists.mapInArrow(run, "client_id long, " + ", ".join(f"{c} double" for c in columns))
    return co_user_means(graph, vectors, columns, clients).select("client_id", F.array(*columns).alias("around"))


def client_vector(q: np.ndarray, own: np.ndarray, around: np.ndarray | None, hops: int = 2) -> np.ndarray:
    """Mean of the own items' mean and, with two hops, the co-users' mean vector."""
    h = q[own].mean(axis=0) if len(own) else np.zeros(q.shape[1])
    return (h + around) / 2 if hops > 1 and around is not None else h


def fit(prep: D.Prepared, rounds: int = 5, clients: int = 20, rate: float = 1.0, dim: int = 8, clip: float = 1.0, ldp_eps: float = 5.0, pseudo: int = 20, hops: int = 2, seed: int = 42) -> tuple[np.ndarray, DataFrame]:
    """(item vectors, the graph's rows)."""
    train, _ = D.splits(prep)
    graph = graph_rows(prep).persist()
    draw = sampling.draw_fixed(train.select("client_id").distinct(), clients, rounds, f"graph-{seed}")
    packed = train.join(draw.select("client_id").distinct(), "client_id", "left_semi").groupBy("client_id").agg(F.sort_array(F.collect_list(F.struct("item_no", "label"))).alias("items"))
    packed = packed.join(draw, "client_id").persist()
    spark = packed.sparkSession
    q = np.random.default_rng(seed).standard_normal((prep.n_items, dim)) * 0.1
    scale = 2 * clip / ldp_eps if ldp_eps else 0.0
    for r in range(rounds):
        shared = spark.sparkContext.broadcast(q)

        def kernel(row, shared=shared, r=r):
            table = shared.value
            i, y = np.array([x["item_no"] for x in row["items"]]), np.array([x["label"] for x in row["items"]], float)
            h = client_vector(table, i[y == 1], _mean(row), hops)
            own = (sigmoid(table[i] @ h) - y)[:, None] * h[None, :]
            rng = generator(seed, r, row["client_id"] & 0x7FFFFFFF)
            noisy = np.union1d(i, rng.integers(len(table), size=pseudo))
            g = np.zeros((len(noisy), table.shape[1]))
            g[np.searchsorted(noisy, i)] = clip_vector_l1(own.ravel(), clip).reshape(own.shape)
            if scale:
                g += rng.laplace(0, scale, g.shape)
            return R.row_places(noisy, table.shape[1]), -g.ravel()

        mine = packed.where(F.col("round") == r)
        met = mine.join(around(graph, q, mine), "client_id", "left") if hops > 1 else mine.withColumn("around", F.lit(None).cast("array<double>"))
        total, _, _ = R.summed_deltas(met, kernel, q.size)
        q = q + rate * total.reshape(q.shape) / clients
        shared.destroy()
    packed.unpersist()
    return q, graph


def _mean(row: dict) -> np.ndarray | None:
    return None if row["around"] is None else np.array(row["around"])


def rank(prep: D.Prepared, q: np.ndarray, graph: DataFrame, hops: int = 2) -> DataFrame:
    """Ranks of test users' positives; a user's vector comes from its tuning half and its neighbours."""
    test = D.splits(prep)[1].select("client_id", F.col("item_no").alias("item_id"), "label", "row_split")
    own = test.where("row_split = 'tune' and label = 1").groupBy("client_id").agg(F.collect_list("item_id").alias("own"))
    cases = scoring.test_cases(test).join(own, "client_id", "left")
    cases = cases.join(around(graph, q, cases), "client_id", "left")
    shared = cases.sparkSession.sparkContext.broadcast(q)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def vector(row: dict) -> np.ndarray:
            return client_vector(shared.value, np.array(row["own"] or [], np.int64), _mean(row), hops)

        yield from scoring.ranked(batches, lambda rows: np.array([vector(r) for r in rows]) @ shared.value.T, np.arange(len(shared.value)))

    return D.dealt(cases).mapInArrow(run, "client_id long, item_id long, rank long")
