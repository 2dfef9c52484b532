"""Centralised neural collaborative filtering on user and item ids (an upper bound that sees all users)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.functions.hashing import uniform
from fedlake.operators import scoring
from fedlake.operators.sequences import item_ordinals
from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.nets import NeuralCF
from fedlake.plans.ranking import CHUNK, MARGIN

#: Users compared with the catalogue's first chunk at a time.
SETTLED = 64


def fit(prep: D.Prepared, steps: int = 10, rate: float = 2.0, share: float = 0.5, width: int = 8, seed: int = 42, most: int | None = None) -> DataFrame:
    """Ranks (client_id, item_id, rank) of test users' positives.

    Ids need rows of every ranked user in training, so test users' tuning halves
    are trained on with the training users' rows. ``most`` is the largest k that
    measures ask for: a user whose positives are all beyond it gets rank ``most + 1``
    for them, and the same measures; all others get exact ranks.
    """
    train, test = D.splits(prep)
    rows = train.select("client_id", "item_no", "label").unionByName(test.where("row_split = 'tune'").select("client_id", "item_no", "label"))
    numbers = item_ordinals(prep.users.select(F.col("client_id").alias("item_id"))).select(F.col("item_id").alias("client_id"), F.col("ordinal").alias("user_no"))
    users = numbers.count()
    net = NeuralCF(users, prep.n_items, width)
    packed = rows.groupBy("client_id").agg(F.sort_array(F.collect_list(F.struct("item_no", "label"))).alias("items")).join(numbers, "client_id")
    packed = D.dealt(packed).persist()
    spark, theta = packed.sparkSession, net.start(seed)
    for k in range(steps):
        shared = spark.sparkContext.broadcast(theta)

        def kernel(row, shared=shared):
            i, y = np.array([x["item_no"] for x in row["items"]]), np.array([x["label"] for x in row["items"]], float)
            small, mine, at = compact(net, shared.value, row["user_no"], i)
            return at, small.gradient(mine, np.zeros(len(i), np.int64), np.arange(len(i)), y) * len(i)

        total, _, n = R.summed_deltas(packed.where(uniform(f"ncf-{seed}", F.lit(k), F.col("client_id")) < share), kernel, len(theta))
        total *= rate
        total /= max(1, n)
        theta -= total
        shared.destroy()
    packed.unpersist()
    return rank(prep, net, theta, numbers, test, most)


def compact(net: NeuralCF, theta: np.ndarray, user: int, items: np.ndarray) -> tuple[NeuralCF, np.ndarray, np.ndarray]:
    """(network, parameters, places in ``theta``) over one user's and its items' rows."""
    at = [net.layout.at[name].start + R.row_places(rows, net.width) for name, rows in (("P", np.array([user])), ("Q", items), ("A", np.array([user])), ("B", items))]
    at = np.concatenate([*at, np.arange(net.layout.at["B"].stop, net.size)])
    return replace(net, users=1, items=len(items)), theta[at], at


def all_scores(net: NeuralCF, theta: np.ndarray, users: list[int], first: int | None = None) -> np.ndarray:
    """(users, items), of the ``first`` items where given: the items' part of the perceptron's first layer is computed once for all the users."""
    p, d = net.layout.views(theta), net.width
    end = net.items if first is None else min(first, net.items)
    out = np.empty((len(users), end))
    mine = p["A"][users] @ p["W"][:d]
    for k in range(0, end, CHUNK):
        to = min(k + CHUNK, end)
        base = p["B"][k:to] @ p["W"][d:] + p["b"]
        out[:, k:to] = (p["P"][users] * p["w"][:d]) @ p["Q"][k:to].T
        for n in range(len(users)):
            out[n, k:to] += np.maximum(base + mine[n], 0) @ p["w"][d:]
    return out + p["c"][0]


def all_below(net: NeuralCF, theta: np.ndarray, rows: list[dict], most: int) -> np.ndarray:
    """For each user whether the catalogue's first chunk already holds ``most`` unseen items above each of its positives, by more than rounding."""
    out = np.zeros(len(rows), bool)
    for n, (row, found) in enumerate(zip(rows, all_scores(net, theta, [r["user_no"] for r in rows], CHUNK), strict=True)):
        own, seen = np.array(row["positives"], np.int64), np.array(row["seen"], np.int64)
        mine = net.scores(theta, np.full(len(own), row["user_no"]), own)
        unseen = np.sort(np.delete(found, seen[seen < len(found)]))
        if np.isfinite(unseen).all() and np.isfinite(mine).all():
            tolerance = MARGIN * max(1.0, float(np.abs(unseen).max(initial=0.0)), float(np.abs(mine).max(initial=0.0)))
            out[n] = (len(unseen) - np.searchsorted(unseen, mine + tolerance, "right") >= most).all()
    return out


def rank(prep: D.Prepared, net: NeuralCF, theta: np.ndarray, numbers: DataFrame, test: DataFrame, most: int | None = None) -> DataFrame:
    cases = scoring.test_cases(test.select("client_id", F.col("item_no").alias("item_id"), "label", "row_split")).join(numbers, "client_id")
    shared = cases.sparkSession.sparkContext.broadcast(theta)

    def left(batches: Iterator[pa.RecordBatch], beyond: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The users that the first chunk leaves open; ranks of the others go to ``beyond``."""
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            for k in range(0, batch.num_rows, SETTLED):
                rows = batch.slice(k, SETTLED).to_pylist()
                done = all_below(net, shared.value, rows, most)
                keep[k : k + SETTLED] = ~done
                for row in (r for r, x in zip(rows, done, strict=True) if x):
                    own = np.array(row["positives"], np.int64)
                    beyond.append(pa.RecordBatch.from_arrays([pa.array(np.full(len(own), row["client_id"], np.int64)), pa.array(own), pa.array(np.full(len(own), most + 1, np.int64))], ["client_id", "item_id", "rank"]))
            yield batch.filter(pa.array(keep))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        beyond: list[pa.RecordBatch] = []
        score = lambda rows: all_scores(net, shared.value, [r["user_no"] for r in rows])
        yield from scoring.ranked(batches if most is None else left(batches, beyond), score, np.arange(net.items))
        yield from beyond

    return D.dealt(cases).mapInArrow(run, "client_id long, item_id long, rank long")
