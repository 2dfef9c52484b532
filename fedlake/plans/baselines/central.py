"""The same network without federation: every user is a task, all users' rows are at hand."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from fedlake.functions.hashing import uniform
from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.client import LocalPlan, client_batch, client_updates, compact


def fit(prep: D.Prepared, net, steps: int = 10, rate: float = 1.0, share: float = 0.5, train=None, seed: int = 42, local: LocalPlan | None = None, tasks: bool = True) -> R.Model:
    """Each step takes a hashed share of the users, one task per partition, one vector back.

    With ``tasks`` a user is a task: its parameters go through the local epochs
    and the step is the mean displacement of the tasks. Without, it is a gradient
    step on the pooled rows (``rate`` 0.5 suits it).
    """
    train, plan = D.splits(prep)[0] if train is None else train, local or LocalPlan()
    packed = D.dealt(D.pack(prep, train)).persist()
    spark = packed.sparkSession
    theta, costs = net.start(seed), []
    for k in range(steps):
        shared = spark.sparkContext.broadcast(theta)

        def kernel(some, shared=shared, k=k):
            if tasks:
                yield from client_updates(net, shared.value, some, plan, k)
                return
            for row in some:
                mine, batch, at = compact(net, shared.value, client_batch(row))
                yield row, (at, -mine.net.gradient(mine.theta, batch) * len(row["items"]))

        chosen = packed.where(uniform(f"central-{seed}", F.lit(k), F.col("client_id")) < share)
        total, n, rows = R.summed_deltas(chosen, kernel, len(theta), together=True)
        theta = theta + rate * total / max(1, n if tasks else rows)
        shared.destroy()
        costs.append({"round": k, "clients": n, "down_bytes": 0, "up_bytes": 0, "gradients": n * (plan.epochs if tasks else 1), "ms": 0.0})
    packed.unpersist()
    return R.Model(prep, net, theta, costs)


def pooled_step(net, theta: np.ndarray, batches: list, rate: float) -> np.ndarray:
    """One full-batch step over the union of batches: what a round of one-step clients weighted by rows must equal."""
    n = sum(len(b) for b in batches)
    return theta - rate * sum(net.gradient(theta, b) * len(b) for b in batches) / n
