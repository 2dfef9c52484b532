"""Second-order meta-learning with the same network, tuned on the support half of each tested user."""

from __future__ import annotations

from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.client import LocalPlan


def fit(prep: D.Prepared, net, rounds: int = 3, clients: int = 10, inner_steps: int = 1, rate: float = 0.05, server_rate: float = 0.5, order: int = 2, reduce: str = "mean") -> R.Model:
    """order 2 carries Hessian terms, order 1 drops them. ``reduce='sum'`` adds the tasks' outer gradients instead of averaging."""
    plan = LocalPlan(method="maml" if order == 2 else "fomaml", rate=rate, inner_steps=inner_steps)
    return R.train_rounds(prep, net, plan, R.ServerPlan(rounds=rounds, clients=clients, rate=server_rate * (clients if reduce == "sum" else 1)))
