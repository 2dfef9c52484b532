"""First-order meta-learning on item ids only: no side information on either side."""

from __future__ import annotations

from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.client import LocalPlan
from fedlake.sources.universes import Universe


def fit(universe: Universe, rounds: int = 3, clients: int = 10, local: LocalPlan | None = None, net: dict | None = None) -> R.Model:
    prep = D.prepare(universe, "ids")
    return R.train_rounds(prep, R.build_net(prep, **(net or {})), local or LocalPlan(), R.ServerPlan(rounds=rounds, clients=clients))
