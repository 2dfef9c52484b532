"""Queries that stand for the published evaluation run its rounds, clients, epochs and network."""

from __future__ import annotations

import pytest

from fedlake import catalog
from fedlake.plans import experiments as X
from fedlake.plans import rounds as R


class Asked(Exception):
    pass


@pytest.fixture
def asked(monkeypatch):
    """Runs a query up to its first training and gives (network, local plan, server plan)."""

    def train(prep, net, local, server, *rest, **named):
        raise Asked(net, local, server)

    monkeypatch.setattr(R, "train_rounds", train)

    def run(name, spark, folder):
        with pytest.raises(Asked) as found:
            catalog.queries()[name](spark, folder).collect()
        return found.value.args

    return run


def test_id_only_trains_whole(asked, spark, folder):
    net, local, server = asked("id_only_metrics", spark, folder)
    full = X.published("P")
    assert (server.rounds, server.clients, local.epochs) == (80, 20, 100) and local == full["local"]
    assert (net.width, net.hidden, net.act) == (64, (128, 64, 32, 16), "sigmoid")


def test_leaderboard_fits_whole(monkeypatch, spark, folder):
    seen = []

    def fit(method, prep, *settings):
        seen.append((prep.universe.name, method, settings))
        return X.popularity.random(prep)

    monkeypatch.setattr(X, "fit_ranks", fit)
    catalog.queries()["leaderboard"](spark, folder)
    full = {name: tuple(X.published(name).values()) for name in ("P", "E")}
    assert [x[:2] for x in seen] == [(name, m) for name in ("P", "E") for m in X.METHODS]
    assert all(settings == full[name] for name, _, settings in seen)


def test_ablation_trains_whole(asked, monkeypatch, spark, folder):
    net, local, server = asked("dp_ablation_purchases", spark, folder)
    assert (server.rounds, server.clients, local.epochs, net.width, net.hidden) == (80, 20, 100, 64, (128, 64, 32, 16))

    stages, tuned = [], []
    monkeypatch.setattr(R, "train_rounds", lambda prep, net, local, server, *rest, **named: R.Model(prep, net, net.start()))

    def items(prep, encoder, sequences, rounds, clients, epochs, **named):
        stages.append((rounds, clients, epochs))
        return encoder.start(), []

    monkeypatch.setattr(X.pretrain, "fit_items", items)
    monkeypatch.setattr(R.Model, "rank", lambda self, test=None, epochs=2, rate=0.05, most=None: tuned.append(epochs) or X.popularity.random(self.prep))
    catalog.queries()["dp_ablation_purchases"](spark, folder)
    assert stages == [(80, 20, 100)] and tuned == [100] * 4
