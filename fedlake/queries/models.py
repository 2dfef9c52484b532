"""Trained models and experiments as queries; SQL can't express them, tests hold them against invariants."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from fedlake.operators import metrics
from fedlake.plans import data as D
from fedlake.plans import experiments as X
from fedlake.plans import pretrain
from fedlake.plans import rounds as R
from fedlake.plans import sharded as S
from fedlake.plans.baselines import fcf
from fedlake.plans.client import LocalPlan
from fedlake.queries.registry import query
from fedlake.sources import universes as U

ROUNDS, CLIENTS = 2, 10


def _prepared(spark, d, name: str = "P") -> D.Prepared:
    return D.prepare(U.universe(spark, d, name))


@query("metafed_metrics")
def metafed_metrics(spark, d):
    """First-order federated rounds, personalised ranking: the flagship."""
    prep = _prepared(spark, d)
    model = R.train_rounds(prep, R.build_net(prep), LocalPlan(), R.ServerPlan(rounds=3, clients=CLIENTS))
    return model.summary().select(F.lit("metafed").alias("model"), "metric", "k", "value", "users")


@query("metafed_sharded_metrics")
def metafed_sharded_metrics(spark, d):
    """The rounds with embedding rows kept in the cluster; only the dense layers are broadcast."""
    prep = _prepared(spark, d)
    model = S.train_sharded(prep, R.build_net(prep), LocalPlan(), R.ServerPlan(rounds=ROUNDS, clients=CLIENTS))
    return model.dense().summary().select(F.lit("metafed_sharded").alias("model"), "metric", "k", "value", "users")


@query("metafed_events_metrics")
def metafed_events_metrics(spark, d):
    """The same on the events universe."""
    prep = _prepared(spark, d, "E")
    model = R.train_rounds(prep, R.build_net(prep), LocalPlan(), R.ServerPlan(rounds=ROUNDS, clients=5))
    return model.summary().select(F.lit("metafed").alias("model"), "metric", "k", "value", "users")


@query("metafed_dp_metrics")
def metafed_dp_metrics(spark, d):
    """Two-stage private training: pre-trained item vectors, joint loss, clipping, Gaussian noise, epsilon."""
    prep, sequences, encoder = X.private_setup(spark, d, "P", U.universe(spark, d, "P"))
    model = pretrain.fit_private(prep, R.build_net(prep), LocalPlan(clip=40.0, lam_item=0.5, lam_segment=0.5), R.ServerPlan(rounds=ROUNDS, clients=CLIENTS, noise="gaussian"), 2, sequences, encoder, 1)
    return model.summary().select(F.lit("metafed_dp").alias("model"), "metric", "k", "value", "users", F.lit(model.epsilon(1e-6).epsilon).alias("epsilon"))


@query("pretrain_loss")
def pretrain_loss(spark, d):
    """Mean self-supervised loss of each noiseless pre-training round."""
    _, sequences, encoder = X.private_setup(spark, d, "E", U.universe(spark, d, "E"))
    _, losses = pretrain.fit_items(_prepared(spark, d, "E"), encoder, sequences, 2, 5)
    return spark.createDataFrame([(k, float(x)) for k, x in enumerate(losses)], "round int, loss double")


@query("personalised_ranks")
def personalised_ranks(spark, d):
    """Rank of every positive of every test user after on-client tuning, from fresh parameters."""
    prep = _prepared(spark, d)
    net = R.build_net(prep)
    return R.Model(prep, net, net.start()).rank(epochs=1)


#: Methods whose row comes from the published settings; the other rows are of a few rounds of the small network.
WHOLE = {"id_only"}


def _method(name: str):
    def run(spark, d):
        found = X.fit_ranks(name, _prepared(spark, d), **(X.published("P") if name in WHOLE else {"rounds": ROUNDS, "clients": CLIENTS}))
        return metrics.summary(metrics.per_user(found)).select(F.lit(name).alias("model"), "metric", "k", "value", "users")

    run.__doc__ = f"Leaderboard row of {name}."
    return run


for _name in X.METHODS[1:]:
    query(f"{_name}_metrics")(_method(_name))


@query("als_topk")
def als_topk(spark, d):
    return fcf.central_als(_prepared(spark, d))


@query("leaderboard")
def leaderboard(spark, d):
    """All methods on both universes at their published settings, one column a k."""
    boards = [X.wide(X.leaderboard(U.universe(spark, d, name), **X.published(name)), name) for name in ("P", "E")]
    return boards[0].unionAll(boards[1])


@query("metafed_deep_metrics")
def metafed_deep_metrics(spark, d):
    """The published network (four hidden layers, sigmoid, width 64), one round."""
    full = X.published("E")
    found = X.fit_ranks("metafed", _prepared(spark, d, "E"), 1, 5, LocalPlan(epochs=5), full["net"])
    return metrics.summary(metrics.per_user(found)).select(F.lit("metafed_deep").alias("model"), "metric", "k", "value", "users")


@query("mia_accuracy")
def mia_accuracy(spark, d):
    """Attack table on events: no noise, the published budgets, Laplace noise at the largest."""
    return X.mia(U.universe(spark, d, "E"), X.ATTACK_BUDGETS["E"])


@query("mia_accuracy_purchases")
def mia_accuracy_purchases(spark, d):
    return X.mia(U.universe(spark, d, "P"), X.ATTACK_BUDGETS["P"], 2)


@query("round_times")
def round_times(spark, d):
    """Time of a round by number of clients, first and second order."""
    return X.round_time(U.universe(spark, d, "P"), (5, 10, 20), 3)


@query("round_costs")
def round_costs(spark, d):
    """Bytes, gradients and time of each round."""
    prep = _prepared(spark, d, "E")
    return R.train_rounds(prep, R.build_net(prep), LocalPlan(), R.ServerPlan(rounds=ROUNDS, clients=5)).cost_frame()


def _sweep(param: str, name: str, base: dict):
    def run(spark, d):
        return X.sweep(U.universe(spark, d, name), param, None, base)

    run.__doc__ = f"The published grid of {param} on universe {name}."
    return run


for _name, _suffix in (("E", ""), ("P", "_purchases")):
    query(f"sweep_rounds{_suffix}")(_sweep("rounds", _name, {"clients": 5, "epochs": 1}))
    query(f"sweep_epochs{_suffix}")(_sweep("epochs", _name, {"clients": 5, "rounds": 1}))
    query(f"sweep_clients{_suffix}")(_sweep("clients", _name, {"rounds": 1, "epochs": 1}))


@query("dp_ablation")
def dp_ablation(spark, d):
    return X.dp_ablation(spark, d, U.universe(spark, d, "E"), 2, 5)


@query("dp_ablation_purchases")
def dp_ablation_purchases(spark, d):
    """No noise, two stages, one stage and Laplace noise at the published settings."""
    return X.dp_ablation(spark, d, U.universe(spark, d, "P"), **X.published("P"))


@query("budget_curve")
def budget_curve(spark, d):
    return X.budget_curve(U.universe(spark, d, "E"), X.ATTACK_BUDGETS["E"], 2, 5)


@query("budget_curve_fit")
def budget_curve_fit(spark, d):
    """The logarithmic fit over measured points."""
    return X.fit_curve(X.budget_curve(U.universe(spark, d, "P"), X.ATTACK_BUDGETS["P"], 1, 5))


@query("inactive_users_hits")
def inactive_users_hits(spark, d):
    base = U.universe(spark, d, "P")
    return X.inactive(replace(base, interactions=U.thin_activity(base.interactions)), 20, ROUNDS, CLIENTS)
