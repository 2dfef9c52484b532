"""The evaluation's experiments on the given tables.

Every function returns a DataFrame of results. Sizes default to a few rounds of
a small network; ``published(name)`` gives the arguments of the published runs
(``leaderboard(universe, **published("P"))``), which every function takes.
"""

from __future__ import annotations

import math
import time
from dataclasses import replace
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import accountant, metrics
from fedlake.plans import attack as A
from fedlake.plans import data as D
from fedlake.plans import pretrain
from fedlake.plans import rounds as R
from fedlake.plans.baselines import central, fcf, fedgraph, id_only, maml, ncf, popularity
from fedlake.plans.client import LocalPlan
from fedlake.plans.nets import SequenceEncoder
from fedlake.sources.universes import Universe

# settings of the published runs: rounds, local epochs, clients a round, clipping bound, widths
FULL = {"P": {"rounds": 80, "epochs": 100, "clients": 20, "clip": 40.0}, "E": {"rounds": 40, "epochs": 100, "clients": 30, "clip": 35.0}, "width": 64, "hidden": (128, 64, 32, 16), "act": "sigmoid"}
SWEEPS = {"rounds": (5, 20, 40, 60, 80, 100), "epochs": (5, 20, 40, 60, 80, 100, 120), "clients": (2, 5, 10, 15, 20, 25, 30, 35, 40)}
METHODS = ("metafed", "metafed_one_step", "central", "ncf", "fcf", "maml", "fomaml", "id_only", "fedgraph", "popularity", "random")


def published(name: str) -> dict:
    """Rounds, clients, local plan and network of the published runs on a universe."""
    own = FULL[name]
    return {"rounds": own["rounds"], "clients": own["clients"], "local": LocalPlan(epochs=own["epochs"]), "net": {"width": FULL["width"], "hidden": FULL["hidden"], "act": FULL["act"]}}


def fit_ranks(method: str, prep: D.Prepared, rounds: int = 3, clients: int = 10, local: LocalPlan | None = None, net: dict | None = None) -> DataFrame:
    """Ranks of the test users' positives under one method, exact up to the largest k of the measures; ``net``: width, hidden, act of the two-tower network."""
    most = max(metrics.KS)
    options = {"width": 8} | (net or {})
    local, width, net = local or LocalPlan(), options["width"], R.build_net(prep, **options)
    server = R.ServerPlan(rounds=rounds, clients=clients)
    if method == "metafed":
        return R.train_rounds(prep, net, local, server).rank(epochs=local.epochs, rate=local.rate, most=most)
    if method == "metafed_one_step":
        return R.train_rounds(prep, net, replace(local, method="one_step"), server).rank(epochs=1, rate=local.rate, most=most)
    if method == "central":
        return central.fit(prep, net, rounds, local=local).rank(epochs=local.epochs, rate=local.rate, most=most)
    if method == "ncf":
        return ncf.fit(prep, rounds, width=width, most=most)
    if method == "fcf":
        return fcf.rank(prep, fcf.fit(prep, rounds, clients))
    if method in ("maml", "fomaml"):
        return maml.fit(prep, net, rounds, clients, order=2 if method == "maml" else 1).rank(epochs=1, rate=local.rate, most=most)
    if method == "id_only":
        return id_only.fit(prep.universe, rounds, clients, local, options).rank(epochs=local.epochs, rate=local.rate, most=most)
    if method == "fedgraph":
        return fedgraph.rank(prep, *fedgraph.fit(prep, rounds, clients))
    if method in ("popularity", "random"):
        return popularity.popular(prep) if method == "popularity" else popularity.random(prep)
    raise ValueError(f"no method {method!r}")


def leaderboard(universe: Universe, methods: tuple[str, ...] = METHODS, rounds: int = 3, clients: int = 10, local: LocalPlan | None = None, net: dict | None = None) -> DataFrame:
    """(method, metric, k, value, users)."""
    prep, out = D.keep_cases(D.prepare(universe)), None
    for m in methods:
        one = metrics.summary(metrics.per_user(fit_ranks(m, prep, rounds, clients, local, net))).select(F.lit(m).alias("method"), "metric", "k", "value", "users")
        out = one if out is None else out.unionAll(one)
    return out


def wide(board: DataFrame, universe: str) -> DataFrame:
    """A leaderboard as the published tables show it: one row a method and metric, one column a k."""
    ks = ",".join(f"at_{k}" for k in metrics.KS)
    cells = [F.max(F.when(F.col("k") == k, F.col("value"))).alias(name) for k, name in zip(metrics.KS, ks.split(","), strict=True)]
    return board.groupBy(F.lit(universe).alias("universe"), "method", "metric").agg(*cells, F.max("users").alias("users"))


def sweep(universe: Universe, param: str, grid: tuple[int, ...] | None = None, base: dict | None = None, net: dict | None = None) -> DataFrame:
    """(param, value, hits20): one factor varied. All round counts come from one run with checkpoints."""
    prep = D.keep_cases(D.prepare(universe))
    spark, grid, rows = prep.items.sparkSession, grid or SWEEPS[param], []
    base = {"rounds": 3, "epochs": 2, "clients": 10} | (base or {})
    net = R.build_net(prep, **(net or {}))

    def hits(model: R.Model, epochs: int = base["epochs"]) -> float:
        return metrics.per_user(model.rank(epochs=epochs, most=20), (20,)).agg(F.avg("hits")).first()[0] or 0.0

    if param == "rounds":
        model = R.train_rounds(prep, net, LocalPlan(epochs=base["epochs"]), R.ServerPlan(rounds=max(grid), clients=base["clients"], keep=tuple(grid)))
        rows = [(param, int(r), hits(R.Model(prep, net, t))) for r, t in sorted(model.checkpoints.items())]
    else:
        for v in grid:
            now = base | {param: v}
            rows.append((param, int(v), hits(R.train_rounds(prep, net, LocalPlan(epochs=now["epochs"]), R.ServerPlan(rounds=now["rounds"], clients=now["clients"])), now["epochs"])))
    return spark.createDataFrame([(a, b, float(c)) for a, b, c in rows], "param string, value int, hits20 double")


def private_setup(spark, folder: str, name: str, universe: Universe, width: int = 8):
    """(prepared, sequences, encoder) for the two-stage runs."""
    from fedlake.sources import universes as U

    prep = D.prepare(universe)
    if name == "P":
        rows, gap, ident = U.purchase_rows(spark, folder).withColumn("eid", F.xxhash64("client_id", "item_id", "ts", "stars")), 365 * 24 * 3600, "eid"
    else:
        rows, gap, ident = U.event_rows(spark, folder), 24 * 3600, "event_id"
    return prep, pretrain.client_sequences(prep, rows, gap, ident), SequenceEncoder(prep.n_item_slots, width)


def dp_ablation(spark, folder: str, universe: Universe, rounds: int = 2, clients: int = 10, z: float = 1.0, clip: float | None = None, local: LocalPlan | None = None, net: dict | None = None) -> DataFrame:
    """(method, metric, k, value, users, epsilon) of no noise, two stages, one stage and Laplace noise; stage 1 has as many rounds and epochs as the other, tuning as many epochs."""
    options = {"width": 8} | (net or {})
    prep, sequences, encoder = private_setup(spark, folder, universe.name, universe, options["width"])
    D.keep_cases(prep)
    net, clip, plain = R.build_net(prep, **options), clip or universe.clip, local or LocalPlan()
    noisy = replace(plain, clip=clip, lam_item=0.5, lam_segment=0.5)
    server = R.ServerPlan(rounds=rounds, clients=clients)
    runs = {
        "metafed": lambda: R.train_rounds(prep, net, plain, server),
        "metafed_dp": lambda: pretrain.fit_private(prep, net, noisy, replace(server, noise="gaussian", z=z), 2, sequences, encoder, rounds, pretrain_epochs=plain.epochs),
        "metafed_dp_one_stage": lambda: pretrain.fit_private(prep, net, replace(noisy, lam_item=0.0, lam_segment=0.0), replace(server, noise="gaussian", z=z), 1),
        "metafed_laplace": lambda: R.train_rounds(prep, net, replace(plain, clip=clip, clip_norm="l1"), replace(server, noise="laplace", z=z)),
    }
    out = None
    for name, run in runs.items():
        model = run()
        eps = model.epsilon(1e-6).epsilon
        one = model.summary(plain.epochs, plain.rate).select(F.lit(name).alias("method"), "metric", "k", "value", "users", F.lit(float(eps)).alias("epsilon"))
        out = one if out is None else out.unionAll(one)
    return out


def privacy_table(spark, cells: list[tuple[int, int, float]], rounds: int = 1000, per_client: bool = False) -> DataFrame:
    """(n_clients, m, delta, eps)."""
    return accountant.epsilon_grid(spark.createDataFrame([(n, m, d, float(rounds * (m if per_client else 1))) for n, m, d in cells], "n_clients int, m int, delta double, compositions double"))


def budget_curve(universe: Universe, budgets: tuple[float, ...] = (2.0, 5.0, 15.0), rounds: int = 2, clients: int = 10, delta: float = 1e-6, local: LocalPlan | None = None, net: dict | None = None) -> DataFrame:
    """(epsilon, z, hits20): the noise that meets each budget, and what it leaves."""
    prep = D.keep_cases(D.prepare(universe))
    net, total = R.build_net(prep, **(net or {})), D.splits(prep)[0].select("client_id").distinct().count()
    bounded = replace(local or LocalPlan(), clip=1.0)
    rows = []
    for eps in budgets:
        z = accountant.solve(eps, delta, total, "z", size=clients, rounds=rounds)
        model = R.train_rounds(prep, net, bounded, R.ServerPlan(rounds=rounds, clients=clients, noise="gaussian", z=z))
        rows.append((eps, float(z), float(metrics.per_user(model.rank(most=20), (20,)).agg(F.avg("hits")).first()[0] or 0.0)))
    return prep.items.sparkSession.createDataFrame(rows, "epsilon double, z double, hits20 double")


def fit_curve(points: DataFrame) -> DataFrame:
    """hits20 = intercept + slope * ln(epsilon)."""
    return points.agg(F.regr_slope("hits20", F.log("epsilon")).alias("slope"), F.regr_intercept("hits20", F.log("epsilon")).alias("intercept"))


def inactive(universe: Universe, limit: int = 20, rounds: int = 3, clients: int = 10) -> DataFrame:
    """(method, hits20, users) on test users with fewer than ``limit`` touched items: several local steps against one."""
    prep = D.prepare(universe)
    few = prep.rows.groupBy("client_id").agg(F.count("*").alias("n")).where(F.col("n") < limit)
    out = None
    for m in ("metafed", "metafed_one_step"):
        users = metrics.per_user(fit_ranks(m, prep, rounds, clients).join(few, "client_id", "left_semi"), (20,))
        one = users.agg(F.avg("hits").alias("hits20"), F.count("*").alias("users")).select(F.lit(m).alias("method"), "hits20", "users")
        out = one if out is None else out.unionAll(one)
    return out


def round_time(universe: Universe, grid: tuple[int, ...] = (5, 10, 20), repeats: int = 5) -> DataFrame:
    """(method, m, ms, ln_ms): median wall time of one round, the first (warming) round dropped; same data, network and local steps."""
    prep = D.prepare(universe)
    net, rows = R.build_net(prep), []
    for m in grid:
        for name, plan in (("first_order", LocalPlan(method="fomaml")), ("second_order", LocalPlan(method="maml")), ("displacement", LocalPlan(epochs=1))):
            model = R.train_rounds(prep, net, plan, R.ServerPlan(rounds=repeats + 1, clients=m))
            ms = median(c["ms"] for c in model.costs[1:])
            rows.append((name, m, float(ms), math.log(ms)))
    return prep.items.sparkSession.createDataFrame(rows, "method string, m int, ms double, ln_ms double")


def kernel_time(net, batches: list, repeats: int = 5) -> dict[str, float]:
    """Seconds of first- and second-order outer gradients over the same batches, without the engine around them."""
    from fedlake.plans.client import maml_gradient

    theta, out = net.start(), {}
    for name in ("fomaml", "maml"):
        times = []
        for _ in range(repeats):
            began = time.perf_counter()
            for b in batches:
                maml_gradient(net, theta, b, LocalPlan(method=name))
            times.append(time.perf_counter() - began)
        out[name] = median(times)
    return out


#: Budgets of the published attack table; the largest is also tried with Laplace noise.
ATTACK_BUDGETS = {"P": (2.0, 5.0, 15.0), "E": (5.0, 20.0, 40.0)}


def mia(universe: Universe, budgets: tuple[float, ...] = (5.0,), rounds: int = 3, share: float = 0.6, delta: float = 1e-6, local: LocalPlan | None = None, net: dict | None = None) -> DataFrame:
    """(target, epsilon, accuracy, users, member_share): attack on targets without noise, with Gaussian noise per budget, with Laplace noise at the largest.

    Every round draws ``share`` of the users that a model may use, so that nearly
    all of them take part; a user counts as a member if some round drew it.
    """
    prep = D.prepare(universe)
    net = R.build_net(prep, **(net or {}))

    def size(rows: DataFrame) -> int:
        return max(1, int(share * rows.select("client_id").distinct().count()))

    def fit(plan: LocalPlan, **noise):
        return lambda rows: R.train_rounds(prep, net, plan, R.ServerPlan(rounds=rounds, clients=size(rows), **noise), rows)

    plain = local or LocalPlan()
    split = A.shadow_split(prep.rows.select("client_id").distinct()).cache()
    forest = A.fit_attack(A.train_shadow(prep, split, fit(plain)), split)
    half = prep.rows.join(split.where("part = 'private' and used").select("client_id"), "client_id", "left_semi")
    total = half.select("client_id").distinct().count()
    targets = [("metafed", math.inf, fit(plain))]
    for eps in budgets:
        z = accountant.solve(eps, delta, total, "z", size=size(half), rounds=rounds)
        targets.append((f"metafed_dp_{eps:g}", eps, fit(replace(plain, clip=1.0), noise="gaussian", z=z)))
        if eps == max(budgets):
            targets.append((f"metafed_laplace_{eps:g}", eps, fit(replace(plain, clip=1.0), noise="laplace", z=z)))
    out = None
    for name, eps, train in targets:
        one = A.evaluate(forest, train(half), split).select(F.lit(name).alias("target"), F.lit(float(eps)).alias("epsilon"), "accuracy", "users", "member_share")
        out = one if out is None else out.unionAll(one)
    return out


def describe(universe: Universe) -> DataFrame:
    """(n_items, n_users): how many users touched how many items."""
    return universe.interactions.groupBy("client_id").agg(F.count("*").alias("n_items")).groupBy("n_items").agg(F.count("*").alias("n_users"))
