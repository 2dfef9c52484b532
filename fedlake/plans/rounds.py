"""The server loop: one Spark job per round over the scheduled clients' packed rows.

Client displacements are rounded to whole multiples of 2^-32 and summed inside
each partition; partitions' sums meet on the driver. Whole-number sums make the
result independent of how clients are spread. The raw displacement of a single
client never leaves the worker process.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import accountant, dp, metrics, sampling, scoring
from fedlake.operators.accountant import PrivacyStatement
from fedlake.plans import data as D
from fedlake.plans.client import LocalPlan, client_updates, tune_many
from fedlake.plans.nets import Bags, TwoTower
from fedlake.plans.ranking import Scorer

FIXED = float(1 << 32)
#: Numbers of a sum that travel as one value, and values of one batch.
BLOCK, SENT = 1024, 512
#: Bytes of all partitions' sums up to which they meet on the driver.
GATHERED = 1 << 26


@dataclass
class Model:
    """Trained parameters with the cost and privacy ledgers of their rounds."""

    prep: D.Prepared
    net: TwoTower
    theta: np.ndarray
    costs: list[dict] = field(default_factory=list)
    privacy: dict | None = None
    #: (client_id) of the clients that took part in the rounds.
    members: DataFrame | None = None
    checkpoints: dict[int, np.ndarray] = field(default_factory=dict)

    def epsilon(self, delta: float, compositions: float | None = None) -> PrivacyStatement:
        """What the noisy rounds spent; without noise the budget is unbounded."""
        p = self.privacy or {"z": 0.0, "q": 1.0, "rounds": len(self.costs), "noise": "none", "covers": "nothing"}
        count = p["rounds"] if compositions is None else compositions
        if p["z"] <= 0:
            eps = float("inf")
        elif p["noise"] == "laplace":
            eps = accountant.epsilon(accountant.rdp_fixed_laplace(p["q"], p["z"], range(2, 65)), count, delta)
        else:
            eps = accountant.epsilon(accountant.rdp_fixed(p["q"], p["z"]), count, delta)
        return PrivacyStatement(eps, delta, "fixed size without replacement", "replace one user", count, p["z"], p["covers"])

    def cost_frame(self) -> DataFrame:
        spark = self.prep.items.sparkSession
        return spark.createDataFrame([(c["round"], c["clients"], c["down_bytes"], c["up_bytes"], c["gradients"], c["ms"]) for c in self.costs], "round int, clients long, down_bytes long, up_bytes long, gradients long, ms double")

    def rank(self, test: DataFrame | None = None, epochs: int = 2, rate: float = 0.05, most: int | None = None) -> DataFrame:
        return personalised_ranks(self, D.cases(self.prep) if test is None else D.dealt(D.ranking_users(self.prep, test)), epochs, rate, most)

    def summary(self, epochs: int = 2, rate: float = 0.05) -> DataFrame:
        return metrics.summary(metrics.per_user(self.rank(epochs=epochs, rate=rate, most=max(metrics.KS))))

    def top_k(self, users: DataFrame, k: int = 10) -> DataFrame:
        return top_lists(self, users, k)


def build_net(prep: D.Prepared, width: int = 8, hidden: tuple[int, ...] = (16,), act: str = "relu", out: str = "sigmoid") -> TwoTower:
    return TwoTower(prep.n_users_slots, prep.n_item_slots, prep.user_fields, prep.item_fields, width, hidden, act, out)


def summed_deltas(clients: DataFrame, kernel, size: int, together: bool = False) -> tuple[np.ndarray, int, int]:
    """(sum of the clients' vectors, clients, rows) over one job. kernel(row) gives a vector, (places, values) of one that is zero elsewhere, or None.

    With ``together`` the kernel takes the rows of a batch and gives (row, what it gives for one row) of each.

    All partitions run at once. Their sums travel as blocks of bytes, those that
    aren't zero only; where the blocks of all partitions could be many, equal
    blocks are summed in the cluster first, so the driver takes one vector.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n, rows = np.zeros(-(-size // BLOCK) * BLOCK, np.int64), 0, 0
        moved = np.zeros(len(total) // BLOCK, bool)
        for batch in batches:
            some = batch.to_pylist()
            for row, delta in kernel(some) if together else ((row, kernel(row)) for row in some):
                if delta is not None:
                    at, values = delta if isinstance(delta, tuple) else (np.arange(size), delta)
                    if np.isfinite(values).all():
                        total[at] += np.trunc(values * FIXED).astype(np.int64)  # toward zero: a clipped norm stays clipped
                        moved[at // BLOCK] = True
                n, rows = n + 1, rows + len(row["items"])
        if n:
            yield _blocks([-1], [n], [rows], [b""])
            blocks = np.flatnonzero(moved)
            for k in range(0, len(blocks), SENT):
                part = blocks[k : k + SENT].tolist()
                yield _blocks(part, [0] * len(part), [0] * len(part), [total[x * BLOCK : (x + 1) * BLOCK].tobytes() for x in part])

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n, rows = {}, 0, 0
        for batch in batches:
            n, rows = n + sum(batch.column("n").to_pylist()), rows + sum(batch.column("rows").to_pylist())
            for block, raw in zip(batch.column("block").to_pylist(), batch.column("sum").to_pylist(), strict=True):
                if block >= 0:
                    one = np.frombuffer(raw, np.int64)
                    sums[block] = sums[block] + one if block in sums else one
        if n:
            yield _blocks([-1], [n], [rows], [b""])
        keys = list(sums)
        for k in range(0, len(keys), SENT):
            part = keys[k : k + SENT]
            yield _blocks(part, [0] * len(part), [0] * len(part), [sums[x].tobytes() for x in part])

    schema = "block int, n long, rows long, sum binary"
    found = clients.mapInArrow(run, schema)
    cores = clients.sparkSession.sparkContext.defaultParallelism
    total, n, rows = np.zeros(-(-size // BLOCK) * BLOCK, np.int64), 0, 0
    if size * 8 * cores > GATHERED:  # summed in the cluster, taken one part at a time: the driver holds the sum and a part of it
        for row in found.repartition(cores, "block").mapInArrow(met, schema).toLocalIterator():
            n, rows = n + row.n, rows + row.rows
            if row.block >= 0:
                total[row.block * BLOCK : (row.block + 1) * BLOCK] += np.frombuffer(row.sum, np.int64)
    else:
        for batch in found.toArrow().to_batches():
            n, rows = n + sum(batch.column("n").to_pylist()), rows + sum(batch.column("rows").to_pylist())
            for block, raw in zip(batch.column("block").to_pylist(), batch.column("sum"), strict=True):
                if block >= 0:
                    total[block * BLOCK : (block + 1) * BLOCK] += np.frombuffer(raw.as_buffer(), np.int64)
    return np.divide(total, FIXED, out=total.view(float))[:size], n, rows  # in place: numbers of a vector that may be long


def row_places(rows: np.ndarray, width: int) -> np.ndarray:
    """Places of a table's rows in the flat vector."""
    return (rows[:, None] * width + np.arange(width)).ravel()


def _blocks(blocks: list[int], n: list[int], rows: list[int], sums: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(blocks, pa.int32()), pa.array(n, pa.int64()), pa.array(rows, pa.int64()), pa.array(sums, pa.binary())], ["block", "n", "rows", "sum"])


@dataclass(frozen=True)
class ServerPlan:
    """Rounds, clients per round, server rate, noise. noise: 'none', 'gaussian', 'laplace', 'local' (clients add their share)."""

    rounds: int = 3
    clients: int = 20
    rate: float = 1.0
    aggregate: str = "mean"  # 'mean' over the fixed round size, 'weighted' by rows
    noise: str = "none"
    z: float = 1.0
    delta: float = 1e-6
    budget: float | None = None
    tolerance: float | None = None
    patience: int = 2
    keep: tuple[int, ...] = ()
    seed: int = 42


def scheduled(prep: D.Prepared, train: DataFrame, server: ServerPlan) -> tuple[DataFrame, int]:
    """Packed rows of all rounds' clients with their round, and the number of training clients. Draws don't depend on data."""
    clients = train.select("client_id").distinct()
    total = clients.count()
    draw = sampling.draw_fixed(clients, server.clients, server.rounds, f"round-{server.seed}")
    packed = D.pack(prep, train.join(draw.select("client_id").distinct(), "client_id", "left_semi"))
    cores = prep.items.sparkSession.sparkContext.defaultParallelism
    return packed.join(draw, "client_id").repartition(min(cores, server.clients), "client_id"), total


def train_rounds(prep: D.Prepared, net: TwoTower, local: LocalPlan, server: ServerPlan, train: DataFrame | None = None, theta: np.ndarray | None = None, make_extra=None, covers: str = "all training", observe=None) -> Model:
    """Server rounds from ``theta``.

    The bounded mean divides by the fixed round size, whatever arrived. Noise is
    added after the server rate, as a multiple z of the mean's sensitivity; its
    effective multiplier against the scaled step is z / rate. Training stops
    after the rounds, when the budget would be exceeded, or when ``observe(theta)``
    (a loss on held-out clients) stops falling.
    """
    spark = prep.items.sparkSession
    train = D.splits(prep)[0] if train is None else train
    packed, total = scheduled(prep, train, server)
    packed = packed.persist()
    theta = net.start(server.seed) if theta is None else theta.copy()
    noisy = server.noise != "none"
    if noisy and local.clip is None:
        raise ValueError("noise needs a clipping bound")
    if noisy and server.aggregate != "mean":
        raise ValueError("the noise is measured for the mean over a fixed round size; weights by rows have another sensitivity")
    if server.noise == "laplace":  # its scale is measured in the L1 norm
        local = replace(local, clip_norm="l1")
    effective = server.z / max(server.rate, 1e-12) if noisy else 0.0
    curve = (accountant.rdp_fixed_laplace(server.clients / total, effective, range(2, 65)) if server.noise == "laplace" else accountant.rdp_fixed(server.clients / total, effective)) if noisy and effective > 0 else None
    sigma = dp.sigma(local.clip, server.clients, server.z) if noisy else 0.0
    costs, kept, best, waited = [], {}, np.inf, 0
    if server.noise == "local":
        local = replace(local, local_noise=sigma, round_size=server.clients)
    for r in range(server.rounds):
        if server.budget is not None and curve is not None and accountant.epsilon(curve, r + 1, server.delta) > server.budget:
            break
        began = time.perf_counter()
        shared = spark.sparkContext.broadcast(theta)  # one model, a size that the data doesn't change

        def kernel(some, shared=shared, r=r):
            for row, (at, delta) in client_updates(net, shared.value, some, local, r, make_extra):
                yield row, (at, delta * len(row["items"]) if server.aggregate == "weighted" else delta)

        summed, n, rows = summed_deltas(packed.where(F.col("round") == r), kernel, len(theta), together=True)
        step = summed / (max(1, rows) if server.aggregate == "weighted" else server.clients)
        theta = theta + server.rate * step
        if server.noise == "gaussian":
            theta = theta + dp.gaussian(len(theta), sigma, server.seed + 2, r)
        elif server.noise == "laplace":
            theta = theta + dp.laplace(len(theta), sigma, server.seed + 2, r)
        shared.destroy()
        steps = local.epochs * -(-rows // max(1, local.batch)) if local.method == "sgd" else n * (local.inner_steps + 1)
        costs.append({"round": r, "clients": n, "down_bytes": server.clients * len(theta) * 8, "up_bytes": server.clients * len(theta) * 8, "gradients": steps, "ms": (time.perf_counter() - began) * 1000})
        if r + 1 in server.keep:
            kept[r + 1] = theta.copy()
        if observe is not None and server.tolerance is not None:
            now = observe(theta)
            waited = 0 if now < best - server.tolerance else waited + 1
            best = min(best, now)
            if waited >= server.patience:
                break
    packed.unpersist()
    ran = sampling.draw_fixed(train.select("client_id").distinct(), server.clients, server.rounds, f"round-{server.seed}").where(F.col("round") < len(costs))
    privacy = {"z": effective, "q": server.clients / total, "rounds": len(costs), "noise": server.noise, "covers": covers} if noisy else None
    return Model(prep, net, theta, costs, privacy, ran.select("client_id").distinct(), kept)


def personalised_ranks(model: Model, users: DataFrame, epochs: int = 2, rate: float = 0.05, most: int | None = None) -> DataFrame:
    """(client_id, item_id, rank) of every positive of the ranking half, after tuning on the tuning half, among all never-touched items.

    Tuning, scoring and counting happen in one kernel per user; item_id is the
    item's number in the catalogue. ``most`` is the largest k that measures ask for:
    a user whose positives are all beyond it, as some chunks of the catalogue show,
    gets rank ``most + 1`` for them, and the same measures; all others get exact ranks.
    """
    spark = users.sparkSession
    shared = spark.sparkContext.broadcast((model.theta, D.item_table(model.prep)))
    net = model.net

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = None
        for batch in batches:
            scorer = scorer or Scorer(net, *shared.value)
            for row, mine in tune_many(net, scorer.theta, batch.to_pylist(), epochs, rate):
                user, own, seen = Bags.of([row["uf"]], [row["us"]]), np.array(row["positives"], np.int64), np.array(row["seen"], np.int64)
                if most is not None and scorer.all_below(user, mine, own, seen, most):
                    above = np.full(len(own), most, np.int64)
                else:
                    scores = scorer.scores(user, mine)
                    above = scoring.count_above(scores, scorer.table.ids, seen, scores[own], own)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), row["client_id"], np.int64)), pa.array(own), pa.array(above + 1)], ["client_id", "item_id", "rank"])

    return users.select("client_id", "uf", "us", "items", "seen", "positives").mapInArrow(run, "client_id long, item_id long, rank long")


def top_lists(model: Model, users: DataFrame, k: int = 10) -> DataFrame:
    """(client_id, items array<long>, mean_score): the k best items of the whole catalogue by the shared parameters.

    Users with equal slots have equal lists: they meet in one task, which scores the catalogue once for them.
    """
    shared = users.sparkSession.sparkContext.broadcast((model.theta, D.item_table(model.prep)))
    net = model.net

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer, known = None, {}
        for batch in batches:
            rows = batch.to_pylist()
            lists, means = [], []
            for row in rows:
                key = tuple(row["uf"]), tuple(row["us"])
                if key not in known:
                    scorer = scorer or Scorer(net, *shared.value)
                    s = scorer.scores(Bags.of([row["uf"]], [row["us"]]))
                    at = scoring.best_places(s, scorer.table.ids, k)
                    known[key] = scorer.table.ids[at], float(s[at].mean()) if len(at) else 0.0
                lists.append(known[key][0])
                means.append(known[key][1])
            yield pa.RecordBatch.from_arrays([pa.array([r["client_id"] for r in rows], pa.int64()), pa.array(lists, pa.list_(pa.int64())), pa.array(means, pa.float64())], ["client_id", "items", "mean_score"])

    mine = model.prep.users.join(users.select("client_id"), "client_id", "left_semi").select("client_id", "uf", "us")
    cores = users.sparkSession.sparkContext.defaultParallelism
    return mine.repartition(cores, "uf", "us").mapInArrow(run, "client_id long, items array<long>, mean_score double")


def held_out_loss(prep: D.Prepared, net: TwoTower, rows: DataFrame):
    """A function theta -> mean loss over the given clients' rows, one distributed pass per call."""
    packed = D.pack(prep, rows).persist()
    spark = packed.sparkSession

    def observe(theta: np.ndarray) -> float:
        shared = spark.sparkContext.broadcast(theta)

        def run(batches):
            from fedlake.plans.client import client_batch

            for batch in batches:
                got = [(net.loss(shared.value, b), len(b)) for b in map(client_batch, batch.to_pylist())]
                yield pa.RecordBatch.from_arrays([pa.array([x * n for x, n in got], pa.float64()), pa.array([n for _, n in got], pa.int64())], ["loss", "n"])

        r = packed.mapInArrow(run, "loss double, n long").agg(F.sum("loss").alias("s"), F.sum("n").alias("n")).first()
        return r.s / max(1, r.n)

    return observe


def save_theta(model: Model, path: str) -> None:
    """Parameters as rows (tensor, row, vec): what a sharded store holds."""
    spark = model.prep.items.sparkSession
    rows = []
    for name, shape in model.net.layout.shapes.items():
        table = model.net.layout.view(model.theta, name)
        table = table.reshape(shape[0], -1) if len(shape) > 1 else table.reshape(1, -1)
        rows += [(name, k, [float(x) for x in v]) for k, v in enumerate(table)]
    spark.createDataFrame(rows, "tensor string, row long, vec array<double>").write.mode("overwrite").parquet(path)


def load_theta(spark, path: str, net: TwoTower) -> np.ndarray:
    theta = np.zeros(net.size)
    for name, shape in net.layout.shapes.items():
        rows = spark.read.parquet(path).where(F.col("tensor") == name).orderBy("row").toArrow()
        net.layout.view(theta, name)[...] = np.array(rows.column("vec").to_pylist()).reshape(shape)
    return theta
