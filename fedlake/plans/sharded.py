"""Server rounds whose embedding rows stay in the cluster.

The embedding tables are a DataFrame of rows (side, slot, vec), written anew
each round in the shared checkpoint folder; only the dense layers, whose size
the data doesn't change, are on the driver and broadcast. A client receives the
rows that its own data names, trains the same kernel on that compact table, and
its displacement is zero everywhere else. Displacements are whole multiples of
2^-32, summed inside the worker and then by key, so without a clipping bound a
round equals ``rounds.train_rounds`` to the bit; with one, the norm is summed in
another order.

Nothing of the size of the catalogue is collected or broadcast. A round joins
the drawn clients' slots with the tables and passes once over them for the
update and the noise, which every row receives whether touched or not.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedlake.functions import hashing
from fedlake.operators import accountant, dp
from fedlake.plans import data as D
from fedlake.plans.client import LocalPlan, client_delta
from fedlake.plans.nets import TwoTower
from fedlake.plans.rounds import FIXED, Model, ServerPlan, scheduled
from fedlake.session import ensure_checkpoint_dir

#: Tables by side; the dense layers follow them in the flat vector.
SIDES = {"u": "Eu", "v": "Ev"}
#: Summed rows that a worker holds before it sends them on.
HELD_ROWS = 1 << 16


@dataclass
class ShardedModel:
    """table: side, slot, vec; head: the dense layers as one vector."""

    prep: D.Prepared
    net: TwoTower
    table: DataFrame
    head: np.ndarray
    costs: list[dict] = field(default_factory=list)
    privacy: dict | None = None

    def dense(self) -> Model:
        """The same parameters as one vector, for catalogues that a worker can hold."""
        theta = np.zeros(self.net.size)
        theta[_head(self.net)] = self.head
        for side, name in SIDES.items():
            rows = self.table.where(F.col("side") == side).select("slot", "vec").toArrow()
            slots = np.asarray(rows.column("slot"))
            self.net.layout.view(theta, name)[slots] = np.asarray(rows.column("vec").combine_chunks().flatten()).reshape(len(slots), self.net.width)
        return Model(self.prep, self.net, theta, self.costs, self.privacy)


def _head(net: TwoTower) -> slice:
    return slice(net.layout.at["Ev"].stop, net.size)


def start_table(spark: SparkSession, net: TwoTower, seed: int = 42) -> tuple[DataFrame, np.ndarray]:
    """Start values: rows drawn by a hash of their place wherever they lie, dense layers as in the dense form."""
    sides = [spark.range(n).select(F.lit(side).alias("side"), F.col("id").alias("slot")) for side, n in (("u", net.user_slots), ("v", net.item_slots))]
    cells = [F.lit(0.05) * hashing.normal(f"start-{seed}", F.col("side"), F.col("slot"), F.lit(k)) for k in range(net.width)]
    small = replace(net, user_slots=1, item_slots=1)
    return sides[0].unionAll(sides[1]).select("side", "slot", F.array(*cells).alias("vec")), small.start(seed)[_head(small)]


def split_theta(spark: SparkSession, net: TwoTower, theta: np.ndarray) -> tuple[DataFrame, np.ndarray]:
    """A dense vector as (table, head)."""
    rows = [(side, k, v.tolist()) for side, name in SIDES.items() for k, v in enumerate(net.layout.view(theta, name))]
    return spark.createDataFrame(rows, "side string, slot long, vec array<double>"), theta[_head(net)].copy()


def with_rows(clients: DataFrame, table: DataFrame) -> DataFrame:
    """The packed clients, each with the table rows that its own slots name, as ``params``."""
    mine = F.transform("us", lambda s: F.struct(F.lit("u").alias("side"), s.cast("long").alias("slot")))
    theirs = F.transform(F.flatten(F.transform("items", lambda x: x["s"])), lambda s: F.struct(F.lit("v").alias("side"), s.cast("long").alias("slot")))
    needs = clients.select("client_id", F.explode(F.array_distinct(F.concat(mine, theirs))).alias("key")).select("client_id", "key.side", "key.slot")
    given = needs.join(table, ["side", "slot"]).groupBy("client_id").agg(F.collect_list(F.struct("side", "slot", "vec")).alias("params"))
    return clients.join(given, "client_id")


def compact(net: TwoTower, row: dict, head: np.ndarray) -> tuple[TwoTower, np.ndarray, dict, dict[str, np.ndarray]]:
    """(network, parameters, client row, slots by side) over only the rows that the client was given."""
    found = {side: sorted((p["slot"], p["vec"]) for p in row["params"] if p["side"] == side) for side in SIDES}
    slots = {side: np.array([s for s, _ in rows], np.int64) for side, rows in found.items()}
    small = replace(net, user_slots=len(slots["u"]), item_slots=len(slots["v"]))
    theta = np.concatenate([np.array([v for _, v in found[side]], float).ravel() for side in SIDES] + [head])
    place = lambda side, given: np.searchsorted(slots[side], given).tolist()
    local = {**row, "us": place("u", row["us"]), "items": [{**x, "s": place("v", x["s"])} for x in row["items"]]}
    return small, theta, local, slots


def summed_rows(work: DataFrame, net: TwoTower, head, plan: LocalPlan, round_: int) -> DataFrame:
    """(side, slot, x0.., head, n, n_rows, given): partial sums of displacements by row, and one row of side 'h' per partition with the dense layers'."""
    width, cells = net.width, [f"x{k}" for k in range(net.width)]
    schema = f"side string, slot long, {', '.join(f'{c} long' for c in cells)}, head array<long>, n long, n_rows long, given long"
    names = ["side", "slot", *cells, "head", "n", "n_rows", "given"]

    def sent(held: dict) -> pa.RecordBatch:
        keys, values = list(held), np.array(list(held.values()), np.int64).reshape(len(held), width)
        none = lambda kind: pa.nulls(len(keys), kind)
        columns = [pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int64()), *[pa.array(values[:, c]) for c in range(width)]]
        return pa.RecordBatch.from_arrays([*columns, none(pa.list_(pa.int64())), none(pa.int64()), none(pa.int64()), none(pa.int64())], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[str, int], np.ndarray] = {}
        total, n, rows, given = np.zeros(len(head.value), np.int64), 0, 0, 0
        for batch in batches:
            for row in batch.to_pylist():
                small, theta, local, slots = compact(net, row, head.value)
                delta = client_delta(small, theta, local, plan, round_)
                n, rows, given = n + 1, rows + len(row["items"]), given + len(row["params"])
                if not np.isfinite(delta).all():
                    continue
                whole = np.trunc(delta * FIXED).astype(np.int64)  # toward zero: a clipped norm stays clipped
                total += whole[_head(small)]
                for side, name in SIDES.items():
                    for slot, cell in zip(slots[side].tolist(), small.layout.view(whole, name), strict=True):
                        held[side, slot] = held[side, slot] + cell if (side, slot) in held else cell
                if len(held) > HELD_ROWS:
                    yield sent(held)
                    held = {}
        if held:
            yield sent(held)
        if n:
            empty = [pa.nulls(1, pa.int64())] * width
            yield pa.RecordBatch.from_arrays([pa.array(["h"]), pa.nulls(1, pa.int64()), *empty, pa.array([total], pa.list_(pa.int64())), pa.array([n]), pa.array([rows]), pa.array([given])], names)

    return work.mapInArrow(run, schema)


def _remove(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def train_sharded(prep: D.Prepared, net: TwoTower, local: LocalPlan, server: ServerPlan, start: tuple[DataFrame, np.ndarray] | None = None) -> ShardedModel:
    """Server rounds as in ``rounds.train_rounds`` with the mean over the fixed round size and no or Gaussian noise."""
    if server.aggregate != "mean" or server.noise not in ("none", "gaussian"):
        raise ValueError("sharded rounds know the mean and 'none' or 'gaussian' noise")
    if server.noise == "gaussian" and local.clip is None:
        raise ValueError("noise needs a clipping bound")
    spark = prep.items.sparkSession
    packed, total = scheduled(prep, D.splits(prep)[0], server)
    packed = packed.persist()
    table, head = start or start_table(spark, net, server.seed)
    folder = f"{ensure_checkpoint_dir(spark)}/sharded-{uuid.uuid4().hex}"
    effective = server.z / max(server.rate, 1e-12) if server.noise == "gaussian" else 0.0
    curve = accountant.rdp_fixed(server.clients / total, effective) if effective > 0 else None
    sigma = dp.sigma(local.clip, server.clients, server.z) if effective > 0 else 0.0
    cells, costs, before = [f"x{k}" for k in range(net.width)], [], None
    for r in range(server.rounds):
        if server.budget is not None and curve is not None and accountant.epsilon(curve, r + 1, server.delta) > server.budget:
            break
        began = time.perf_counter()
        shared = spark.sparkContext.broadcast(head)  # the dense layers: a size that the data doesn't change
        found = summed_rows(with_rows(packed.where(F.col("round") == r).drop("round"), table), net, shared, local, r).persist()
        moved = found.where("side <> 'h'").groupBy("side", "slot").agg(*[F.sum(c).alias(c) for c in cells])
        step = [F.col("vec")[k] + F.lit(server.rate) * (F.coalesce(F.col(c), F.lit(0)) / F.lit(FIXED) / F.lit(float(server.clients))) for k, c in enumerate(cells)]
        if sigma:
            step = [x + dp.noise_column(sigma, f"sharded-{server.seed}", F.lit(r), F.col("side"), F.col("slot"), F.lit(k)) for k, x in enumerate(step)]
        path = f"{folder}/{r}"
        table.join(moved, ["side", "slot"], "left").select("side", "slot", F.array(*step).alias("vec")).write.parquet(path)
        summed, n, rows, given = np.zeros(len(head), np.int64), 0, 0, 0
        for part in found.where("side = 'h'").select("head", "n", "n_rows", "given").toLocalIterator():  # one row per partition
            summed, n, rows, given = summed + np.array(part["head"], np.int64), n + part["n"], rows + part["n_rows"], given + part["given"]
        head = head + server.rate * (summed / FIXED / server.clients)
        if sigma:
            head = head + dp.gaussian(len(head), sigma, server.seed + 2, r)
        found.unpersist()
        shared.destroy()
        table = spark.read.parquet(path)
        if before:
            _remove(spark, before)
        before = path
        sent = 8 * (n * len(head) + given * net.width)
        costs.append({"round": r, "clients": n, "down_bytes": sent, "up_bytes": sent, "gradients": local.epochs * -(-rows // max(1, local.batch)), "ms": (time.perf_counter() - began) * 1000})
    packed.unpersist()
    privacy = {"z": effective, "q": server.clients / total, "rounds": len(costs), "noise": server.noise, "covers": "all training"} if sigma else None
    return ShardedModel(prep, net, table, head, costs, privacy)
