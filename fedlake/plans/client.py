"""What a client computes: local updates on one packed row, always a pure function of (row, parameters, seed, round)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np

from fedlake.operators.dp import clip_vector, clip_vector_l1, gaussian_distributed, generator
from fedlake.plans.nets import Bags, Batch, TwoTower, activate, hessian_vector, sigmoid, slope

#: Clients trained side by side at most, and numbers of their dense layers held at a time.
TOGETHER, HELD = 64, 1 << 19


@dataclass(frozen=True)
class LocalPlan:
    """How clients train. method: 'sgd' (displacement of local epochs), 'one_step', 'maml', 'fomaml'."""

    method: str = "sgd"
    rate: float = 0.05
    epochs: int = 2
    batch: int = 32
    inner_steps: int = 1
    clip: float | None = None
    clip_norm: str = "l2"
    clip_each_step: bool = False
    local_noise: float = 0.0
    round_size: int = 1
    seed: int = 42
    #: Joint objective: weights of the supervised and the two self-supervised losses.
    lam_sup: float = 1.0
    lam_item: float = 0.0
    lam_segment: float = 0.0


def client_batch(row: dict) -> Batch:
    items = row["items"]
    n = len(items)
    return Batch(Bags.of([row["uf"]], [row["us"]]).repeat(n), Bags.of([x["f"] for x in items], [x["s"] for x in items]), np.array([x["y"] for x in items], float))


@dataclass
class Tuned:
    """A client's parameters over only the rows that its data names: ``net`` and ``theta`` hold user rows ``u_slots``, item rows ``v_slots`` and all dense layers."""

    net: TwoTower
    theta: np.ndarray
    u_slots: np.ndarray
    v_slots: np.ndarray


def _places(net: TwoTower, name: str, slots: np.ndarray) -> np.ndarray:
    """Places of a table's rows in the flat vector."""
    return (net.layout.at[name].start + slots[:, None] * net.width + np.arange(net.width)).ravel()


def compact(net: TwoTower, theta: np.ndarray, batch: Batch) -> tuple[Tuned, Batch, np.ndarray]:
    """(parameters that the batch names, the batch over them, their places in ``theta``); gradients are zero at all other places."""
    u, mine = np.unique(batch.user.slots, return_inverse=True)
    v, theirs = np.unique(batch.item.slots, return_inverse=True)
    small = replace(net, user_slots=len(u), item_slots=len(v))
    at = np.concatenate([_places(net, "Eu", u), _places(net, "Ev", v), np.arange(net.layout.at["Ev"].stop, net.size)])
    sides = (Bags(k.reshape(b.slots.shape), b.fields, b.weights) for k, b in ((mine, batch.user), (theirs, batch.item)))
    return Tuned(small, theta[at], u, v), Batch(*sides, batch.y), at


def _clip(delta: np.ndarray, plan: LocalPlan) -> np.ndarray:
    return (clip_vector if plan.clip_norm == "l2" else clip_vector_l1)(delta, plan.clip)


def local_sgd(net: TwoTower, theta0: np.ndarray, batch: Batch, plan: LocalPlan, round_: int, client: int) -> np.ndarray:
    """Parameters after the local epochs."""
    theta = theta0.copy()
    for epoch in range(plan.epochs):
        order = generator(plan.seed, round_, client & 0x7FFFFFFF, epoch).permutation(len(batch))
        for k in range(0, len(batch), plan.batch):
            theta -= plan.rate * plan.lam_sup * net.gradient(theta, batch.take(order[k : k + plan.batch]))
            if plan.clip_each_step and plan.clip:
                theta = theta0 + _clip(theta - theta0, plan)
    return theta


def maml_gradient(net: TwoTower, theta0: np.ndarray, batch: Batch, plan: LocalPlan) -> np.ndarray:
    """Outer gradient: support rows (even places) adapt, query rows (odd places) judge; Hessian terms unless first-order."""
    support, query = batch.take(slice(0, None, 2)), batch.take(slice(1, None, 2))
    if not len(query):
        return np.zeros_like(theta0)
    path = [theta0]
    for _ in range(plan.inner_steps):
        path.append(path[-1] - plan.rate * net.gradient(path[-1], support))
    v = net.gradient(path[-1], query)
    if plan.method == "maml":
        for theta in reversed(path[:-1]):
            v = v - plan.rate * hessian_vector(lambda t: net.gradient(t, support), theta, v)
    return v


def joint_sgd(net: TwoTower, theta0: np.ndarray, batch: Batch, plan: LocalPlan, round_: int, client: int, extra) -> tuple[np.ndarray, np.ndarray]:
    """(places, displacement there) after the local epochs; ``extra(theta)`` gives (places, gradient) of the self-supervised part per mini-batch."""
    theta, touched = theta0.copy(), np.zeros(len(theta0), bool)
    for epoch in range(plan.epochs):
        order = generator(plan.seed, round_, client & 0x7FFFFFFF, epoch).permutation(len(batch))
        for k in range(0, len(batch), plan.batch):
            mine, part, at = compact(net, theta, batch.take(order[k : k + plan.batch]))
            g = plan.lam_sup * mine.net.gradient(mine.theta, part)
            places, more = extra(theta)
            theta[at] -= plan.rate * g
            theta[places] -= plan.rate * more
            touched[at] = touched[places] = True
            if plan.clip_each_step and plan.clip:
                where = np.flatnonzero(touched)
                theta[where] = theta0[where] + _clip(theta[where] - theta0[where], plan)
    where = np.flatnonzero(touched)
    return where, theta[where] - theta0[where]


def client_update(net: TwoTower, theta0: np.ndarray, row: dict, plan: LocalPlan, round_: int, extra=None) -> tuple[np.ndarray, np.ndarray]:
    """(places, values) of the (clipped) displacement that leaves the client, zero elsewhere; for the two-level methods minus the outer gradient."""
    batch = client_batch(row)
    if plan.method == "sgd" and extra is not None:
        at, delta = joint_sgd(net, theta0, batch, plan, round_, row["client_id"], extra)
    else:
        mine, batch, at = compact(net, theta0, batch)
        if plan.method in ("maml", "fomaml"):
            delta = -maml_gradient(mine.net, mine.theta, batch, plan)
        elif plan.method == "one_step":
            delta = -plan.rate * mine.net.gradient(mine.theta, batch)
        else:
            delta = local_sgd(mine.net, mine.theta, batch, plan, round_, row["client_id"]) - mine.theta
    if plan.clip is not None:
        delta = _clip(delta, plan)
    if plan.local_noise:  # every place gets its share
        whole = gaussian_distributed(net.size, plan.local_noise, plan.round_size, plan.seed + 1, round_, row["client_id"] & 0x7FFFFFFF)
        whole[at] += delta
        return np.arange(net.size), whole
    return at, delta


def client_updates(net: TwoTower, theta0: np.ndarray, rows: list[dict], plan: LocalPlan, round_: int, make_extra=None) -> Iterator[tuple[dict, tuple[np.ndarray, np.ndarray]]]:
    """Each client with its ``client_update``; local epochs without other losses or bounds between them run side by side."""
    if plan.method != "sgd" or make_extra is not None or plan.clip_each_step or plan.local_noise:
        for row in rows:
            yield row, client_update(net, theta0, row, plan, round_, make_extra(row, round_) if make_extra is not None else None)
        return
    tail = np.arange(net.layout.at["Ev"].stop, net.size)
    for group in in_groups(net, rows):
        for row, (mine, before) in zip(group, local_sgd_many(net, theta0, group, plan, round_), strict=True):
            delta = mine.theta - before
            yield row, (np.concatenate([_places(net, "Eu", mine.u_slots), _places(net, "Ev", mine.v_slots), tail]), _clip(delta, plan) if plan.clip is not None else delta)


def client_delta(net: TwoTower, theta0: np.ndarray, row: dict, plan: LocalPlan, round_: int, extra=None) -> np.ndarray:
    """``client_update`` as one vector."""
    at, values = client_update(net, theta0, row, plan, round_, extra)
    out = np.zeros(net.size)
    out[at] = values
    return out


def tune(net: TwoTower, theta: np.ndarray, row: dict, epochs: int, rate: float, batch: int = 32, seed: int = 42) -> Tuned | None:
    """Tuned parameters of one client, over the rows that its data names; nothing leaves it. None: the parameters as they are."""
    if epochs <= 0 or not row["items"]:
        return None
    mine, data, _ = compact(net, theta, client_batch(row))
    return replace(mine, theta=local_sgd(mine.net, mine.theta, data, LocalPlan(rate=rate, epochs=epochs, batch=batch, seed=seed), 1 << 30, row["client_id"]))


def _dense_parts(net: TwoTower) -> list[str]:
    """The layers that every client moves as a whole, in the order of the flat vector."""
    return [name for name in net.layout.shapes if name not in ("Eu", "Ev")]


def _rows_named(bags: Bags, owner: np.ndarray, stride: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owners, slots of the distinct rows in order of both, each bag cell's place among them); cells without weight take place 0."""
    held = bags.weights > 0
    keys, inverse = np.unique((owner[:, None] * stride + bags.slots)[held], return_inverse=True)
    at = np.zeros(bags.slots.shape, np.int64)
    at[held] = inverse
    return keys // stride, keys % stride, at


def _embed_many(table: np.ndarray, at: np.ndarray, fields: np.ndarray, weights: np.ndarray, n_fields: int) -> np.ndarray:
    """(rows, fields * width): the mean embedding of each field, side by side."""
    out, rows = np.zeros((len(at), n_fields, table.shape[1])), np.arange(len(at))
    for c in range(at.shape[1]):
        out[rows, fields[:, c]] += weights[:, c, None] * table[at[:, c]]
    return out.reshape(len(at), -1)


def _scatter_many(size: int, back: np.ndarray, at: np.ndarray, fields: np.ndarray, weights: np.ndarray, n_fields: int) -> np.ndarray:
    """The gradient of ``_embed_many`` by the table."""
    n, back = len(at), back.reshape(len(at), n_fields, -1)
    d, rows = back.shape[2], np.arange(n)
    held = weights > 0
    which = np.broadcast_to(rows[:, None], at.shape)[held]
    values = weights[held][:, None] * back[which, fields[held]]
    return np.bincount((at[held][:, None] * d + np.arange(d)).ravel(), values.ravel(), size * d).reshape(size, d)


def local_sgd_many(net: TwoTower, theta0: np.ndarray, rows: list[dict], plan: LocalPlan, round_: int) -> list[tuple[Tuned, np.ndarray]]:
    """``local_sgd`` of several clients side by side: for each its parameters over the rows that its data names, and what they were before.

    Clients take the same steps as alone; sums of a mini-batch may run in another order.
    """
    p, d = net.layout.views(theta0), net.width
    sizes = np.array([len(r["items"]) for r in rows])
    g, n_rows = len(rows), int(sizes.sum())
    ends = np.cumsum(sizes)
    starts, owner = ends - sizes, np.repeat(np.arange(g), sizes)
    items = Bags.of([x["f"] for r in rows for x in r["items"]], [x["s"] for r in rows for x in r["items"]])
    users = Bags.of([r["uf"] for r in rows], [r["us"] for r in rows])
    y = np.array([x["y"] for r in rows for x in r["items"]], float)
    u_owner, u_slots, u_at = _rows_named(users, np.arange(g), net.user_slots)
    v_owner, v_slots, v_at = _rows_named(items, owner, net.item_slots)
    eu, ev = p["Eu"][u_slots], p["Ev"][v_slots]
    dense = {name: np.repeat(p[name][None], g, axis=0) for name in _dense_parts(net)}
    wide = int(min(plan.batch, sizes.max(initial=0)))
    step, long = np.arange(wide), np.flatnonzero(sizes > plan.batch).tolist()
    order = np.arange(n_rows)
    for epoch in range(plan.epochs):
        for k in long:
            order[starts[k] : ends[k]] = starts[k] + generator(plan.seed, round_, rows[k]["client_id"] & 0x7FFFFFFF, epoch).permutation(int(sizes[k]))
        for first in range(0, int(sizes.max(initial=0)), plan.batch):
            left = np.clip(sizes - first, 0, plan.batch)
            live = np.flatnonzero(left)
            places = np.minimum(starts[live, None] + first + step, n_rows - 1)
            held = step < left[live, None]
            at = order[places].ravel()
            every = len(live) == g
            mine = dense if every else {name: x[live] for name, x in dense.items()}
            part = (v_at[at], items.fields[at], items.weights[at] * held.ravel()[:, None])
            mine_u = (u_at[live], users.fields[live], users.weights[live])
            xu, xv = _embed_many(eu, *mine_u, net.user_fields), _embed_many(ev, *part, net.item_fields).reshape(len(live), wide, -1)
            su, sv = (xu[:, None, :] @ mine["Wu"])[:, 0] + mine["bu"], xv @ mine["Wv"] + mine["bv"][:, None]
            au, av = activate(net.act, su), activate(net.act, sv)
            zs, ss = [np.concatenate([np.broadcast_to(au[:, None], av.shape), av], axis=2)], []
            for j in range(len(net.hidden)):
                ss.append(zs[-1] @ mine[f"W{j}"] + mine[f"b{j}"][:, None])
                zs.append(activate(net.act, ss[-1]))
            score = (zs[-1] @ mine["wo"][:, :, None])[:, :, 0] + mine["bo"]
            label = y[at].reshape(score.shape)
            error = (sigmoid(score) - label if net.out == "sigmoid" else 2 * (score - label)) * held / left[live, None]
            grad = {"wo": (error[:, None, :] @ zs[-1])[:, 0], "bo": error.sum(axis=1, keepdims=True)}
            back = error[:, :, None] * mine["wo"][:, None, :]
            for j in range(len(net.hidden) - 1, -1, -1):
                back = back * slope(net.act, ss[j], zs[j + 1])
                grad[f"W{j}"], grad[f"b{j}"] = zs[j].transpose(0, 2, 1) @ back, back.sum(axis=1)
                back = back @ mine[f"W{j}"].transpose(0, 2, 1)
            bu, bv = back[:, :, :d].sum(axis=1) * slope(net.act, su, au), back[:, :, d:] * slope(net.act, sv, av)
            grad["Wu"], grad["bu"] = xu[:, :, None] * bu[:, None, :], bu
            grad["Wv"], grad["bv"] = xv.transpose(0, 2, 1) @ bv, bv.sum(axis=1)
            into_u = (bu[:, None, :] @ mine["Wu"].transpose(0, 2, 1))[:, 0]
            into_v = (bv @ mine["Wv"].transpose(0, 2, 1)).reshape(len(at), -1)
            rate = plan.rate * plan.lam_sup
            eu -= rate * _scatter_many(len(eu), into_u, *mine_u, net.user_fields)
            ev -= rate * _scatter_many(len(ev), into_v, *part, net.item_fields)
            for name, change in grad.items():
                if every:
                    dense[name] -= rate * change
                else:
                    dense[name][live] -= rate * change
    tail = np.concatenate([dense[name].reshape(g, -1) for name in dense], axis=1)
    start = theta0[net.layout.at["Ev"].stop :]
    u_cut, v_cut = np.searchsorted(u_owner, np.arange(g + 1)), np.searchsorted(v_owner, np.arange(g + 1))
    out = []
    for k in range(g):
        u, v = slice(u_cut[k], u_cut[k + 1]), slice(v_cut[k], v_cut[k + 1])
        small = replace(net, user_slots=u.stop - u.start, item_slots=v.stop - v.start)
        before = np.concatenate([p["Eu"][u_slots[u]].ravel(), p["Ev"][v_slots[v]].ravel(), start])
        out.append((Tuned(small, np.concatenate([eu[u].ravel(), ev[v].ravel(), tail[k]]), u_slots[u], v_slots[v]), before))
    return out


def in_groups(net: TwoTower, rows: list[dict]) -> Iterator[list[dict]]:
    """Clients with about equally many rows together, as many as keep their layers and rows small."""
    dense = net.size - net.layout.at["Ev"].stop
    together = max(1, min(TOGETHER, HELD // max(1, dense)))
    near = sorted(rows, key=lambda r: len(r["items"]))
    for k in range(0, len(near), together):
        yield near[k : k + together]


def tune_many(net: TwoTower, theta: np.ndarray, rows: list[dict], epochs: int, rate: float, batch: int = 32, seed: int = 42) -> Iterator[tuple[dict, Tuned | None]]:
    """Each client with what ``tune`` gives for it."""
    if epochs <= 0:
        yield from ((r, None) for r in rows)
        return
    yield from ((r, None) for r in rows if not r["items"])
    plan = LocalPlan(rate=rate, epochs=epochs, batch=batch, seed=seed)
    for group in in_groups(net, [r for r in rows if r["items"]]):
        yield from zip(group, (mine for mine, _ in local_sgd_many(net, theta, group, plan, 1 << 30)), strict=True)


def personalise(net: TwoTower, theta: np.ndarray, row: dict, epochs: int, rate: float, batch: int = 32, seed: int = 42) -> np.ndarray:
    """Tuned parameters of one client; nothing leaves it. No epochs: the parameters as they are."""
    if epochs <= 0 or not row["items"]:
        return theta
    return local_sgd(net, theta, client_batch(row), LocalPlan(rate=rate, epochs=epochs, batch=batch, seed=seed), 1 << 30, row["client_id"])
