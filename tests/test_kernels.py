"""Gradients, Hessian-vector products and meta-learning rules of the numpy kernels."""

from __future__ import annotations

import numpy as np
import pytest

from fedlake.plans.baselines.central import pooled_step
from fedlake.plans.baselines.fcf import item_gradient, user_factor
from fedlake.plans.client import LocalPlan, client_delta, local_sgd, maml_gradient, personalise
from fedlake.plans.experiments import kernel_time
from fedlake.plans.nets import Bags, Batch, NeuralCF, SequenceEncoder, TwoTower, hessian_vector

R = np.random.default_rng(0)


def bag(n, slots, fields):
    return Bags.of([[k % fields for k in range(4)] for _ in range(n)], [list(R.integers(0, slots, 4)) for _ in range(n)])


def tower(act="relu", out="sigmoid"):
    net = TwoTower(10, 20, 2, 3, 4, (6, 5), act, out)
    return net, net.start(1) + R.standard_normal(net.size) * 0.1, Batch(bag(7, 10, 2), bag(7, 20, 3), R.integers(0, 2, 7).astype(float))


@pytest.mark.parametrize("act", ["relu", "sigmoid"])
@pytest.mark.parametrize("out", ["sigmoid", "linear"])
def test_tower_gradient(act, out):
    net, theta, batch = tower(act, out)
    v, h = R.standard_normal(net.size), 1e-6
    slope = (net.loss(theta + h * v, batch) - net.loss(theta - h * v, batch)) / (2 * h)
    assert abs(slope - net.gradient(theta, batch) @ v) < 1e-6 * max(1, abs(slope))
    hv = hessian_vector(lambda t: net.gradient(t, batch), theta, v)
    near = (net.gradient(theta + 1e-5 * v, batch) - net.gradient(theta - 1e-5 * v, batch)) / 2e-5
    assert np.abs(hv - near).max() < 1e-6


def test_item_scores_factorise():
    net, theta, batch = tower()
    user = batch.user.take([0])
    items = batch.item
    whole = net.forward(theta, Batch(user.repeat(7), items, batch.y))["score"]
    assert np.allclose(net.item_scores(theta, user, items, chunk=3), whole)


def test_ncf_gradient():
    net = NeuralCF(5, 6, 3, 4)
    theta, u, i, y = net.start(), R.integers(0, 5, 8), R.integers(0, 6, 8), R.integers(0, 2, 8).astype(float)
    v, h = R.standard_normal(net.size), 1e-6
    slope = (net.loss(theta + h * v, u, i, y) - net.loss(theta - h * v, u, i, y)) / (2 * h)
    assert abs(slope - net.gradient(theta, u, i, y) @ v) < 1e-6


@pytest.mark.parametrize("inside", [False, True])
def test_contrastive_gradients(inside):
    e = SequenceEncoder(20, 4, positive_in_denominator=inside)
    phi = e.start(2) + R.standard_normal(e.size) * 0.2
    view, target, negatives, segments = bag(5, 20, 3), bag(1, 20, 3), bag(4, 20, 3), [bag(2, 20, 3) for _ in range(3)]
    v, h = R.standard_normal(e.size), 1e-6
    for f in (lambda p: e.item_mask(p, view, target, negatives), lambda p: e.segment_mask(p, view, segments[0], segments[1:])):
        slope = (f(phi + h * v)[0] - f(phi - h * v)[0]) / (2 * h)
        assert abs(slope - f(phi)[1] @ v) < 1e-6 * max(1, abs(slope))


class Quadratic:
    """Loss of half the squared distance to the mean target; its Hessian is the identity."""

    size = 1

    def gradient(self, theta, batch):
        return theta - batch.y.mean()


def test_maml_on_a_quadratic():
    a, theta = 0.1, np.array([2.0])
    batch = Batch(bag(2, 5, 2), bag(2, 5, 2), np.array([1.0, 3.0]))
    support, query = 1.0, 3.0
    first = (1 - a) * (theta - support) + support - query
    assert np.allclose(maml_gradient(Quadratic(), theta, batch, LocalPlan(method="fomaml", rate=a)), first)
    assert np.allclose(maml_gradient(Quadratic(), theta, batch, LocalPlan(method="maml", rate=a)), (1 - a) * first)


def row_of(batch: Batch, client=1):
    items = [{"f": f.tolist(), "s": s.tolist(), "y": y} for f, s, y in zip(batch.item.fields, batch.item.slots, batch.y, strict=True)]
    return {"client_id": client, "uf": batch.user.fields[0].tolist(), "us": batch.user.slots[0].tolist(), "items": items}


def test_one_round_of_one_step_is_a_pooled_step():
    net, theta, batch = tower()
    rows = [row_of(Batch(batch.user.take([0]).repeat(4), batch.item.take(range(4)), batch.y[:4]), 1), row_of(Batch(batch.user.take([1]).repeat(3), batch.item.take(range(4, 7)), batch.y[4:]), 2)]
    plan = LocalPlan(method="one_step", rate=0.3)
    from fedlake.plans.client import client_batch

    weighted = sum(client_delta(net, theta, r, plan, 0) * len(r["items"]) for r in rows) / 7
    assert np.allclose(theta + weighted, pooled_step(net, theta, [client_batch(r) for r in rows], 0.3))
    full = LocalPlan(epochs=1, batch=100, rate=0.3)
    assert np.allclose(client_delta(net, theta, rows[0], full, 0), client_delta(net, theta, rows[0], plan, 0))


def test_local_update_limits():
    net, theta, batch = tower()
    row = row_of(batch)
    assert np.abs(client_delta(net, theta, row, LocalPlan(rate=0.0), 0)).max() == 0
    assert personalise(net, theta, row, 0, 0.1) is theta
    assert np.linalg.norm(client_delta(net, theta, row, LocalPlan(rate=1.0, epochs=5, clip=0.01), 0)) <= 0.01 * (1 + 1e-12)
    assert np.array_equal(local_sgd(net, theta, batch, LocalPlan(), 3, 9), local_sgd(net, theta, batch, LocalPlan(), 3, 9))
    each = client_delta(net, theta, row, LocalPlan(rate=1.0, epochs=5, clip=0.01, clip_each_step=True), 0)
    assert np.linalg.norm(each) <= 0.01 * (1 + 1e-12)


def test_factor_model_closed_form():
    q, y, c = R.standard_normal((6, 2)), R.integers(0, 2, 6).astype(float), 1 + R.random(6)
    x = user_factor(q, y, c, 0.1)
    assert np.allclose(q.T @ (c * (q @ x - y)) + 0.1 * x, 0)
    assert item_gradient(q, x, y, c).shape == q.shape


def test_second_order_costs_more():
    net, _, batch = tower()
    t = kernel_time(net, [batch] * 20, 3)
    assert t["maml"] > t["fomaml"]
