"""Masked views of one pass against each view alone."""

from __future__ import annotations

import numpy as np
import pytest

from fedlake.operators.dp import generator
from fedlake.plans import pretrain as P
from fedlake.plans.nets import SequenceEncoder

RNG = np.random.default_rng(4)


def _item(k: int) -> dict:
    return {"item_no": k, "f": [0, 1, 2] if k % 3 else [0, 2], "s": [k % 4, 4 + k % 5, 9 + k] if k % 3 else [k % 4, 9 + k]}


@pytest.mark.parametrize("lengths", [[3], [20, 3, 7], [5, 5, 12, 1, 4]])
@pytest.mark.parametrize("within", [False, True])
def test_one_pass_equals_each_view(lengths, within):
    encoder = SequenceEncoder(60, 6, positive_in_denominator=within)
    phi = encoder.start(2) + RNG.standard_normal(encoder.size) * 0.2
    sessions = [{"session_id": n, "seq": [_item(int(k)) for k in RNG.integers(50, size=size)]} for n, size in enumerate(lengths)]
    views = list(P._views(sessions, 0.5, 0.25, generator(1, 2), [_item(k) for k in range(50)]))
    assert {v[0] for v in views} == {"item_mask", "segment_mask"}
    loss, grad = 0.0, np.zeros_like(phi)
    for name, weight, bags in views:
        one, g = getattr(encoder, name)(phi, *bags)
        loss, grad = loss + weight * one, grad + weight * g
    found, other = encoder.masks(phi, views)
    assert found == pytest.approx(loss, rel=1e-12) and np.allclose(other, grad, rtol=0, atol=1e-12)


def test_update_equals_gradient():
    encoder = SequenceEncoder(60, 6)
    phi, head = encoder.start(2), encoder.layout.at["Ev"].stop
    sessions = [{"session_id": n, "seq": [_item(int(k)) for k in RNG.integers(50, size=size)]} for n, size in enumerate([9, 4])]
    for some in (sessions, sessions[:0]):
        loss, whole = P.ssl_gradient(encoder, phi, some, 0.5, 0.25, generator(1, 2), [_item(k) for k in range(50)])
        found, slots, rows, rest = P.ssl_update(encoder, encoder.layout.view(phi, "Ev"), phi[head:], some, 0.5, 0.25, generator(1, 2), [_item(k) for k in range(50)])
        assert found == pytest.approx(loss, rel=1e-12) and np.allclose(whole[:head].reshape(-1, 6)[slots].ravel(), rows, rtol=0, atol=1e-12)
        assert np.allclose(whole[head:], rest, rtol=0, atol=1e-12)
