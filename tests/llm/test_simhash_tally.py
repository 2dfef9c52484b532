"""The count filter of the byte index: it rejects pairs, and long lists give the links that short ones give."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pytest

from fedlake.llm import simhash
from fedlake.llm.components import connected_components


def signed(values):
    return [int(v) - (1 << 64) if int(v) >= 1 << 63 else int(v) for v in values]


def roots(values, radius):
    root = {v: v for v in values}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(values, 2):
        if ((a ^ b) & (2**64 - 1)).bit_count() <= radius:
            x, y = top(a), top(b)
            root[max(x, y)] = min(x, y)
    return {v: top(v) for v in values}


@pytest.mark.parametrize("radius", range(5))
def test_two_groups_survive_any_changed_bytes(radius):
    groups = simhash._position_groups(radius)
    assert sorted(p for g in groups for p in g) == list(range(8))
    for changed in combinations(range(8), radius):
        assert sum(not set(g) & set(changed) for g in groups) >= 2


def test_the_tally_rejects_pairs_of_a_list():
    same = 0x1122334400000000  # four shared bytes put all of them into one list
    values = np.array([same, same | 0x01010000, same | 0x01010100, same | 0x03], np.uint64)
    assert simhash.list_links(values, 2, 6) == [(0, 1), (0, 3), (1, 2)]
    assert simhash.list_links(values, 2, 7) == [(0, 3), (1, 2)]


@pytest.mark.parametrize(("radius", "dense"), [(0, 512), (2, 512), (2, 2), (4, 2)])
def test_components_at_every_radius_and_list_length(spark, monkeypatch, radius, dense):
    monkeypatch.setattr(simhash, "DENSE_LIST", dense)
    r = np.random.default_rng(radius)
    values = [0, 2**64 - 1]
    for _ in range(12):
        v = int(r.integers(0, 2**63))
        for _ in range(5):
            values.append(v)
            for k in r.integers(0, 64, max(1, radius)):
                v ^= 1 << int(k)
    values += [0x5566 << 48 | int(x) << 8 for x in r.integers(0, 2**12, 60)]  # one crowded list
    values = signed(dict.fromkeys(values))
    links = simhash.fingerprint_links(spark.createDataFrame([(v,) for v in values], "fp long"), radius)
    got = {x.u: x.root for x in connected_components(links).collect()}
    assert {v: got.get(v, v) for v in values} == roots(values, radius)
