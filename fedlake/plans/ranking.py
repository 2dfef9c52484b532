"""Scores of the whole catalogue for one user's parameters, without work that users or items share.

Items with the same side features share their part of the item encoder's first
layer: it is computed once for each distinct set of side slots, and only an
item's own id embedding is added per item. Tuning moves the dense layers and the
rows that the user's data names, so those few rows are replaced, not the tables.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from fedlake.operators import scoring
from fedlake.plans.client import Tuned
from fedlake.plans.nets import Bags, TwoTower, activate

#: Items scored at a time: their layers stay in the processor's cache.
CHUNK = 4096
#: Chunks scored one by one before the whole catalogue is; a share of the largest score that is far above its rounding.
PROBES, MARGIN = 8, 1e-9
#: Items that are compared before any chunk is: high under the untuned parameters, so above most positives of most users.
WITNESSES = 256


@dataclass
class ItemTable:
    """The catalogue in order of number: each item's id slot and field, and which distinct set of side slots it has."""

    ids: np.ndarray
    own_slot: np.ndarray
    own_field: int
    which: np.ndarray
    sides: Bags

    @classmethod
    def of(cls, ids: np.ndarray, fields: pa.ListArray, slots: pa.ListArray) -> ItemTable:
        """The last slot of an item is its id."""
        n, sizes = len(ids), np.asarray(pc.list_value_length(slots))
        f, s = np.asarray(fields.flatten()), np.asarray(slots.flatten())
        ends = np.cumsum(sizes)
        own = ends - 1
        width = max(int(sizes.max(initial=1)) - 1, 0)
        held = np.arange(width) < (sizes - 1)[:, None]
        rest = np.ones(len(s), bool)
        rest[own] = False
        wide = np.full((n, 2 * width), -1, np.int32)
        wide[:, :width][held], wide[:, width:][held] = f[rest], s[rest]
        if width:
            keys = np.ascontiguousarray(wide).view(np.dtype((np.void, 8 * width))).ravel()
            _, first, which = np.unique(keys, return_index=True, return_inverse=True)
        else:
            first, which = np.zeros(min(n, 1), np.int64), np.zeros(n, np.int64)
        distinct, kept = wide[first], held[first]
        sides = Bags.of([r[:width][k].tolist() for r, k in zip(distinct, kept, strict=True)], [r[width:][k].tolist() for r, k in zip(distinct, kept, strict=True)])
        return cls(ids, s[own].astype(np.int64), int(f[own[0]]) if n else 0, which.astype(np.int32), sides)

    def __len__(self) -> int:
        return len(self.ids)


class Scorer:
    """Scores of all items under ``theta`` with the rows that a user has tuned put in."""

    def __init__(self, net: TwoTower, theta: np.ndarray, table: ItemTable):
        self.net, self.theta, self.table, self.witnesses = net, theta, table, None
        self.own = net.layout.view(theta, "Ev")[table.own_slot]
        self.at_own = np.full(net.item_slots, -1, np.int64)
        self.at_own[table.own_slot] = np.arange(len(table))
        stride = net.item_slots
        self.pairs, self.column = np.unique(table.sides.fields * stride + table.sides.slots, return_inverse=True)
        self.column = self.column.reshape(table.sides.slots.shape)
        self.pair_field, self.pair_slot = self.pairs // stride, self.pairs % stride

    def _sides(self, wv: np.ndarray, bv: np.ndarray, ev: np.ndarray) -> np.ndarray:
        """The side slots' part of the item encoder before its activation, for each distinct set."""
        d = self.net.width
        part = np.empty((len(self.pairs), d))
        for f in np.unique(self.pair_field):
            mine = self.pair_field == f
            part[mine] = ev[mine] @ wv[f * d : (f + 1) * d]
        out = np.repeat(bv[None, :], len(self.table.sides), axis=0)
        for c in range(self.column.shape[1]):
            out += self.table.sides.weights[:, c, None] * part[self.column[:, c]]
        return out

    def all_below(self, user: Bags, tuned: Tuned | None, own: np.ndarray, seen: np.ndarray, most: int) -> bool:
        """Whether some items of the catalogue already hold ``most`` unseen items above each of ``own``, by more than rounding: all their ranks are beyond ``most`` then.

        False leaves it open; ``scores`` of the whole catalogue decide.
        """
        score = self._scorer(user, tuned)
        mine = score(own)
        if not np.isfinite(mine).all():
            return False
        open_ = np.ones(len(own), bool)
        if self.witnesses is None:  # the best items of the untuned parameters, for whichever user comes first
            self.witnesses = np.sort(scoring.best_places(self.scores(user), self.table.ids, WITNESSES))
        first = self._surely_above(score, np.setdiff1d(self.witnesses, seen, assume_unique=True), mine)
        if first is None:
            return False
        open_ &= first < most
        above = np.zeros(len(own), np.int64)
        for k in range(0, min(len(self.table), PROBES * CHUNK), CHUNK):
            if not open_.any():
                return True
            found = self._surely_above(score, np.setdiff1d(np.arange(k, min(k + CHUNK, len(self.table))), seen, assume_unique=True), mine)
            if found is None:
                return False
            above += found
            open_ &= above < most
        return not open_.any()

    @staticmethod
    def _surely_above(score, at: np.ndarray, mine: np.ndarray) -> np.ndarray | None:
        """How many of the places score above each of ``mine`` by more than rounding; None where a score isn't finite."""
        found = score(at)
        if not np.isfinite(found).all():
            return None
        tolerance = MARGIN * max(1.0, float(np.abs(found).max(initial=0.0)), float(np.abs(mine).max(initial=0.0)))
        return len(found) - np.searchsorted(np.sort(found), mine + tolerance, "right")

    def _scorer(self, user: Bags, tuned: Tuned | None):
        """A function of places: the scores of only those items, equal to ``scores`` there up to rounding."""
        net, t, d = self.net, self.table, self.net.width
        p, base = net.layout.views(self.theta), net.layout.view(self.theta, "Ev")
        ev, layers, replaced = base[self.pair_slot], p, None
        if tuned is not None:
            layers = tuned.net.layout.views(tuned.theta)
            known = np.minimum(np.searchsorted(tuned.v_slots, self.pair_slot), len(tuned.v_slots) - 1)
            hit = tuned.v_slots[known] == self.pair_slot
            ev[hit] = layers["Ev"][known[hit]]
            user = Bags(np.searchsorted(tuned.u_slots, user.slots), user.fields, user.weights)
            replaced = tuned.v_slots
        u = activate(net.act, user.embed(layers["Eu"], net.user_fields) @ layers["Wu"] + layers["bu"])
        part = np.empty((len(self.pairs), d))
        for f in np.unique(self.pair_field):
            here = self.pair_field == f
            part[here] = ev[here] @ layers["Wv"][f * d : (f + 1) * d]
        w_own = layers["Wv"][t.own_field * d : (t.own_field + 1) * d]

        def score(at: np.ndarray) -> np.ndarray:
            rows = self.own[at]
            if replaced is not None:
                known = np.minimum(np.searchsorted(replaced, t.own_slot[at]), len(replaced) - 1)
                hit = replaced[known] == t.own_slot[at]
                rows[hit] = layers["Ev"][known[hit]]
            z = rows @ w_own + layers["bv"]
            which = t.which[at]
            for c in range(self.column.shape[1]):
                z += t.sides.weights[which, c, None] * part[self.column[which, c]]
            z = _active(net.act, z)
            z = np.concatenate([np.repeat(u, len(z), axis=0), z], axis=1)
            for j in range(len(net.hidden)):
                z = _active(net.act, z @ layers[f"W{j}"] + layers[f"b{j}"])
            return z @ layers["wo"] + layers["bo"][0]

        return score

    def scores(self, user: Bags, tuned: Tuned | None = None) -> np.ndarray:
        net, t, d = self.net, self.table, self.net.width
        p, base = net.layout.views(self.theta), net.layout.view(self.theta, "Ev")
        ev = base[self.pair_slot]
        layers, moved = p, np.zeros(0, np.int64)
        if tuned is not None:
            layers = tuned.net.layout.views(tuned.theta)
            known = np.minimum(np.searchsorted(tuned.v_slots, self.pair_slot), len(tuned.v_slots) - 1)
            hit = tuned.v_slots[known] == self.pair_slot
            ev[hit] = layers["Ev"][known[hit]]
            moved = np.flatnonzero(self.at_own[tuned.v_slots] >= 0)
            user = Bags(np.searchsorted(tuned.u_slots, user.slots), user.fields, user.weights)
        u = activate(net.act, user.embed(layers["Eu"], net.user_fields) @ layers["Wu"] + layers["bu"])
        side = self._sides(layers["Wv"], layers["bv"], ev)
        w_own = layers["Wv"][t.own_field * d : (t.own_field + 1) * d]
        places = self.at_own[tuned.v_slots[moved]] if len(moved) else moved
        before = self.own[places]
        if len(moved):
            self.own[places] = layers["Ev"][moved]
        out = np.empty(len(t))
        if net.hidden:
            first, shift = np.ascontiguousarray(layers["W0"][d:]), u @ layers["W0"][:d] + layers["b0"]
        for k in range(0, len(t), CHUNK):
            v = self.own[k : k + CHUNK] @ w_own
            v += side[t.which[k : k + CHUNK]]
            v = _active(net.act, v)
            if net.hidden:
                z = v @ first
                z += shift
                z = _active(net.act, z)
                for j in range(1, len(net.hidden)):
                    z = _active(net.act, z @ layers[f"W{j}"] + layers[f"b{j}"])
            else:
                z = np.concatenate([np.repeat(u, len(v), axis=0), v], axis=1)
            out[k : k + CHUNK] = z @ layers["wo"]
        self.own[places] = before
        out += layers["bo"][0]
        return out


def _active(kind: str, x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0, out=x) if kind == "relu" else activate(kind, x)
