"""Network kernels in numpy with hand-written gradients.

Every network works on one flat parameter vector. All operations are analytic
(rectifiers switch on the real part), so a Hessian-vector product is the
imaginary part of a gradient at ``theta + i h v``.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import chain

import numpy as np


class Layout:
    """Named tensors in one flat vector."""

    def __init__(self, shapes: list[tuple[str, tuple[int, ...]]]):
        self.shapes = dict(shapes)
        self.at, n = {}, 0
        for name, shape in shapes:
            size = int(np.prod(shape))
            self.at[name] = slice(n, n + size)
            n += size
        self.size = n

    def view(self, flat: np.ndarray, name: str) -> np.ndarray:
        return flat[self.at[name]].reshape(self.shapes[name])

    def views(self, flat: np.ndarray) -> dict[str, np.ndarray]:
        return {name: self.view(flat, name) for name in self.shapes}


@dataclass
class Bags:
    """One side of a batch: slots by row and column with the field and weight of each; padding has weight 0."""

    slots: np.ndarray
    fields: np.ndarray
    weights: np.ndarray

    @classmethod
    def of(cls, fields: list[list[int]], slots: list[list[int]]) -> Bags:
        n = len(slots)
        sizes = np.fromiter(map(len, slots), np.int64, n)
        width, total = int(sizes.max(initial=0)), int(sizes.sum())
        s, f, w = np.zeros((n, width), np.int64), np.zeros((n, width), np.int64), np.zeros((n, width))
        held = np.arange(width) < sizes[:, None]
        s[held] = np.fromiter(chain.from_iterable(slots), np.int64, total)
        f[held] = np.fromiter(chain.from_iterable(fields), np.int64, total)
        if total:
            key = (np.arange(n)[:, None] * (int(f.max()) + 1) + f)[held]
            w[held] = 1 / np.bincount(key)[key]
        return cls(s, f, w)

    def __len__(self) -> int:
        return len(self.slots)

    def take(self, rows) -> Bags:
        return Bags(self.slots[rows], self.fields[rows], self.weights[rows])

    def repeat(self, n: int) -> Bags:
        return self.take(np.zeros(n, np.int64))

    def embed(self, table: np.ndarray, n_fields: int) -> np.ndarray:
        """(rows, fields * width): the mean embedding of each field, side by side."""
        out = np.zeros((len(self), n_fields, table.shape[1]), table.dtype)
        rows = np.arange(len(self))
        for c in range(self.slots.shape[1]):
            out[rows, self.fields[:, c]] += self.weights[:, c, None] * table[self.slots[:, c]]
        return out.reshape(len(self), -1)

    def scatter(self, grad_table: np.ndarray, back: np.ndarray, n_fields: int) -> None:
        """Adds the gradient of ``embed`` into the table's gradient."""
        back = back.reshape(len(self), n_fields, -1)
        rows = np.arange(len(self))
        for c in range(self.slots.shape[1]):
            np.add.at(grad_table, self.slots[:, c], self.weights[:, c, None] * back[rows, self.fields[:, c]])


@dataclass
class Batch:
    user: Bags
    item: Bags
    y: np.ndarray

    def __len__(self) -> int:
        return len(self.y)

    def take(self, rows) -> Batch:
        return Batch(self.user.take(rows), self.item.take(rows), self.y[rows])


def sigmoid(x: np.ndarray) -> np.ndarray:
    """Logistic function; real arguments are held where its exponential is finite."""
    return 1 / (1 + np.exp(-x)) if np.iscomplexobj(x) else 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def activate(kind: str, x: np.ndarray) -> np.ndarray:
    return np.where(x.real > 0, x, 0) if kind == "relu" else sigmoid(x)


def slope(kind: str, x: np.ndarray, a: np.ndarray) -> np.ndarray:
    return (x.real > 0).astype(float) if kind == "relu" else a * (1 - a)


@dataclass
class TwoTower:
    """Two side encoders, their concatenation, a perceptron and one output unit."""

    user_slots: int
    item_slots: int
    user_fields: int
    item_fields: int
    width: int = 8
    hidden: tuple[int, ...] = (16,)
    act: str = "relu"
    out: str = "sigmoid"

    def __post_init__(self):
        d = self.width
        shapes = [("Eu", (self.user_slots, d)), ("Ev", (self.item_slots, d)), ("Wu", (self.user_fields * d, d)), ("bu", (d,)), ("Wv", (self.item_fields * d, d)), ("bv", (d,))]
        last = 2 * d
        for k, h in enumerate(self.hidden):
            shapes += [(f"W{k}", (last, h)), (f"b{k}", (h,))]
            last = h
        shapes += [("wo", (last,)), ("bo", (1,))]
        self.layout = Layout(shapes)

    @property
    def size(self) -> int:
        return self.layout.size

    def start(self, seed: int = 42) -> np.ndarray:
        r = np.random.default_rng(seed)
        theta = np.zeros(self.size)
        for name, shape in self.layout.shapes.items():
            if name[0] in "EWw":
                spread = 0.05 if name[0] == "E" else 1 / np.sqrt(shape[0])
                self.layout.view(theta, name)[...] = r.standard_normal(shape) * spread
        return theta

    def forward(self, theta: np.ndarray, batch: Batch) -> dict:
        p = self.layout.views(theta)
        xu, xv = batch.user.embed(p["Eu"], self.user_fields), batch.item.embed(p["Ev"], self.item_fields)
        su, sv = xu @ p["Wu"] + p["bu"], xv @ p["Wv"] + p["bv"]
        z = np.concatenate([activate(self.act, su), activate(self.act, sv)], axis=1)
        zs, ss = [z], []
        for k in range(len(self.hidden)):
            ss.append(zs[-1] @ p[f"W{k}"] + p[f"b{k}"])
            zs.append(activate(self.act, ss[-1]))
        score = zs[-1] @ p["wo"] + p["bo"][0]
        return {"p": p, "xu": xu, "xv": xv, "su": su, "sv": sv, "zs": zs, "ss": ss, "score": score}

    def predict(self, theta: np.ndarray, batch: Batch) -> np.ndarray:
        s = self.forward(theta, batch)["score"]
        return sigmoid(s) if self.out == "sigmoid" else s

    def loss(self, theta: np.ndarray, batch: Batch) -> float:
        s = self.forward(theta, batch)["score"]
        if self.out == "sigmoid":
            return float(np.mean(np.logaddexp(0, s) - batch.y * s))
        return float(np.mean((s - batch.y) ** 2))

    def gradient(self, theta: np.ndarray, batch: Batch) -> np.ndarray:
        """Of the mean loss over the batch."""
        f = self.forward(theta, batch)
        p, n = f["p"], max(1, len(batch))
        g = np.zeros(self.size, theta.dtype)
        v = self.layout.views(g)
        s = f["score"]
        d = ((sigmoid(s) - batch.y) if self.out == "sigmoid" else 2 * (s - batch.y)) / n
        v["wo"][...], v["bo"][0] = f["zs"][-1].T @ d, d.sum()
        back = d[:, None] * p["wo"][None, :]
        for k in range(len(self.hidden) - 1, -1, -1):
            back = back * slope(self.act, f["ss"][k], f["zs"][k + 1])
            v[f"W{k}"][...], v[f"b{k}"][...] = f["zs"][k].T @ back, back.sum(axis=0)
            back = back @ p[f"W{k}"].T
        w = self.width
        for side, x, s, a, part in (("u", f["xu"], f["su"], f["zs"][0][:, :w], back[:, :w]), ("v", f["xv"], f["sv"], f["zs"][0][:, w:], back[:, w:])):
            part = part * slope(self.act, s, a)
            v[f"W{side}"][...], v[f"b{side}"][...] = x.T @ part, part.sum(axis=0)
            into = part @ p[f"W{side}"].T
            (batch.user if side == "u" else batch.item).scatter(v[f"E{side}"], into, self.user_fields if side == "u" else self.item_fields)
        return g

    def item_scores(self, theta: np.ndarray, user: Bags, items: Bags, chunk: int = 8192) -> np.ndarray:
        """Scores of one user for many items: the user's half of the first layer is computed once."""
        p = self.layout.views(theta)
        u = activate(self.act, user.embed(p["Eu"], self.user_fields) @ p["Wu"] + p["bu"])
        w, out = self.width, np.empty(len(items))
        for k in range(0, len(items), chunk):
            part = items.take(slice(k, k + chunk))
            v = activate(self.act, part.embed(p["Ev"], self.item_fields) @ p["Wv"] + p["bv"])
            if self.hidden:
                z = activate(self.act, u @ p["W0"][:w] + v @ p["W0"][w:] + p["b0"])
                for j in range(1, len(self.hidden)):
                    z = activate(self.act, z @ p[f"W{j}"] + p[f"b{j}"])
            else:
                z = np.concatenate([np.repeat(u, len(v), axis=0), v], axis=1)
            out[k : k + chunk] = z @ p["wo"] + p["bo"][0]
        return out


@dataclass
class NeuralCF:
    """Collaborative filtering on user and item ids: an element-wise product branch and a perceptron branch."""

    users: int
    items: int
    width: int = 8
    hidden: int = 16

    def __post_init__(self):
        d, h = self.width, self.hidden
        self.layout = Layout([("P", (self.users, d)), ("Q", (self.items, d)), ("A", (self.users, d)), ("B", (self.items, d)), ("W", (2 * d, h)), ("b", (h,)), ("w", (d + h,)), ("c", (1,))])

    @property
    def size(self) -> int:
        return self.layout.size

    def start(self, seed: int = 42) -> np.ndarray:
        r = np.random.default_rng(seed)
        theta = r.standard_normal(self.size) * 0.1
        for name in ("b", "c"):
            self.layout.view(theta, name)[...] = 0
        return theta

    def _forward(self, p, u, i):
        prod = p["P"][u] * p["Q"][i]
        x = np.concatenate([p["A"][u], p["B"][i]], axis=1)
        s = x @ p["W"] + p["b"]
        h = activate("relu", s)
        return prod, x, s, h, np.concatenate([prod, h], axis=1) @ p["w"] + p["c"][0]

    def scores(self, theta, u, i) -> np.ndarray:
        return self._forward(self.layout.views(theta), u, i)[-1]

    def loss(self, theta, u, i, y) -> float:
        s = self.scores(theta, u, i)
        return float(np.mean(np.logaddexp(0, s) - y * s))

    def gradient(self, theta, u, i, y) -> np.ndarray:
        p = self.layout.views(theta)
        prod, x, s, h, score = self._forward(p, u, i)
        g = np.zeros(self.size, theta.dtype)
        v = self.layout.views(g)
        d = (sigmoid(score) - y) / max(1, len(y))
        v["w"][...], v["c"][0] = np.concatenate([prod, h], axis=1).T @ d, d.sum()
        w = self.width
        dp = d[:, None] * p["w"][None, :w]
        np.add.at(v["P"], u, dp * p["Q"][i])
        np.add.at(v["Q"], i, dp * p["P"][u])
        dh = d[:, None] * p["w"][None, w:] * slope("relu", s, h)
        v["W"][...], v["b"][...] = x.T @ dh, dh.sum(axis=0)
        dx = dh @ p["W"].T
        np.add.at(v["A"], u, dx[:, :w])
        np.add.at(v["B"], i, dx[:, w:])
        return g


@dataclass
class SequenceEncoder:
    """Self-supervised part: a feed-forward item encoder and a gated recurrent encoder, with contrastive losses.

    Shares the item embedding table ``Ev`` with the recommender; parameters are
    ``Ev`` first, then the encoders.
    """

    item_slots: int
    width: int = 8
    positive_in_denominator: bool = False
    normalise: bool = False

    def __post_init__(self):
        d = self.width
        self.layout = Layout([("Ev", (self.item_slots, d)), ("Wi", (d, d)), ("bi", (d,)), ("Wz", (2 * d, d)), ("bz", (d,)), ("Wr", (2 * d, d)), ("br", (d,)), ("Wh", (2 * d, d)), ("bh", (d,))])

    @property
    def size(self) -> int:
        return self.layout.size

    def start(self, seed: int = 7) -> np.ndarray:
        r = np.random.default_rng(seed)
        theta = np.zeros(self.size)
        for name, shape in self.layout.shapes.items():
            if name[0] in "EW":
                self.layout.view(theta, name)[...] = r.standard_normal(shape) * (0.05 if name == "Ev" else 1 / np.sqrt(shape[0]))
        return theta

    def items(self, p, bags: Bags):
        """Item vectors: mean of the slots' embeddings, one tanh layer."""
        x = Bags(bags.slots, bags.fields * 0, bags.weights / np.maximum(bags.weights.sum(axis=1, keepdims=True), 1e-12)).embed(p["Ev"], 1)
        return x, np.tanh(x @ p["Wi"] + p["bi"])

    def items_back(self, p, v, bags: Bags, x, e, d):
        d = d * (1 - e * e)
        v["Wi"] += x.T @ d
        v["bi"] += d.sum(axis=0)
        Bags(bags.slots, bags.fields * 0, bags.weights / np.maximum(bags.weights.sum(axis=1, keepdims=True), 1e-12)).scatter(v["Ev"], d @ p["Wi"].T, 1)

    def run(self, p, xs: np.ndarray):
        """xs: (batch, time, width) to the last hidden state and what the way back needs."""
        h = np.zeros((len(xs), self.width), xs.dtype)
        steps = []
        for t in range(xs.shape[1]):
            c = np.concatenate([xs[:, t], h], axis=1)
            z = sigmoid(c @ p["Wz"] + p["bz"])
            r = sigmoid(c @ p["Wr"] + p["br"])
            c2 = np.concatenate([xs[:, t], r * h], axis=1)
            n = np.tanh(c2 @ p["Wh"] + p["bh"])
            steps.append((c, z, r, c2, n, h))
            h = (1 - z) * h + z * n
        return h, steps

    def run_back(self, p, v, steps, dh):
        d = self.width
        out = []
        for c, z, r, c2, n, h in reversed(steps):
            dn, dz = dh * z * (1 - n * n), dh * (n - h) * z * (1 - z)
            v["Wh"] += c2.T @ dn
            v["bh"] += dn.sum(axis=0)
            dc2 = dn @ p["Wh"].T
            dr = dc2[:, d:] * h * r * (1 - r)
            v["Wz"] += c.T @ dz
            v["bz"] += dz.sum(axis=0)
            v["Wr"] += c.T @ dr
            v["br"] += dr.sum(axis=0)
            dc = dz @ p["Wz"].T + dr @ p["Wr"].T
            out.append(dc2[:, :d] + dc[:, :d])
            dh = dh * (1 - z) + dc2[:, d:] * r + dc[:, d:]
        return np.stack(out[::-1], axis=1)

    def _contrast(self, anchor, positive, negatives):
        """Loss and gradients of one view: anchor (d), positive (d), negatives (J, d)."""
        sp, sn = anchor @ positive, negatives @ anchor
        every = np.concatenate([[sp], sn]) if self.positive_in_denominator else sn
        top = every.max() if len(every) else 0.0
        e = np.exp(every - top)
        w = e / e.sum()
        loss = -sp + top + np.log(e.sum())
        wp, wn = (w[0], w[1:]) if self.positive_in_denominator else (0.0, w)
        return loss, (wp - 1) * positive + wn @ negatives, (wp - 1) * anchor, wn[:, None] * anchor[None, :]

    def item_mask(self, theta, view: Bags, target: Bags, negatives: Bags):
        """(loss, gradient): view (T items), target (1 item), negatives (J items)."""
        p, g = self.layout.views(theta), np.zeros(self.size)
        v = self.layout.views(g)
        sides = [self.items(p, b) for b in (view, target, negatives)]
        h, steps = self.run(p, sides[0][1][None])
        loss, da, dp, dn = self._contrast(h[0], sides[1][1][0], sides[2][1])
        dx = self.run_back(p, v, steps, da[None])[0]
        for bags, (x, e), d in zip((view, target, negatives), sides, (dx, dp[None], dn), strict=True):
            self.items_back(p, v, bags, x, e, d)
        return float(loss), g

    def segment_mask(self, theta, view: Bags, segment: Bags, negatives: list[Bags]):
        """(loss, gradient): both sides go through the sequence encoder."""
        p, g = self.layout.views(theta), np.zeros(self.size)
        v = self.layout.views(g)
        runs = []
        for bags in (view, segment, *negatives):
            x, e = self.items(p, bags)
            h, steps = self.run(p, e[None])
            runs.append((bags, x, e, h[0], steps))
        loss, da, dp, dn = self._contrast(runs[0][3], runs[1][3], np.array([r[3] for r in runs[2:]]))
        for (bags, x, e, _, steps), d in zip(runs, [da, dp, *dn], strict=True):
            self.items_back(p, v, bags, x, e, self.run_back(p, v, steps, d[None])[0])
        return float(loss), g


    def masks(self, theta, views: list[tuple[str, float, tuple]]):
        """(loss, gradient) of weighted views (name, weight, bags), ``item_mask`` and ``segment_mask`` of all of them in one pass.

        All bags are one table; sequences run side by side, the longest first, so those that still run are the first ones.
        """
        p, g, d = self.layout.views(theta), np.zeros(self.size), self.width
        v = self.layout.views(g)
        if not views:
            return 0.0, g
        each = [[b for x in bags for b in (x if isinstance(x, list) else [x])] for _, _, bags in views]
        every = [b for bags in each for b in bags]
        sizes = np.array([len(b) for b in every])
        starts, wide = np.cumsum(sizes) - sizes, max(b.slots.shape[1] for b in every)
        slots, weights = np.zeros((int(sizes.sum()), wide), np.int64), np.zeros((int(sizes.sum()), wide))
        for b, k in zip(every, starts.tolist(), strict=True):
            slots[k : k + len(b), : b.slots.shape[1]], weights[k : k + len(b), : b.slots.shape[1]] = b.slots, b.weights
        weights /= np.maximum(weights.sum(axis=1, keepdims=True), 1e-12)
        x = np.zeros((len(slots), d))
        for c in range(wide):
            x += weights[:, c, None] * p["Ev"][slots[:, c]]
        e = np.tanh(x @ p["Wi"] + p["bi"])
        first = np.cumsum([0, *map(len, each)])
        run = [int(k) for (name, _, _), low, high in zip(views, first[:-1], first[1:], strict=True) for k in range(low, low + 1 if name == "item_mask" else high)]
        run.sort(key=lambda k: -int(sizes[k]))
        place, long = {k: n for n, k in enumerate(run)}, sizes[run]
        at = starts[run][:, None] + np.arange(long[0])
        live = [int((long > t).sum()) for t in range(long[0])]
        gates, shift = np.concatenate([p["Wz"], p["Wr"]], axis=1), np.concatenate([p["bz"], p["br"]])
        h, steps = np.zeros((len(run), d)), []
        for t, m in enumerate(live):
            mine, before = e[at[:m, t]], h[:m].copy()
            c = np.concatenate([mine, before], axis=1)
            zr = sigmoid(c @ gates + shift)
            z, r = zr[:, :d], zr[:, d:]
            c2 = np.concatenate([mine, r * before], axis=1)
            n = np.tanh(c2 @ p["Wh"] + p["bh"])
            h[:m] = (1 - z) * before + z * n
            steps.append((c, z, r, c2, n, before))
        loss, dh, de = 0.0, np.zeros_like(h), np.zeros_like(e)
        for (name, weight, _), low, high in zip(views, first[:-1], first[1:], strict=True):
            if name == "item_mask":
                target, others = starts[low + 1], slice(starts[low + 2], starts[low + 2] + sizes[low + 2])
                one, da, dp, dn = self._contrast(h[place[low]], e[target], e[others])
                de[target] += weight * dp
                de[others] += weight * dn
            else:
                rest = [place[k] for k in range(low + 2, high)]
                one, da, dp, dn = self._contrast(h[place[low]], h[place[low + 1]], h[rest])
                dh[place[low + 1]] += weight * dp
                dh[rest] += weight * dn
            dh[place[low]] += weight * da
            loss += weight * one
        turned, turned_h = gates.T.copy(), p["Wh"].T.copy()
        for t in range(len(live) - 1, -1, -1):
            m, (c, z, r, c2, n, before) = live[t], steps[t]
            back = dh[:m]
            dn, dz = back * z * (1 - n * n), back * (n - before) * z * (1 - z)
            v["Wh"] += c2.T @ dn
            v["bh"] += dn.sum(axis=0)
            dc2 = dn @ turned_h
            dzr = np.concatenate([dz, dc2[:, d:] * before * r * (1 - r)], axis=1)
            both, sums = c.T @ dzr, dzr.sum(axis=0)
            v["Wz"] += both[:, :d]
            v["Wr"] += both[:, d:]
            v["bz"] += sums[:d]
            v["br"] += sums[d:]
            dc = dzr @ turned
            de[at[:m, t]] += dc2[:, :d] + dc[:, :d]
            dh[:m] = back * (1 - z) + dc2[:, d:] * r + dc[:, d:]
        de *= 1 - e * e
        v["Wi"] += x.T @ de
        v["bi"] += de.sum(axis=0)
        back, held = de @ p["Wi"].T, weights > 0
        rows = np.broadcast_to(np.arange(len(slots))[:, None], slots.shape)[held]
        v["Ev"] += np.bincount((slots[held][:, None] * d + np.arange(d)).ravel(), (weights[held][:, None] * back[rows]).ravel(), v["Ev"].size).reshape(v["Ev"].shape)
        return float(loss), g


def hessian_vector(gradient, theta: np.ndarray, v: np.ndarray, step: float = 1e-20) -> np.ndarray:
    """H v by a complex step through the gradient."""
    return gradient(theta + 1j * step * v).imag / step
