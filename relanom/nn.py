"""Small reverse-mode differentiation on numpy, the graph autoencoder and the neural baselines.

A batch holds ``x`` [n, d], ``y`` (nan: unlabelled) and, per relation, the neighbours of all
targets in one list: ``seg`` (owner, rising), ``id``, ``x`` and ``m`` (raw mean of the neighbour's
own neighbours) with ``has``.  Input projections are affine, so means are taken of raw vectors
and projections are multiplied with the weights behind them before they meet the rows.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import NamedTuple

import numpy as np


#: Numbers that training computes with.
PRECISION = np.float32


class Var:
    """A value with the gradient of the loss by it."""

    __slots__ = ("value", "grad", "back", "parents", "fixed")

    def __init__(self, value, parents=(), back=None, fixed=False):
        self.value, self.parents, self.back, self.grad, self.fixed = np.asarray(value, PRECISION), parents, back, None, fixed

    def _with(self, grad) -> None:
        grad = np.asarray(grad, self.value.dtype)
        self.grad = grad if self.grad is None else self.grad + grad

    def backward(self) -> None:
        """Gradients of everything the value comes from; what lies between is let go of on the way, so it is not held till cycles are collected."""
        order, seen, open_ = [], {id(self)}, [(self, iter(self.parents))]
        while open_:
            v, parents = open_[-1]
            p = next((p for p in parents if id(p) not in seen), None)
            if p is None:
                order.append(v)
                open_.pop()
            else:
                seen.add(id(p))
                open_.append((p, iter(p.parents)))
        self.grad = np.ones_like(self.value)
        while order:
            v = order.pop()
            if v.back:
                if v.grad is not None:
                    for p, g in zip(v.parents, v.back(v.grad)):
                        if g is not None:
                            p._with(g)
                v.parents, v.back, v.grad = (), None, None


def _fit(g: np.ndarray, shape: tuple) -> np.ndarray:
    """Undo broadcasting."""
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def add(a: Var, b: Var) -> Var:
    return Var(a.value + b.value, (a, b), lambda g: (_fit(g, a.value.shape), _fit(g, b.value.shape)))


def sub(a: Var, b: Var) -> Var:
    return Var(a.value - b.value, (a, b), lambda g: (_fit(g, a.value.shape), _fit(-g, b.value.shape)))


def mul(a: Var, b: Var) -> Var:
    return Var(a.value * b.value, (a, b), lambda g: (None if a.fixed else _fit(g * b.value, a.value.shape), None if b.fixed else _fit(g * a.value, b.value.shape)))


def times(a: Var, w: Var) -> Var:
    """a [n, i] by w [i, o]."""
    return Var(a.value @ w.value, (a, w), lambda g: (None if a.fixed else g @ w.value.T, a.value.T @ g))


def activate(a: Var, kind: str) -> Var:
    if kind == "relu":
        on = a.value > 0
        return Var(np.maximum(a.value, 0), (a,), lambda g: (g * on,))
    t = np.tanh(a.value)
    return Var(t, (a,), lambda g: (g * (1 - t * t),))


def softplus(a: Var) -> Var:
    v = a.value
    return Var(np.maximum(v, 0) + np.log1p(np.exp(-np.abs(v))), (a,), lambda g: (g / (1 + np.exp(-np.clip(v, -80, 80))),))


def softmax(a: Var) -> Var:
    e = np.exp(a.value - a.value.max(axis=1, keepdims=True))
    p = e / e.sum(axis=1, keepdims=True)
    return Var(p, (a,), lambda g: (p * (g - (g * p).sum(axis=1, keepdims=True)),))


def row_sum(a: Var) -> Var:
    return Var(a.value.sum(axis=1), (a,), lambda g: (np.broadcast_to(g[:, None], a.value.shape),))


def mean(a: Var) -> Var:
    n = max(1, a.value.size)
    return Var(a.value.sum() / n, (a,), lambda g: (np.full(a.value.shape, float(g) / n, a.value.dtype),))


#: Places that get at most so many rows are summed up row by row; more are summed place by place.
FEW = 12


def _sums(rows: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """Sum of the rows that go to each of n places; quick where ``at`` rises."""
    if rows.ndim == 1:
        return np.bincount(at, rows, n)
    rises = not len(at) or bool((np.diff(at) >= 0).all())
    if rises and len(at) == n and (at == np.arange(n)).all():
        return rows
    out = np.zeros((n, rows.shape[1]), rows.dtype)
    if len(at):
        order = None if rises else np.argsort(at, kind="stable")
        at = at if rises else at[order]
        first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        size = np.diff(np.append(first, len(at)))
        if size.max() > FEW:
            rows, ones = rows if rises else rows[order], np.ones(size.max(), rows.dtype)
            for place, a, k in zip(at[first].tolist(), first.tolist(), size.tolist()):
                np.dot(ones[:k], rows[a : a + k], out=out[place])
        else:
            # The k-th row of every place that has one: no place is met twice.
            for k in range(size.max()):
                some = first[size > k]
                out[at[some]] += rows[some + k if rises else order[some + k]]
    return out


def take(a: Var, at: np.ndarray) -> Var:
    return Var(np.take(a.value, at, axis=0), (a,), lambda g: (_sums(g, at, len(a.value)),))


def segment_mean(a: Var, seg: np.ndarray, n: int) -> Var:
    """Mean of the rows of each segment; a segment without rows is zero."""
    size = np.maximum(np.bincount(seg, minlength=n), 1)[:, None]
    return Var(_sums(a.value, seg, n) / size, (a,), lambda g: (np.take((g / size).astype(g.dtype), seg, axis=0),))


def reached(seen: np.ndarray, w: Var, back: Var | None, seg: np.ndarray, kind: str) -> Var:
    """Activated product of the rows ``seen`` with w, to which each segment's row of ``back`` is added; one array of that size, changed in place."""
    state = seen @ w.value
    if back is not None:
        state += np.take(back.value, seg, axis=0)
    np.maximum(state, 0, out=state) if kind == "relu" else np.tanh(state, out=state)

    def go(g):
        g = g * (state > 0 if kind == "relu" else 1 - state * state)
        return (seen.T @ g, *(() if back is None else (_sums(g, seg, len(back.value)),)))

    return Var(state, (w,) if back is None else (w, back), go)


def row(a: Var) -> Var:
    """A vector as one row."""
    return Var(a.value[None, :], (a,), lambda g: (g[0],))


def row_dots(a: Var, b: Var, i: np.ndarray, j: np.ndarray) -> Var:
    """Products of row i of a with row j of b, pair by pair."""
    every = len(j) == len(b.value) and (j == np.arange(len(j))).all()
    of_a, of_b = lambda: a.value[i], lambda: b.value if every else b.value[j]
    # Rows are taken again on the way back, so no copy of them is held till then.
    return Var(np.einsum("nd,nd->n", of_a(), of_b()), (a, b), lambda g: (_sums(g[:, None] * of_b(), i, len(a.value)), _sums(g[:, None] * of_a(), j, len(b.value))))


def square(a: Var) -> Var:
    return Var(a.value**2, (a,), lambda g: (2 * a.value * g,))


def const(value) -> Var:
    """A value that needs no gradient."""
    return Var(value, fixed=True)


def stacked(parts: list[Var]) -> Var:
    """Matrices of one width below each other."""
    at = np.cumsum([0, *[len(p.value) for p in parts]])
    return Var(np.concatenate([p.value for p in parts]), tuple(parts), lambda g: tuple(g[a:b] for a, b in zip(at, at[1:])))


class Relation(NamedTuple):
    """Widths of a neighbour's features and of its second hop.

    own: the second hop are nodes of the target's type, with the target's features; back: a neighbour also receives
    from the target, of which it knows no other; hot: so many last columns of the second hop are stored as one code.
    """

    x: int
    m: int
    own: bool = False
    back: bool = False
    hot: int = 0


@dataclass(frozen=True)
class Spec:
    """Width of the target's features, and the relations."""

    x: int
    relations: tuple[Relation, ...] = ()


class Model:
    """Parameters by name; ``loss`` builds a scalar Var, ``score`` an array."""

    supervision = "unsupervised"

    def __init__(self, spec: Spec, hidden: int = 16, seed: int = 0, act: str = "relu"):
        self.spec, self.hidden, self.act = spec, hidden, act
        rng = np.random.default_rng(seed)
        self.params = {k: (rng.standard_normal(s) * np.sqrt(2.0 / s[0]) if len(s) == 2 else np.zeros(s)) for k, s in self.shapes().items()}

    def shapes(self) -> dict[str, tuple]:
        raise NotImplementedError

    def vars(self) -> dict[str, Var]:
        return {k: Var(v) for k, v in self.params.items()}


def affine(p, name: str, a: Var) -> Var:
    return add(times(a, p[f"W{name}"]), p[f"b{name}"])


def dense(name: str, i: int, o: int) -> dict[str, tuple]:
    return {f"W{name}": (i, o), f"b{name}": (o,)}


def seen_of(batch: dict) -> list[tuple[np.ndarray, np.ndarray, dict]]:
    """Per relation what no parameter changes: means of the neighbours' features with a column for whether there are any, and
    the rows that neighbours see. It is kept with the batch, as all models meet the same."""
    if "seen" not in batch:
        n, made = len(batch["x"]), []
        for r in batch["relations"]:
            some, has = (np.bincount(r["seg"], minlength=n) > 0)[:, None], r["has"][:, None].astype(PRECISION)
            mean_x = segment_mean(const(r["x"]), r["seg"], n).value
            seen = np.hstack([r["x"], np.ones_like(has), r["m"] * has, has], dtype=PRECISION, casting="same_kind")
            made.append((np.hstack([mean_x, some], dtype=PRECISION, casting="unsafe"), seen))
        batch["seen"] = made
    return [(*made, r) for made, r in zip(batch["seen"], batch["relations"])]


class GraphEncoder(Model):
    """Two layers of relation-wise mean aggregation over the receptive field."""

    def encoder_shapes(self) -> dict[str, tuple]:
        h, out = self.hidden, dense("in", self.spec.x, self.hidden) | {"self1": (self.hidden,) * 2, "self2": (self.hidden,) * 2}
        for k, r in enumerate(self.spec.relations):
            out |= dense(f"nb{k}", r.x, h) | ({} if r.own else dense(f"far{k}", r.m, h)) | {f"rel1_{k}": (h, h), f"far1_{k}": (h, h), f"rel2_{k}": (h, h)}
            out |= {f"back1_{k}": (h, h)} if r.back else {}
        return out

    def layers(self, p, batch) -> tuple[Var, Var, list[Var]]:
        """z and first-layer states of the targets, and first-layer states of all neighbours, relation by relation."""
        n, h0 = len(batch["x"]), affine(p, "in", const(batch["x"]))
        own, first = times(h0, p["self1"]), []
        # An affine map behind another: the weights are multiplied first, the bias is a row of its own.
        through = lambda name, w: [times(p[f"W{name}"], w), times(row(p[f"b{name}"]), w)]
        for k, (spec, (mean_x, seen, r)) in enumerate(zip(self.spec.relations, seen_of(batch))):
            own = add(own, times(const(mean_x), stacked(through(f"nb{k}", p[f"rel1_{k}"]))))
            weights = stacked(through(f"nb{k}", p["self1"]) + through("in" if spec.own else f"far{k}", p[f"far1_{k}"]))
            first.append(reached(seen, weights, times(h0, p[f"back1_{k}"]) if spec.back else None, r["seg"], self.act))
        h1 = activate(own, self.act)
        z = times(h1, p["self2"])
        for k, r in enumerate(batch["relations"]):
            z = add(z, times(segment_mean(first[k], r["seg"], n), p[f"rel2_{k}"]))
        return activate(z, self.act), h1, first

    def encode(self, p, batch) -> Var:
        return self.layers(p, batch)[0]

    def embed(self, p, batch) -> np.ndarray:
        """Embeddings of the targets."""
        return self.encode(p, batch).value


def rank_loss(score: Var, y: np.ndarray, rng: np.random.Generator, pairs: int = 4096) -> Var | None:
    """Mean softplus of (negative minus positive) over drawn pairs of labelled rows."""
    pos, neg = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(pos) or not len(neg):
        return None
    i, j = rng.choice(pos, pairs), rng.choice(neg, pairs)
    return mean(softplus(sub(take(score, j), take(score, i))))


class RelationalAutoencoder(GraphEncoder):
    """Reconstruction error of the (rule-augmented) target features, with optional edge and ranking terms."""

    supervision = "ranking"

    def __init__(self, spec: Spec, hidden: int = 16, seed: int = 0, act: str = "relu", alpha: float = 0.0, beta: float = 1.0):
        self.alpha, self.beta = alpha, beta
        super().__init__(spec, hidden, seed, act)

    def shapes(self):
        out = self.encoder_shapes() | dense("d1", self.hidden, self.hidden) | dense("d2", self.hidden, self.spec.x)
        return out | ({f"{name}{k}": (self.hidden, self.hidden) for k in range(len(self.spec.relations)) for name in ("edge", "back2_")} if self.alpha else {})

    def error(self, p, batch, z: Var) -> Var:
        back = affine(p, "d2", activate(affine(p, "d1", z), self.act))
        return row_sum(square(sub(back, const(batch["x"]))))

    def edge_terms(self, p, batch, z: Var, h1: Var, first: list[Var], rng) -> list[tuple[Var, np.ndarray]]:
        """Per relation the BCE of observed edges, each with that of a drawn pair that is no edge, and the targets.

        Both ends are second-layer states; a neighbour's second layer sees the target it was reached from.
        """
        out = []
        for k, r in enumerate(batch["relations"]):
            if len(r["seg"]):
                other = activate(add(times(first[k], p["self2"]), take(times(h1, p[f"back2_{k}"]), r["seg"])), self.act)
                drawn, real = non_edges(r["seg"], r["id"], rng)
                ends = times(z, p[f"edge{k}"])
                yes, no = row_dots(ends, other, r["seg"], np.arange(len(drawn))), row_dots(ends, other, r["seg"], drawn)
                out.append((add(softplus(sub(const(0.0), yes)), mul(softplus(no), const(real.astype(float)))), r["seg"]))
        return out

    def loss(self, p, batch, rng) -> Var:
        z, h1, first = self.layers(p, batch)
        score = self.error(p, batch, z)
        total = mean(score)
        if self.alpha:
            for term, _ in self.edge_terms(p, batch, z, h1, first, rng):
                total = add(total, mul(const(self.alpha), mean(term)))
        if self.beta and (rank := rank_loss(score, batch["y"], rng)) is not None:
            total = add(total, mul(const(self.beta), rank))
        return total

    def score(self, p, batch) -> np.ndarray:
        z, h1, first = self.layers(p, batch)
        out = self.error(p, batch, z).value.copy()
        if self.alpha:
            for term, seg in self.edge_terms(p, batch, z, h1, first, np.random.default_rng(0)):
                size = np.maximum(np.bincount(seg, minlength=len(out)), 1)
                out += self.alpha * np.bincount(seg, term.value, len(out)) / size
        return out


def non_edges(seg: np.ndarray, ids: np.ndarray, rng: np.random.Generator, tries: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """For every edge a drawn neighbour of the batch to which its target has no edge, and whether one was found."""
    _, number = np.unique(ids, return_inverse=True)
    target, wide = seg.astype(np.int64), number.max() + 1
    edges = np.unique(target * wide + number)

    def edge(at: np.ndarray) -> np.ndarray:
        pair = target[at] * wide + number[drawn[at]]
        return edges[np.minimum(np.searchsorted(edges, pair), len(edges) - 1)] == pair

    drawn = rng.integers(0, len(seg), len(seg))
    bad = np.flatnonzero(edge(np.arange(len(seg))))
    for _ in range(tries):
        if not len(bad):
            break
        drawn[bad] = rng.integers(0, len(seg), len(bad))
        bad = bad[edge(bad)]
    real = np.ones(len(seg), bool)
    real[bad] = False
    return drawn, real


class SupervisedGraph(GraphEncoder):
    """The same encoder with a logistic head; ``weighted`` balances the classes."""

    supervision = "labels"

    def __init__(self, spec, hidden=16, seed=0, act="relu", weighted=False):
        self.weighted = weighted
        super().__init__(spec, hidden, seed, act)

    def shapes(self):
        return self.encoder_shapes() | dense("out", self.hidden, 1)

    def logits(self, p, batch) -> Var:
        return row_sum(affine(p, "out", self.encode(p, batch)))

    def loss(self, p, batch, rng) -> Var:
        logit, known = self.logits(p, batch), ~np.isnan(batch["y"])
        y = np.where(known, batch["y"], 0.0)
        # A row without a label adds nothing; the mean is over those that have one.
        n, w = max(1, known.sum()), known.astype(float)
        if self.weighted and 0 < y.sum() < n:
            w = w * np.where(y == 1, n / (2 * y.sum()), n / (2 * (n - y.sum())))
        return mean(mul(const(w * len(y) / n), sub(softplus(logit), mul(const(y), logit))))

    def score(self, p, batch) -> np.ndarray:
        return self.logits(p, batch).value


class Mlp(SupervisedGraph):
    """Supervised network on flat features."""

    def encoder_shapes(self):
        return dense("in", self.spec.x, self.hidden) | dense("mid", self.hidden, self.hidden)

    def encode(self, p, batch):
        return activate(affine(p, "mid", activate(affine(p, "in", const(batch["x"])), self.act)), self.act)


class Autoencoder(Model):
    """Reconstruction error on flat features; ``beta`` adds the ranking term."""

    def __init__(self, spec, hidden=16, seed=0, act="relu", beta=0.0):
        self.beta, self.supervision = beta, "ranking" if beta else "unsupervised"
        super().__init__(spec, hidden, seed, act)

    def shapes(self):
        narrow = max(2, self.hidden // 4)
        return dense("e1", self.spec.x, self.hidden) | dense("e2", self.hidden, narrow) | dense("d1", narrow, self.hidden) | dense("d2", self.hidden, self.spec.x)

    def errors(self, p, batch) -> Var:
        h = activate(affine(p, "e1", const(batch["x"])), self.act)
        back = affine(p, "d2", activate(affine(p, "d1", affine(p, "e2", h)), self.act))
        return row_sum(square(sub(back, const(batch["x"]))))

    def loss(self, p, batch, rng) -> Var:
        e = self.errors(p, batch)
        rank = rank_loss(e, batch["y"], rng) if self.beta else None
        return add(mean(e), mul(const(self.beta), rank)) if rank is not None else mean(e)

    def score(self, p, batch):
        return self.errors(p, batch).value


class DeepSvdd(Model):
    """Distance from a fixed centre in the space of a network without biases.

    ``nu`` makes the boundary soft: only what lies outside the radius that holds a share 1 - nu of a batch adds to the loss.
    """

    def shapes(self):
        return {"w1": (self.spec.x, self.hidden), "w2": (self.hidden, self.hidden)}

    def __init__(self, spec, hidden=16, seed=0, act="relu", decay=1e-4, nu: float | None = None):
        self.decay, self.nu, self.centre = decay, nu, None
        super().__init__(spec, hidden, seed, act)

    def prepare(self, batch) -> None:
        """Centre of the first embeddings of a batch."""
        self.centre_at(self.embedded(self.vars(), batch).value.mean(axis=0))

    def centre_at(self, c: np.ndarray) -> None:
        """A mean of embeddings as the centre, moved away from zero."""
        self.centre = np.where(np.abs(c) < 0.1, np.where(c < 0, -0.1, 0.1), c)

    def embedded(self, p, batch) -> Var:
        return times(activate(times(const(batch["x"]), p["w1"]), self.act), p["w2"])

    def distance(self, p, batch) -> Var:
        return row_sum(square(sub(self.embedded(p, batch), const(self.centre))))

    def loss(self, p, batch, rng) -> Var:
        weights, distance = add(mean(square(p["w1"])), mean(square(p["w2"]))), self.distance(p, batch)
        if self.nu:
            radius = float(np.quantile(distance.value, 1 - self.nu))
            outside = distance.value > radius
            distance = mul(sub(distance, const(radius)), const(outside / self.nu))
        return add(mean(distance), mul(const(self.decay), weights))

    def score(self, p, batch):
        return self.distance(p, batch).value


class DecomposedRepresentation(Model):
    """Encoding as a softmax-weighted mix of fixed orthonormal vectors; what the mix cannot express is the score."""

    def __init__(self, spec, hidden=16, seed=0, act="relu", basis=5, spread=0.1):
        self.basis = np.linalg.qr(np.random.default_rng(seed + 1).standard_normal((hidden, min(basis, hidden))))[0].T
        self.spread = spread
        super().__init__(spec, hidden, seed, act)

    def shapes(self):
        h = self.hidden
        return dense("e1", self.spec.x, h) | dense("e2", h, h) | dense("w", self.spec.x, len(self.basis)) | dense("d", h, self.spec.x)

    def parts(self, p, batch):
        x = const(batch["x"])
        e = affine(p, "e2", activate(affine(p, "e1", x), self.act))
        w = softmax(affine(p, "w", x))
        return e, w, row_sum(square(sub(e, times(w, const(self.basis)))))

    def loss(self, p, batch, rng) -> Var:
        e, w, gap = self.parts(p, batch)
        back = mean(row_sum(square(sub(affine(p, "d", e), const(batch["x"])))))
        i, j = rng.integers(0, len(batch["x"]), (2, 256))
        apart = mean(row_sum(square(sub(take(w, i), take(w, j)))))
        return sub(add(mean(gap), back), mul(const(self.spread), apart))

    def score(self, p, batch):
        return self.parts(p, batch)[2].value


class Adam:
    """Moment estimates with bias correction; ``state`` goes from round to round."""

    def __init__(self, rate: float = 0.001, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8, state: tuple | None = None):
        self.rate, self.b1, self.b2, self.eps = rate, b1, b2, eps
        self.t, self.m, self.v = state or (0, {}, {})
        self.m, self.v = dict(self.m), dict(self.v)

    @property
    def state(self) -> tuple:
        return self.t, self.m, self.v

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = self.b1 * self.m.get(k, 0) + (1 - self.b1) * g
            self.v[k] = self.b2 * self.v.get(k, 0) + (1 - self.b2) * g * g
            params[k] = params[k] - self.rate * (self.m[k] / (1 - self.b1**self.t)) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + self.eps)


def part_of(batch: dict, at: np.ndarray) -> dict:
    """The batch of some targets, in rising order, with their neighbours."""
    at = np.sort(at)
    relations = []
    for r in batch["relations"]:
        low, high = np.searchsorted(r["seg"], at, "left"), np.searchsorted(r["seg"], at, "right")
        n = high - low
        keep = np.repeat(low - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(at) else np.empty(0, int)
        relations.append({"seg": np.repeat(np.arange(len(at)), n), **{c: r[c][keep] for c in ("id", "x", "m", "has")}})
    return {"x": batch["x"][at], "y": batch["y"][at], "relations": relations}


def joined(batches: list[dict]) -> dict:
    """Several batches as one."""
    if len(batches) == 1:
        return batches[0]
    first = np.cumsum([0, *[len(b["x"]) for b in batches]])
    relations = []
    for k in range(len(batches[0]["relations"])):
        parts = [b["relations"][k] for b in batches]
        relations.append({"seg": np.concatenate([r["seg"] + a for r, a in zip(parts, first)]), **{c: np.concatenate([r[c] for r in parts]) for c in ("id", "x", "m", "has")}})
    return {"x": np.concatenate([b["x"] for b in batches]), "y": np.concatenate([b["y"] for b in batches]), "relations": relations}


def mini_batches(stream, steps: int, size: int, rng: np.random.Generator, pool: int = 4096):
    """Batches of about ``size`` rows from a stream of batches: every row once, in an order drawn within each of them.

    Each comes with up to half as many positives again, drawn anew from a sample of ``pool`` of those seen so far.  A stream
    that gives fewer than ``steps`` batches is held whole, and passes over it go on until there are as many.
    """
    held, rows, made, reservoir = [], 0, 0, None

    def with_positives(part: dict) -> dict:
        if reservoir is None:
            return part
        extra = rng.permutation(len(reservoir["x"]))[: size // 2]
        return joined([part, part_of(reservoir, extra)])

    for batch in stream:
        n = len(batch["x"])
        positives = np.flatnonzero(batch["y"] == 1)
        if len(positives):
            both = joined([reservoir, part_of(batch, positives)]) if reservoir is not None else part_of(batch, positives)
            if len(both["x"]) > pool:
                both = part_of(both, rng.choice(len(both["x"]), pool, replace=False))
            reservoir = both
        order = rng.permutation(n)
        for a in range(0, n, size):
            yield with_positives(part_of(batch, order[a : a + size]))
            made += 1
        if rows + n <= steps * size:
            held.append(batch)
        rows += n
    if not held or not rows:
        return
    whole = joined(held)
    held.clear()
    while made < steps:
        order = rng.permutation(len(whole["x"]))
        for a in range(0, len(order), size):
            if made < steps:
                yield with_positives(part_of(whole, order[a : a + size]))
                made += 1


def train_steps(models: dict[str, Model], states: dict[str, tuple], stream, steps: int, size: int, rates: dict[str, float], seed: int) -> tuple[int, dict[str, tuple]]:
    """Rows seen and (parameters, optimiser state) of every model after one run through the stream; all models see the same batches."""
    adams = {k: Adam(rates[k], state=states.get(k)) for k in models}
    params, rngs, rows = {k: dict(m.params) for k, m in models.items()}, {k: np.random.default_rng([seed, i]) for i, k in enumerate(sorted(models))}, 0

    def counted():
        nonlocal rows
        for batch in stream:
            rows += len(batch["x"])
            yield batch

    for batch in mini_batches(counted(), steps, size, np.random.default_rng(seed)):
        for k, model in models.items():
            p = {name: Var(v) for name, v in params[k].items()}
            model.loss(p, batch, rngs[k]).backward()
            adams[k].step(params[k], {name: v.grad for name, v in p.items() if v.grad is not None})
    return rows, {k: (params[k], adams[k].state) for k in models}
