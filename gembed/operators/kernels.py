"""The training step on matrices that one task holds: batched negatives, gradients, Adagrad.

A batch has edges of one relation. It is cut into chunks; the chunk's own endpoints and some uniform
draws, all of the relation's entity type and of the part at hand, are the candidates that replace each
edge's source or destination. So a batch gathers a number of rows in proportion to its edges whatever
the number of negatives, and the scores are small dense products.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from . import relops
from .losses import OVER
from .spec import GraphSpec, RelationSpec

EPS = 1e-10


@dataclass
class Matrix:
    """Vectors of one part and their optimiser state (a number a row, or of the full shape)."""

    x: np.ndarray
    acc: np.ndarray


@dataclass
class Bags:
    """Nodes that are bags of features: node i has the features ids[ptr[i]:ptr[i + 1]], its vector is their mean."""

    features: Matrix
    ptr: np.ndarray
    ids: np.ndarray

    @property
    def x(self) -> np.ndarray:
        return _Means(self)

    def spread(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each node one entry per feature: place of the node in ``nodes``, the feature, and one over the bag's size."""
        size = self.ptr[nodes + 1] - self.ptr[nodes]
        at = np.repeat(np.arange(len(nodes)), size)
        first = np.repeat(self.ptr[nodes] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) if len(nodes) else size
        return at, self.ids[first + np.arange(len(at))], (1 / np.maximum(size, 1)).astype(np.float32)[at]


class _Means:
    """Reads a ``Bags`` like a matrix of vectors; a node without features has the zero vector."""

    def __init__(self, bags: Bags):
        self.bags, self.shape = bags, (len(bags.ptr) - 1, bags.features.x.shape[1])

    def __len__(self) -> int:
        return self.shape[0]

    def __getitem__(self, nodes: np.ndarray) -> np.ndarray:
        flat = np.asarray(nodes).ravel()
        at, features, share = self.bags.spread(flat)
        out = np.zeros((len(flat), self.shape[1]), self.bags.features.x.dtype)
        if len(at):
            first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
            out[at[first]] = np.add.reduceat(self.bags.features.x[features] * share[:, None], first, axis=0)
        return out.reshape(*np.shape(nodes), self.shape[1])


@dataclass
class Params:
    """A relation's parameters by (side, what): side is ``both``, ``src`` or ``dst``; what is lhs or rhs."""

    theta: dict[tuple[str, str], np.ndarray] = field(default_factory=dict)
    acc: dict[tuple[str, str], np.ndarray] = field(default_factory=dict)

    @classmethod
    def start(cls, rel: RelationSpec, d: int, seed: int = 1) -> Params:
        out = cls()
        rng = np.random.Generator(np.random.Philox(key=[seed, 77]))
        for side in ("src", "dst") if rel.reciprocal else ("both",):
            for what, op in (("lhs", rel.lhs_op), ("rhs", rel.rhs_op)):
                p = relops.parameters(op, d)
                if p is not None:
                    p = p + rng.normal(0, 0.01, p.shape).astype(np.float32)
                    out.theta[side, what] = p
                    out.acc[side, what] = np.zeros_like(p)
        return out

    def copy(self) -> Params:
        return Params({k: v.copy() for k, v in self.theta.items()}, {k: v.copy() for k, v in self.acc.items()})


@dataclass
class Counters:
    edges: int = 0
    loss: float = 0.0
    rows_gathered: int = 0
    scores: int = 0
    negatives: int = 0
    violations: int = 0

    def add(self, **by) -> None:
        for k, v in by.items():
            setattr(self, k, getattr(self, k) + v)


def negatives_per_chunk(chunk: int, uniform: int, sides: int = 2) -> int:
    """Negatives of a full chunk: every candidate but each edge's own endpoint."""
    return sides * chunk * (chunk + uniform - 1)


def _summed(ids: np.ndarray, grads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different ids in order, and the sum of each one's rows. Places are sorted along with the ids, in one number;
    most ids occur once, so first occurrences are copied and only the others are added, two floats at a time."""
    n, dim = grads.shape
    bits = n.bit_length()
    both = np.sort((ids.astype(np.int64) << bits) | np.arange(n))
    order, found = both & ((1 << bits) - 1), both >> bits
    new = np.concatenate([[True], found[1:] != found[:-1]])[:n]
    first, rest = np.flatnonzero(new), np.flatnonzero(~new)
    out = grads.take(order[first], 0)
    if len(rest):
        more = grads.take(order[rest], 0)
        pairs = out.dtype == np.float32 and dim % 2 == 0
        to, add = (x.view(np.complex64) if pairs else x for x in (out, more))
        at = (np.cumsum(new)[rest] - 1)[:, None] * to.shape[1] + np.arange(to.shape[1])
        np.add.at(to.reshape(-1), at.ravel(), add.ravel())
    return found[first], out


def _apply(m: Matrix, ids: np.ndarray, grads: np.ndarray, lr: float, optimizer: str) -> None:
    """One update; rows that occur more than once in a batch are summed first. A bag passes it on to its features."""
    if isinstance(m, Bags):
        at, features, share = m.spread(ids)
        if len(at):
            _apply(m.features, features, grads[at] * share[:, None], lr, optimizer)
        return
    rows, g = _summed(ids, grads)
    if optimizer == "sgd":
        m.x[rows] -= lr * g
    elif optimizer == "adagrad_row":
        acc = m.acc[rows] + np.einsum("ij,ij->i", g, g)
        m.acc[rows] = acc
        g *= (lr / (np.sqrt(acc) + EPS))[:, None]
        m.x[rows] = m.x.take(rows, 0) - g
    else:
        m.acc[rows] += g * g
        m.x[rows] -= lr * g / (np.sqrt(m.acc[rows]) + EPS)


def _apply_params(p: Params, grads: dict, lr: float, optimizer: str) -> None:
    for key, g in grads.items():
        if optimizer == "sgd":
            p.theta[key] -= lr * g
        else:
            p.acc[key] += g * g
            p.theta[key] -= lr * g / (np.sqrt(p.acc[key]) + EPS)


def _against(spec: GraphSpec, kept: np.ndarray, pool: np.ndarray, dead: np.ndarray, weight: np.ndarray):
    """Loss and gradients of one side: kept (chunks, C, d) against pool (chunks, C + U, d), whose first C are the true endpoints.

    dead: places of the scores (chunks, C, C + U) of negatives that don't count. Gives loss, gradients of kept and pool, and violations.
    """
    scores = kept @ pool.transpose(0, 2, 1)
    c, wide = kept.shape[1], pool.shape[1]
    pos = np.einsum("kii->ki", scores[:, :, :c]).copy()
    scores.reshape(-1)[dead] = -np.inf
    wrong = np.count_nonzero(scores >= pos[..., None])
    alive = wide - np.bincount(dead // wide, minlength=pos.size).reshape(pos.shape)
    loss, gp, gn = OVER[spec.loss](pos, scores, alive, weight, spec.margin)
    gn = gn.astype(scores.dtype, copy=False)
    np.einsum("kii->ki", gn[:, :, :c])[...] += gp
    return loss, gn @ pool, gn.transpose(0, 2, 1) @ kept, wrong


def _both_sides(spec: GraphSpec, rel: RelationSpec, params: Params, ps: np.ndarray, pd: np.ndarray, c: int, dead_s: np.ndarray, dead_d: np.ndarray, weight: np.ndarray):
    """Loss, gradients of the sources' and the destinations' pools and of the parameters, and violations, both endpoints corrupted in turn.

    The first c vectors of a chunk's pool are its edges' own endpoints, so one transform of a pool serves both sides;
    with reciprocal parameters only the endpoints that stay are transformed, by those of the side.
    """
    th, cos = params.theta, spec.sim == "cos"
    if rel.reciprocal:
        taken = ((rel.lhs_op, ("dst", "lhs"), ps[:, :c]), ("identity", None, pd), (rel.rhs_op, ("src", "rhs"), pd[:, :c]), ("identity", None, ps))
    else:
        taken = ((rel.lhs_op, ("both", "lhs"), ps), (rel.rhs_op, ("both", "rhs"), pd))
    made = [relops.forward(op, x, th.get(key)) for op, key, x in taken]
    unit, sizes = zip(*[relops.normalise(y) if cos else (y, None) for y in made], strict=True)
    a_d, b_d, a_s, b_s = unit if rel.reciprocal else (unit[0][:, :c], unit[1], unit[1][:, :c], unit[0])
    l1, ga_d, gb_d, v1 = _against(spec, a_d, b_d, dead_d, weight)
    l2, ga_s, gb_s, v2 = _against(spec, a_s, b_s, dead_s, weight)
    if rel.reciprocal:
        gs = [ga_d, gb_d, ga_s, gb_s]
    else:
        gb_s[:, :c] += ga_d
        gb_d[:, :c] += ga_s
        gs = [gb_s, gb_d]
    if cos:
        gs = [relops.normalise_back(y, size, g) for y, size, g in zip(unit, sizes, gs, strict=True)]
    back = [relops.backward(op, x, th.get(key), g) for (op, key, x), g in zip(taken, gs, strict=True)]
    grads = {key: dt for (_, key, _), (_, dt) in zip(taken, back, strict=True) if dt is not None}
    out = [g for g, _ in back]
    if rel.reciprocal:
        out[3][:, :c] += out[0]
        out[1][:, :c] += out[2]
        out = [out[3], out[1]]
    return l1 + l2, *out, grads, v1 + v2


def step(spec: GraphSpec, rel: RelationSpec, params: Params, src: Matrix, dst: Matrix, s: np.ndarray, d: np.ndarray, w: np.ndarray, rng: np.random.Generator, count: Counters | None = None, update: bool = True, draws: tuple[np.ndarray, np.ndarray] | None = None):
    """One batch: s, d are row numbers in ``src.x`` and ``dst.x``; returns the loss (and gradients if not update)."""
    n = len(s)
    size = min(spec.chunk, n) if spec.negatives == "batched" else 1
    chunks = -(-n // size)
    pad = chunks * size - n
    s2 = np.concatenate([s, np.zeros(pad, s.dtype)]).reshape(chunks, size)
    d2 = np.concatenate([d, np.zeros(pad, d.dtype)]).reshape(chunks, size)
    w2 = np.concatenate([w * rel.weight, np.zeros(pad)]).reshape(chunks, size).astype(np.float32)
    full = np.concatenate([np.ones(n, bool), np.zeros(pad, bool)]).reshape(chunks, size)
    if draws is not None:
        us, ud = draws
    elif spec.negatives == "batched":
        us = rng.integers(0, len(src.x), (chunks, spec.uniform))
        ud = rng.integers(0, len(dst.x), (chunks, spec.uniform))
    else:  # fresh candidates for every edge: alpha of them endpoints of random edges of the batch, the rest uniform
        k = spec.chunk + spec.uniform - 1
        data = rng.random((chunks, k)) < spec.alpha
        us = np.where(data, s[rng.integers(0, n, (chunks, k))], rng.integers(0, len(src.x), (chunks, k)))
        ud = np.where(data, d[rng.integers(0, n, (chunks, k))], rng.integers(0, len(dst.x), (chunks, k)))
    gather = lambda x, at: x.take(at, 0) if isinstance(x, np.ndarray) else x[at]
    at_s, at_d = np.concatenate([s2, us], 1), np.concatenate([d2, ud], 1)
    ps, pd = gather(src.x, at_s), gather(dst.x, at_d)
    known = np.unique(s.astype(np.int64) * len(dst.x) + d) if spec.mask_known else None

    def dead(pool, kept, swap):
        """Places of negatives that don't count: own endpoints, what only fills a chunk up, and known edges."""
        gone = pool[:, None, :] == pool[:, :size, None]
        if pad:
            gone |= ~full[:, :, None]
            gone[:, :, :size] |= ~full[:, None, :]
        if known is not None:
            a, b = (pool[:, None, :], kept[:, :, None]) if swap else (kept[:, :, None], pool[:, None, :])
            gone |= np.isin(a.astype(np.int64) * len(dst.x) + b, known)
        return np.flatnonzero(gone)

    dead_s, dead_d = dead(at_s, d2, True), dead(at_d, s2, False)
    loss, gs, gd, grads, wrong = _both_sides(spec, rel, params, ps, pd, size, dead_s, dead_d, w2)
    if spec.n3:
        for x, g in ((ps[:, :size], gs[:, :size]), (pd[:, :size], gd[:, :size])):
            loss += spec.n3 * float((np.abs(x) ** 3 * full[..., None]).sum())
            g += 3 * spec.n3 * x * np.abs(x) * full[..., None]
    dim = src.x.shape[1]
    ids_s, g_s, ids_d, g_d = at_s.ravel(), gs.reshape(-1, dim), at_d.ravel(), gd.reshape(-1, dim)
    if count is not None:
        every = size * (at_s.size + at_d.size)
        count.add(edges=n, loss=loss, rows_gathered=at_s.size + at_d.size, scores=n + every, negatives=every - len(dead_s) - len(dead_d), violations=wrong)
    if not update:
        return loss, (ids_s, g_s), (ids_d, g_d), grads
    if src is dst:
        _apply(src, np.concatenate([ids_s, ids_d]), np.concatenate([g_s, g_d]), spec.lr, spec.optimizer)
    else:
        _apply(src, ids_s, g_s, spec.lr, spec.optimizer)
        _apply(dst, ids_d, g_d, spec.lr, spec.optimizer)
    _apply_params(params, grads, spec.relation_lr, spec.optimizer)
    return loss


def start_matrix(spec: GraphSpec, etype: int, part: int, n: int) -> Matrix:
    """Starting vectors of a part, from its place in the model alone."""
    rng = np.random.Generator(np.random.Philox(key=[spec.seed, (etype << 32) + part]))
    x = ((rng.random((n, spec.dim), np.float32) - np.float32(0.5)) * np.float32(2 * spec.scale())).astype(np.float32)
    return Matrix(x, np.zeros((n, spec.dim) if spec.optimizer == "adagrad" else n, np.float32))


def train_edges(spec: GraphSpec, rel: RelationSpec, params: Params, src: Matrix, dst: Matrix, s: np.ndarray, d: np.ndarray, w: np.ndarray, rng: np.random.Generator, count: Counters) -> None:
    """All batches of one run of edges of a relation; a type with one node has no negatives and no loss."""
    for lo in range(0, len(s), spec.batch):
        step(spec, rel, params, src, dst, s[lo : lo + spec.batch], d[lo : lo + spec.batch], w[lo : lo + spec.batch], rng, count)
