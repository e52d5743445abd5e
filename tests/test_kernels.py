"""Operators, losses and the training step against finite differences, identities and hand counts."""

import itertools

import numpy as np
import pytest

from gembed.operators import kernels as K
from gembed.operators import losses, relops
from gembed.operators import spec as S


def setting(op, sim, loss, reciprocal, d=6, **more):
    rel = S.RelationSpec("r", "a", "b", rhs_op=op, lhs_op=op if reciprocal else "identity", reciprocal=reciprocal)
    spec = S.GraphSpec((S.EntityType("a"), S.EntityType("b")), (rel,), dim=d, sim=sim, loss=loss, **({"chunk": 4, "uniform": 3, "batch": 8, "n3": 1e-2, "margin": 0.3} | more))
    rng = np.random.default_rng(0)
    p = K.Params.start(rel, d)
    for k in p.theta:
        p.theta[k] = p.theta[k].astype(float) + rng.normal(0, 0.3, p.theta[k].shape)
    a, b = K.Matrix(rng.normal(0, 1, (7, d)), np.zeros(7)), K.Matrix(rng.normal(0, 1, (9, d)), np.zeros(9))
    edges = rng.integers(0, 7, 6), rng.integers(0, 9, 6), rng.random(6) + 0.5
    return spec, rel, p, a, b, edges, (rng.integers(0, 7, (2, 3)), rng.integers(0, 9, (2, 3))), rng


@pytest.mark.parametrize("op,sim,loss,reciprocal", list(itertools.product(S.OPERATORS, S.SIMILARITIES, S.LOSSES, (False, True))))
def test_gradients_by_finite_differences(op, sim, loss, reciprocal):
    spec, rel, p, a, b, (s, d, w), draws, rng = setting(op, sim, loss, reciprocal)
    run = lambda: K.step(spec, rel, p, a, b, s, d, w, rng, None, False, draws)
    _, (i1, g1), (i2, g2), gp = run()
    ga, gb = np.zeros_like(a.x), np.zeros_like(b.x)
    np.add.at(ga, i1, g1)
    np.add.at(gb, i2, g2)
    e = 1e-6
    for x, g in [(a.x, ga), (b.x, gb)] + [(p.theta[k], gp[k]) for k in gp]:
        for _ in range(4):
            at = tuple(rng.integers(0, n) for n in x.shape)
            old = x[at]
            x[at] = old + e
            up = run()[0]
            x[at] = old - e
            down = run()[0]
            x[at] = old
            assert abs((up - down) / (2 * e) - g[at]) < 1e-4


def test_counts_of_negatives():
    assert K.negatives_per_chunk(50, 50) == 9900
    spec, rel, p, a, b, (s, d, w), _, rng = setting("identity", "dot", "softmax", False)
    count = K.Counters()
    K.step(spec, rel, p, a, b, s, d, w, rng, count)
    assert count.edges == 6 and count.rows_gathered == 2 * 8 + 2 * 2 * 3


def test_a_step_raises_true_edges():
    for loss in S.LOSSES:
        spec, rel, p, a, b, (s, d, w), draws, rng = setting("identity", "dot", loss, False, n3=0.0, lr=0.05, margin=1.0)
        before = K.step(spec, rel, p, a, b, s, d, w, rng, None, False, draws)[0]
        for _ in range(20):
            K.step(spec, rel, p, a, b, s, d, w, rng, None, True, draws)
        assert K.step(spec, rel, p, a, b, s, d, w, rng, None, False, draws)[0] < before


def test_identities_of_operators():
    x = np.random.default_rng(1).normal(size=(5, 6))
    for op in ("translation", "diagonal", "linear", "complex_diagonal", "circular_correlation"):
        assert np.allclose(relops.forward(op, x, relops.parameters(op, 6).astype(float)), x, atol=1e-12)
    t = np.arange(6.0)
    assert np.allclose(relops.forward("diagonal", x, t), relops.forward("linear", x, np.diag(t)))
    real = np.concatenate([x[:, :3], np.zeros((5, 3))], 1)
    assert np.allclose(relops.forward("complex_diagonal", real, np.array([1.0, 2, 3, 0, 0, 0])), relops.forward("diagonal", real, np.array([1.0, 2, 3, 0, 0, 0])))


def test_circular_correlation_by_definition():
    rng = np.random.default_rng(2)
    t, x = rng.normal(size=8), rng.normal(size=(3, 8))
    want = np.array([[sum(t[i] * row[(i + k) % 8] for i in range(8)) for k in range(8)] for row in x])
    assert np.allclose(relops.forward("circular_correlation", x, t), want)


def test_losses_by_hand():
    pos, neg, live, w = np.array([1.0]), np.array([[0.5, 2.0]]), np.array([[True, True]]), np.array([2.0])
    assert np.isclose(losses.ranking(pos, neg, live, w, 0.1)[0], 2 * (0 + 1.1))
    assert np.isclose(losses.softmax(pos, neg, live, w)[0], -2 * np.log(np.e / (np.e + np.exp(0.5) + np.exp(2))))
    assert np.isclose(losses.logistic(pos, neg, live, w)[0], 2 * np.log1p(np.exp(-1)) + 1 * (np.log1p(np.exp(0.5)) + np.log1p(np.exp(2))))
    alone = np.array([[False, False]])
    assert losses.ranking(pos, neg, alone, w)[0] == 0 and losses.softmax(pos, neg, alone, w)[0] == 0


def test_row_adagrad_keeps_untouched_rows():
    m = K.Matrix(np.ones((4, 2), np.float32), np.zeros(4, np.float32))
    K._apply(m, np.array([1, 1, 3]), np.array([[1.0, 0], [1.0, 0], [0, 2.0]]), 0.1, "adagrad_row")
    assert m.acc.tolist() == [0, 4, 0, 4] and m.x[0].tolist() == [1, 1] and m.x[2].tolist() == [1, 1]
    assert np.allclose(m.x[1], [0.9, 1]) and np.allclose(m.x[3], [1, 0.9])


def test_spec_rejects_what_is_undefined():
    with pytest.raises(ValueError):
        setting("complex_diagonal", "dot", "softmax", False, d=5)
    with pytest.raises(ValueError):
        S.GraphSpec((S.EntityType("a"),), (S.RelationSpec("r", "a", "zzz"),))
    spec = S.preset("rescal", [S.EntityType("a")], [("r", "a", "a")], dim=8)
    with pytest.warns(UserWarning):
        assert spec.lint({"r": 10}) == ["r"]
    assert spec.n_shared() == 64


def test_masking_known_positives():
    spec, rel, p, a, b, (s, d, w), draws, rng = setting("identity", "dot", "softmax", False, mask_known=True)
    c1, c2 = K.Counters(), K.Counters()
    K.step(spec, rel, p, a, b, s, d, w, rng, c1, False, draws)
    K.step(spec.with_(mask_known=False), rel, p, a, b, s, d, w, rng, c2, False, draws)
    assert c1.negatives <= c2.negatives


def test_unbatched_negatives_cost_more_rows():
    rel = S.RelationSpec("r", "n", "n")
    rows = {}
    for mode in ("batched", "unbatched"):
        spec = S.GraphSpec((S.EntityType("n"),), (rel,), dim=4, negatives=mode, chunk=10, uniform=10, batch=100)
        m, count = K.start_matrix(spec, 0, 0, 500), K.Counters()
        rng = np.random.default_rng(0)
        K.train_edges(spec, rel, K.Params.start(rel, 4), m, m, rng.integers(0, 500, 100), rng.integers(0, 500, 100), np.ones(100, np.float32), rng, count)
        rows[mode] = count.rows_gathered
    assert rows["unbatched"] > 8 * rows["batched"]


def test_correlation_by_a_circulant_equals_that_by_transforms(monkeypatch):
    rng = np.random.default_rng(2)
    x, dy, theta = rng.normal(size=(3, 5, 7)), rng.normal(size=(3, 5, 7)), rng.normal(size=7)
    one = relops.forward("circular_correlation", x, theta), *relops.backward("circular_correlation", x, theta, dy)
    monkeypatch.setattr(relops, "CIRCULANT", 0)
    two = relops.forward("circular_correlation", x, theta), *relops.backward("circular_correlation", x, theta, dy)
    for a, b in zip(one, two, strict=True):
        np.testing.assert_allclose(a, b, atol=1e-12)


def test_a_pool_is_transformed_once_for_both_sides(monkeypatch):
    spec, rel, p, a, b, (s, d, w), draws, rng = setting("linear", "cos", "ranking", False)
    rows, forward = [], relops.forward
    monkeypatch.setattr(relops, "forward", lambda op, x, theta: rows.append(x.shape[:2]) or forward(op, x, theta))
    K.step(spec, rel, p, a, b, s, d, w, rng, None, False, draws)
    assert rows == [(2, 7), (2, 7)]


@pytest.mark.parametrize("kind,dim", ((np.float32, 6), (np.float32, 5), (np.float64, 4)))
def test_rows_of_an_id_are_summed(kind, dim):
    rng = np.random.default_rng(3)
    ids, grads = rng.integers(0, 40, 300), rng.integers(-9, 9, (300, dim)).astype(kind)
    want = np.zeros((40, dim), kind)
    np.add.at(want, ids, grads)
    rows, sums = K._summed(ids, grads)
    assert rows.tolist() == sorted(set(ids.tolist())) and np.array_equal(sums, want[rows])


@pytest.mark.parametrize("loss", S.LOSSES)
def test_scores_that_do_not_count_leave_no_trace(loss):
    rng = np.random.default_rng(4)
    pos, neg, w = rng.normal(size=(2, 3)), rng.normal(size=(2, 3, 5)), rng.random((2, 3))
    live = rng.random(neg.shape) < 0.6
    live[0, 0] = False
    kept = neg.copy()
    value, gp, gn = losses.LOSSES[loss](pos, neg, live, w, 0.1)
    other = losses.LOSSES[loss](pos, np.where(live, neg, 50.0), live, w, 0.1)
    assert np.array_equal(neg, kept) and np.isfinite(value) and not gn[~live].any()
    assert value == other[0] and np.array_equal(gp, other[1]) and np.array_equal(gn, other[2])
