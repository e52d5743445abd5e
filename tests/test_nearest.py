"""Nearest vectors and ranks by blocks against plain numpy, with copies of vectors and blocks of scores in small pieces."""

import numpy as np
import pytest

from gembed.operators import evaluate, nearest

DIM = 6


def _rows(n=300, copies=120, seed=3):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, DIM)).astype(np.float32)
    x[rng.choice(n, copies, replace=False)] = x[0]
    return rng.permutation(n) * 3, x


def _scores(x):
    s = np.zeros((len(x), len(x)))
    for k in range(DIM):
        s += x[:, k, None].astype(np.float64) * x[None, :, k]
    np.fill_diagonal(s, -np.inf)
    return s


@pytest.mark.parametrize("blocks", [(1, 1), (3, 5)])
def test_best_and_ranks_equal_brute_force(spark, monkeypatch, blocks):
    monkeypatch.setattr(nearest, "SCORE_BYTES", 8 * 300 * 7)
    ids, x = _rows()
    s = _scores(x)
    df = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x)], "id long, vec array<float>")
    got = {(r["query"], r["place"]): (r["id"], r["score"]) for r in nearest.nearest_exact(df, df, 5, True, *blocks).collect()}
    best = [np.lexsort((ids, -s[i]))[:5] for i in range(len(ids))]
    assert got == {(int(ids[i]), p + 1): (int(ids[j]), s[i, j]) for i, b in enumerate(best) for p, j in enumerate(b)}
    # edges to any vectors, not only to the best: ranks are counted among all
    rng = np.random.default_rng(4)
    edges = [(i, int(j)) for i in range(0, len(ids), 2) for j in rng.choice(np.delete(np.arange(len(ids)), i), 3 if i % 4 else 2, replace=False)]
    given = spark.createDataFrame([(int(ids[i]), int(ids[j]), float(s[i, j])) for i, j in edges], "query long, id long, score double")
    ranks = {(r["q"], r["true"]): (r["better"], r["better_filtered"]) for r in nearest.ranks_exact(given, df, 3).collect()}
    own = {i: [j for a, j in edges if a == i] for i, _ in edges}
    assert ranks == {(int(ids[i]), int(ids[j])): (int((s[i] > s[i, j]).sum()), int((s[i] > s[i, j]).sum()) - sum(s[i, o] > s[i, j] for o in own[i])) for i, j in edges}


def test_a_task_holds_a_bounded_piece_of_scores(monkeypatch):
    monkeypatch.setattr(nearest, "SCORE_BYTES", 8 * 300 * 7)
    _, x = _rows()
    packed = {"qids": np.arange(300, dtype="<i8").tobytes(), "ids": np.arange(300, dtype="<i8").tobytes(), "qx": x.tobytes(), "x": x.tobytes(), "dim": DIM}
    pieces = [s.shape for _, s, _ in nearest._Pair(packed).pieces()]
    assert sum(n for n, _ in pieces) == 300 and max(n * m * 8 for n, m in pieces) <= nearest.SCORE_BYTES
    assert nearest.BLOCK_BYTES <= 8 << 20 and evaluate.SCORE_BYTES <= 64 << 20


def test_the_evaluators_pieces_of_scores_change_nothing(spark, monkeypatch):
    from gembed.operators import train_block
    from gembed.operators.spec import EntityType, preset

    ids, x = _rows(60, 20)
    e = spark.createDataFrame([("near", str(i), str(ids[(n * 7 + k) % 60]), 1) for n, i in enumerate(ids) for k in (1, 5)], "rel string, src string, dst string, weight long")
    vec = spark.createDataFrame([(0, str(i), v.tolist()) for i, v in zip(ids, x)], "etype int, key string, vec array<float>")
    model = train_block.from_vectors(e, preset("identity", [EntityType("node")], [("near", "node", "node")], dim=DIM), vec, 2)
    s = x.astype(np.float64) @ x.T.astype(np.float64)
    at = {str(i): n for n, i in enumerate(ids)}
    pairs = [(r["src"], r["dst"]) for r in e.collect()]
    want = set()
    for a, b in pairs:
        for side, kept, true in (("dst", a, b), ("src", b, a)):
            p = s[at[a], at[b]]
            gone = {true} | ({d for c, d in pairs if c == a} if side == "dst" else {c for c, d in pairs if d == b})
            others = np.array([s[at[kept], n] for k, n in at.items() if k not in gone])
            near = abs(others - p) <= 1e-6 * max(1, abs(p))
            want.add((side, a, b, int(((others > p) & ~near).sum()), int(near.sum())))
    monkeypatch.setattr(evaluate, "SCORE_BYTES", 8 * 60 * 7)
    for pool in (None, 0):
        got = evaluate.rank_edges(model, e, e, mode="all", filtered=True, exact=True, pool_bytes=pool).select("side", "src", "dst", "better", "ties")
        assert {tuple(r) for r in got.collect()} == want
