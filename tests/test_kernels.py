"""NumPy kernels against brute force."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from manifold_engine.functions import linalg as LA
from manifold_engine.functions import metrics as D
from manifold_engine.operators import maps as M
from manifold_engine.sources.points import build_chain, rigid_motion


def _graph(x, r):
    d = D.euclidean_block(x, x)
    i, j = np.nonzero((d <= r) & (np.arange(len(x))[:, None] < np.arange(len(x))[None, :]))
    return LA.SymmetricEdges(len(x), i, j, np.ones(len(i)), np.zeros(len(x))), d


def test_euclidean_block_exact_zero():
    x = np.random.default_rng(0).standard_normal((40, 5)) + 1e6
    d = D.euclidean_block(x, x)
    assert np.all(np.diag(d) == 0) and np.allclose(d, np.sqrt(((x[:, None] - x[None]) ** 2).sum(2)), atol=1e-3)


def test_rmsd_is_rigid_invariant_symmetric_and_a_metric():
    rng = np.random.default_rng(1)
    pos = build_chain(rng.uniform(-3, 3, (12, 19)))
    assert np.allclose(np.linalg.norm(np.diff(pos, axis=1), axis=2), 1.53)
    x = pos.reshape(12, -1)
    y = rigid_motion(pos, np.arange(12)).reshape(12, -1)
    d = D.rmsd_block(x, x)
    assert np.abs(D.rmsd_block(x, y) - d).max() < 1e-6 and np.abs(d - d.T).max() < 1e-9
    assert np.all(d[:, :, None] <= d[:, None, :] + d.T[None] + 1e-6)
    mirror = (pos * (1, 1, -1)).reshape(12, -1)
    assert D.rmsd_block(x[:1], mirror[:1])[0, 0] > 0.1
    h = np.random.default_rng(2).standard_normal((5, 6, 3, 3))
    assert np.allclose(D._leading_root(h, np.linalg.norm(h, axis=(2, 3)) * 3), D._signed_sum(h))


def test_emd_and_hamming_blocks():
    a, b = np.array([[1.0, 0, 0]]), np.array([[0, 0, 1.0]])
    assert D.emd_block(a, b)[0, 0] == 2
    assert D.hamming_block(np.array([[5.0, 1]]), np.array([[6.0, 0]]))[0, 0] == 3


def test_lanczos_equals_dense():
    x = np.random.default_rng(3).standard_normal((200, 2))
    a = np.exp(-(D.euclidean_block(x, x) ** 2))
    i, j = np.triu_indices(200, 1)
    e = LA.SymmetricEdges(200, i, j, a[i, j], np.ones(200))
    assert np.allclose(e.dense(), a)
    w, v = LA.top_dense(a, 5)
    lw, lv = LA.lanczos(lambda y: e @ y, 200, 5)
    assert np.allclose(w, lw) and np.allclose(np.abs((v * lv).sum(0)), 1, atol=1e-6)


@pytest.mark.parametrize("growth", ["random_edge", "star_random", "star_depth", "star_breadth", "star_greedy", "boruvka"])
def test_trees_span_and_landmarks_cover(growth):
    for seed in range(5):
        x = np.random.default_rng(seed).standard_normal((120, 2))
        r = LA.bottleneck(D.euclidean_block(x, x)) * 1.1
        assert LA.bottleneck_rows(x, D.euclidean_block) == pytest.approx(r / 1.1)
        g, d = _graph(x, r)
        parent, depth = LA.boruvka_tree(g, seed) if growth == "boruvka" else LA.grow_tree(g, growth, 0, seed)
        assert (depth >= 0).all() and (parent >= 0).sum() == 119
        kids = np.flatnonzero(parent >= 0)
        assert (depth[kids] == depth[parent[kids]] + 1).all() and (d[kids, parent[kids]] <= r).all()
        lm = LA.tree_landmarks(parent, depth)
        assert d[:, lm].min(1).max() <= r
        from manifold_engine.operators.landmarks import check_landmark_graph

        assert check_landmark_graph(lm, x[lm], r) == {"isolated": 0, "components": 1}


def test_path_and_star_fixtures():
    path = LA.SymmetricEdges(5, np.arange(4), np.arange(1, 5), np.ones(4), np.zeros(5))
    assert LA.tree_landmarks(*LA.grow_tree(path, "star_breadth", 0)).tolist() == [1, 2, 3]
    star = LA.SymmetricEdges(5, np.zeros(4, int), np.arange(1, 5), np.ones(4), np.zeros(5))
    assert LA.tree_landmarks(*LA.grow_tree(star, "star_greedy", 0)).tolist() == [0]
    two = LA.SymmetricEdges(2, np.array([0]), np.array([1]), np.ones(1), np.zeros(2))
    assert LA.tree_landmarks(*LA.grow_tree(two, "star_depth", 0)).tolist() == [0]
    one = LA.SymmetricEdges(1, np.zeros(0, int), np.zeros(0, int), np.zeros(0), np.zeros(1))
    assert LA.tree_landmarks(*LA.grow_tree(one, "star_random", 0)).tolist() == [0]


def test_two_points_and_identical_points():
    m = M.fit_local(np.array([0, 1]), np.array([[0.0], [1.0]]), 0.5, 2)
    a = np.exp(-1.0)
    assert np.allclose(m.lam, [1, (1 - a) / (1 + a)])
    same = M.fit_local(np.arange(4), np.ones((4, 2)), 1.0, 4)
    assert np.allclose(same.lam, [1, 0, 0, 0], atol=1e-9)


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10_000), st.integers(3, 30))
def test_map_invariants(seed, n):
    rng = np.random.default_rng(seed)
    x, c = rng.standard_normal((n, 3)), rng.integers(1, 6, n).astype(float)
    m = M.fit_local(np.arange(n), x, 0.7, n, counts=c)
    assert m.lam[0] == pytest.approx(1) and (m.lam <= 1 + 1e-9).all() and np.ptp(m.psi[:, 0]) < 1e-8
    assert np.allclose((c[:, None] * m.psi**2).sum(0), 1)
    k = min(2, n - 1)
    if m.lam[k] > 1e-3:
        assert np.allclose(M.nystrom(x, m, k)[0], m.coordinates(k), atol=1e-7)
    far, at, best = M.nystrom(x + 1e4, m, k)
    assert np.isfinite(far).all()
    at = np.repeat(np.arange(n), c.astype(int))
    assert np.allclose(M.fit_local(np.arange(len(at)), x[at], 0.7, k + 1).lam, m.lam[: k + 1])
