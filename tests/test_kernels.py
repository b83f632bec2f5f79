"""Representatives and their online form on hand-sized and random units."""

from __future__ import annotations

import numpy as np
import pytest

from groupsearch.functions import kernels as k


def unit(n, d, seed=0):
    x = np.random.default_rng(seed).standard_normal((n, d))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_hand_sized_units():
    e = np.eye(2)
    assert np.allclose(k.pinv_rep(e), k.sum_rep(e))
    pair = np.array([[1, 0], [0.5, 3**0.5 / 2]])
    m = k.pinv_rep(pair)
    assert np.allclose(pair @ m, 1) and m @ m == pytest.approx(4 / 3)
    s = k.sum_rep(pair)
    assert np.allclose(pair @ s, 1.5) and s @ s == pytest.approx(3)
    assert np.allclose(k.pinv_rep(np.array([[1.0, 0], [1, 0]])), [1, 0])
    assert np.allclose(k.pinv_rep(np.array([[1.0, 0], [-1, 0]])), 0)
    three = np.array([[1, 0], [0, 1], [0.5**0.5, 0.5**0.5]])
    assert np.allclose(k.pinv_rep(three), (1 + 0.5**0.5) / 2)


def test_minimum_norm():
    x = unit(10, 64)
    m = k.pinv_rep(x)
    assert np.abs(x @ m - 1).max() < 1e-9
    for seed in range(20):
        z = np.random.default_rng(seed).standard_normal(64)
        z -= x.T @ np.linalg.solve(x @ x.T, x @ z)  # feasible: m + z keeps all products
        assert np.linalg.norm(m + z) >= np.linalg.norm(m)
    rest = k.pinv_rep(x) - x[0]
    assert abs(x[0] @ rest) < 1e-9 and m @ m == pytest.approx(1 + rest @ rest)


def test_least_squares_beyond_dimension():
    x = unit(30, 8)
    m = k.pinv_rep(x)
    assert np.abs(x.T @ (x @ m - 1)).max() < 1e-9


def test_ridge_limits():
    x = unit(6, 32)
    assert np.allclose(k.pinv_rep(x, lam=1e-12), k.pinv_rep(x), atol=1e-6)
    far = k.pinv_rep(x, lam=1e9)
    assert np.allclose(far / np.linalg.norm(far), x.sum(0) / np.linalg.norm(x.sum(0)), atol=1e-6)


@pytest.mark.parametrize("seed", range(4))
def test_online_equals_batch_in_any_order(seed):
    x = unit(12, 40, seed)
    x = np.vstack([x, x[3]])  # with an exact copy
    for order in (range(13), np.random.default_rng(seed).permutation(13)):
        state = k.UnitState("pinv")
        for i in order:
            state.append(x[i])
        assert np.allclose(state.rep, k.pinv_rep(x), atol=1e-8)


def test_online_contradiction_falls_back_to_least_squares():
    state = k.UnitState("pinv")
    for x in ([1.0, 0], [0, 1.0], [0.5**0.5, 0.5**0.5], [1.0, 0]):
        state.append(np.array(x))
    assert np.allclose(state.rep, k.pinv_rep(np.stack(state.members)))


def test_lloyd_separates_clusters_and_handles_small_inputs():
    rng = np.random.default_rng(1)
    centres = unit(4, 16, 9)
    v = np.vstack([c + 0.05 * rng.standard_normal((25, 16)) for c in centres])
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    own, _ = k.spherical_lloyd(v, 4, "pinv", True, 0, start=np.array([0, 25, 50, 75]))
    assert all(len(set(own[25 * i : 25 * i + 25])) == 1 for i in range(4))
    own, reps = k.spherical_lloyd(v[:2], 5, "sum", False, 0)
    assert len(own) == 2 and len(reps) == 2


def test_top_k_rows_breaks_ties_by_id():
    s = np.array([[1.0, 3, 3, 2, 3, 0]])
    assert k.top_k_rows(s, np.array([9, 8, 7, 6, 5, 4]), 2).tolist() == [[4, 2]]
    wide = np.zeros((2, 50))
    assert k.top_k_rows(wide, np.arange(50)[::-1], 3).tolist() == [[49, 48, 47]] * 2


def test_hamming_distances():
    bits = np.random.default_rng(2).integers(0, 2, (30, 128)).astype(bool)
    words = np.ascontiguousarray(np.packbits(bits, axis=1).view(np.uint64).T)
    assert (k.hamming_distances(words, words[:, 3]) == (bits != bits[3]).sum(1)).all()
