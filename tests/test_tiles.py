"""Tile kernels against NumPy, and the hand-computed values."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rankgrid.functions import tiles as t


def low(rng, m, n, r):
    return t.Tile(rng.standard_normal((m, r)), rng.standard_normal((n, r)))


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 12), st.integers(1, 12), st.integers(0, 12), st.sampled_from([0.0, 1e-8, 1e-3, 1.0]), st.integers(0, 99))
def test_pivoted_qr_keeps_the_bound(m, n, r, eps, seed):
    rng = np.random.default_rng(seed)
    a = rng.standard_normal((m, min(r, m, n))) @ rng.standard_normal((min(r, m, n), n))
    x, w = t.pivoted_qr(a, eps)
    assert np.linalg.norm(a - x @ w.T) <= eps + 1e-12 * (1 + np.linalg.norm(a))
    assert x.shape[1] <= min(m, n)
    assert np.allclose(x.T @ x, np.eye(x.shape[1]), atol=1e-10)


def test_rank_one_tile_by_hand():
    c = t.compress(np.outer([1.0, 2, 2], [3.0, 0, 4]), 1e-12)
    assert (c.kind, c.rank, c.stored) == ("L", 1, 6)
    assert c.norm() == pytest.approx(15)


@pytest.mark.parametrize(("m", "n", "r", "keeps"), [(4, 4, 2, True), (4, 4, 3, False), (1, 1, 1, False), (8, 5, 2, True)])
def test_storage_rule(m, n, r, keeps):
    assert t.keeps_low(r, m, n) is keeps


@pytest.mark.parametrize("kinds", ["FF", "FL", "LF", "LL"])
def test_products_and_sums(kinds):
    rng = np.random.default_rng(1)
    a, b = (low(rng, 6, 6, r) for r in (2, 5))
    a, b = (t.Tile(x.dense()) if k == "F" else x for x, k in zip((a, b), kinds, strict=True))
    assert np.allclose(t.multiply(a, b).dense(), a.dense() @ b.dense())
    assert np.allclose(t.add(a, b).dense(), a.dense() + b.dense())
    if kinds == "LL":
        assert t.multiply(a, b).rank == 2
        assert t.add(a, b).rank == 7


def test_recompression_undoes_a_doubled_rank():
    a = low(np.random.default_rng(2), 9, 9, 3)
    twice = t.add(a, a)
    again = t.recompress(twice, 1e-9)
    assert (twice.rank, again.rank) == (6, 3)
    assert np.allclose(again.dense(), 2 * a.dense())


def test_rank_excess_over_svd_is_small():
    x = np.linspace(0, 1, 40)
    a = 1 / np.sqrt(1 + (x[:, None] - x[None, :] - 2) ** 2)
    s = np.linalg.svd(a, compute_uv=False)
    best = next(k for k in range(41) if np.sqrt((s[k:] ** 2).sum()) <= 1e-6)
    assert t.pivoted_qr(a, 1e-6)[0].shape[1] <= max(best + 3, best * 1.25)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 8), st.integers(1, 8), st.integers(1, 8), st.integers(0, 50))
def test_sparse_product(m, k, n, seed):
    rng = np.random.default_rng(seed)
    a, b = (rng.integers(-2, 3, s) * (rng.random(s) < 0.4) for s in ((m, k), (k, n)))
    assert np.array_equal(t.sparse_multiply(a.astype(float), b.astype(float)), a @ b)


def test_zero_and_empty_tiles():
    assert t.compress(np.zeros((3, 4)), 1e-9).rank == 0
    assert t.multiply(t.Tile(np.ones((2, 3))), t.Tile(np.zeros((3, 0)), np.zeros((4, 0)))).dense().shape == (2, 4)
