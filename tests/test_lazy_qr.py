"""The pivoted QR: rank, bound and orthogonality, and that a step does not update the whole matrix."""

import numpy as np
import pytest

from rankgrid.functions import tiles


def _kernel(n, kind, shift):
    z, y = np.sort(np.random.default_rng(0).uniform(-1, 10, n)), np.sort(np.random.default_rng(1).uniform(-1, 10, n))
    d2 = (z[:, None] - y[None]) ** 2 + shift
    return np.exp(-d2) if kind == "decay" else 1 / np.sqrt(1 + d2)


@pytest.mark.parametrize(("kind", "shift", "eps"), [("decay", 0, 1e-6), ("decay", 9, 1e-6), ("longrange", 9, 1e-10), ("decay", 0, 1e-12)])
def test_rank_is_near_the_least_there_is(kind, shift, eps):
    a = _kernel(300, kind, shift)
    q, w = tiles.pivoted_qr(a, eps)
    s = np.linalg.svd(a, compute_uv=False)
    least = int((np.sqrt(np.cumsum(s[::-1] ** 2))[::-1] > eps).sum())
    assert np.linalg.norm(a - q @ w.T) <= eps * (1 + 1e-9)
    assert np.abs(q.T @ q - np.eye(q.shape[1])).max() < 1e-14
    assert least <= q.shape[1] <= least + max(6, least // 5)


def test_a_repeated_column_adds_no_rank():
    a = np.repeat(_kernel(40, "longrange", 0), 5, axis=1)
    q, w = tiles.pivoted_qr(a, 1e-11)
    assert q.shape[1] <= 40 and np.linalg.norm(a - q @ w.T) <= 1e-11


def test_a_step_writes_nothing_of_the_size_of_the_matrix(monkeypatch):
    """An outer product a step before."""
    monkeypatch.setattr(tiles.np, "outer", None)
    assert tiles.pivoted_qr(_kernel(60, "decay", 9), 1e-6)[0].shape[1] < 30
