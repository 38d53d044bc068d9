"""Kernel matrices by cores of shared bases, against dense NumPy, and the work that lrb_exact_limit leaves out."""

import numpy as np
import pytest

from rankgrid import registry
from rankgrid.functions import tiles
from rankgrid.operators.multiply import mm_panels
from rankgrid.sources import matrices as mx
from rankgrid.sources import skeletons
from tests.test_matrices import dense

EPS = (1e-1, 1e-6, 0.0)


def points(spark, n, null=False):
    """Points of two nations along a line, each place four times; no two columns of a tile are equally long, as pivots would be open."""
    at = [0.03 * (k // 4) ** 1.1 for k in range(n)]
    rows = [(k, k % 2, k % 2, at[k], 3.0 * (k % 2), 0.0, None if null and k == 5 else at[k]) for k in range(n)]
    return spark.createDataFrame(rows, "key long, region long, nation long, bal double, px double, py double, pz double")


def test_products_of_cores_are_products_of_the_matrix(spark):
    p = points(spark, 480)
    m, _ = mx.kernel_matrix(p, "longrange", most=64)
    a, s = dense(m), m.rows.starts
    cores = skeletons.kernel_cores(p, "longrange", EPS, most=64)
    assert cores.points.starts == s
    # far fewer numbers than the matrix has
    assert cores.axis.n < m.rows.n / 2
    whole = mm_panels(cores.at(0.0), cores.at(0.0), depth="all")
    square = dense(whole)
    eye = np.eye(cores.axis.n)
    # the matrix is the identity but for what its core adds
    assert np.linalg.norm(square - eye) == pytest.approx(np.linalg.norm(a @ a - np.eye(len(a))), rel=1e-9)
    for e in EPS[:-1]:
        parts = [[tiles.compress(a[i:j, k:n], e) for k, n in zip(s, s[1:], strict=False)] for i, j in zip(s, s[1:], strict=False)]
        low = np.block([[t.dense() for t in row] for row in parts])
        assert cores.full(e) == sum(t.kind == "F" for row in parts for t in row)
        got = dense(mm_panels(cores.at(e), cores.at(e), depth="all"))
        assert np.linalg.norm(got - square) == pytest.approx(np.linalg.norm(low @ low - a @ a), rel=1e-4)
        rounded = dense(cores.recompressed(mm_panels(cores.at(e), cores.at(e), depth="all"), e))
        assert 0 < np.linalg.norm(rounded - got) <= e * (len(s) - 1)
    assert cores.full(0.0) == (len(s) - 1) ** 2


def test_a_null_place_is_not_left_out(spark):
    cores = skeletons.kernel_cores(points(spark, 40, null=True), "longrange", (0.1, 0.0), most=64)
    assert np.isnan(dense(mm_panels(cores.at(0.1), cores.at(0.1), depth="all"))).any()


def test_the_exact_limit_multiplies_no_tile_of_points(spark, monkeypatch):
    def no(*_, **__):
        raise AssertionError("the dense kernel was made")

    monkeypatch.setattr(mx, "kernel_matrix", no)
    rows = registry.queries()["lrb_exact_limit"](spark, "/root/testdata/sf0.001").collect()
    assert [r["eps"] for r in rows] == [1e-1, 1e-4, 1e-7, 0.0]
    assert [r["full"] for r in rows] == [90, 607, 625, 625]
    assert [r["error"] for r in rows] == pytest.approx([10.358679553, 0.00103421579, 0.0, 0.0], rel=1e-6)
