"""What an iteration leaves on disk while it runs."""

import os

import numpy as np
import pytest

from rankgrid import registry, session
from rankgrid.operators.iterate import Options, inv_sqrt
from rankgrid.schema import Axis
from rankgrid.workloads.lowrank import supplier
from tests.test_matrices import dense, matrix

DATA = "/root/testdata/sf0.001"


@pytest.fixture
def folder(tmp_path, monkeypatch):
    monkeypatch.setattr(session, "shared_dir", lambda spark: f"file://{tmp_path}")
    return tmp_path


def _tables(folder):
    return sorted(f.split("-")[0] for f in os.listdir(folder))


def test_a_root_leaves_the_tables_of_its_last_round(spark, folder):
    rows = registry.queries()["sqrt_check"](spark, DATA)
    left = _tables(folder)
    assert [left.count(name) for name in ("x", "t", "zy")] == [1, 1, 1]
    m = dense(supplier(spark, DATA))
    w, v = np.linalg.eigh(m)
    want = (v * np.sqrt(w)) @ v.T
    got = {(r["i"], r["j"]): r["v"] for r in rows.collect()}
    assert len(got) == want.size and max(abs(got[i, j] - want[i, j]) for i, j in got) < 5.1e-5


def test_all_rounds_stay_where_they_are_asked_for(spark, folder):
    a = np.diag(np.linspace(1, 3, 6)) + 0.1
    m = matrix(spark, a, Axis.uniform(6, 3), Axis.uniform(6, 3))
    seen = []
    one = inv_sqrt(m, 3, each=lambda k, roots: seen.append(roots))
    assert [_tables(folder).count(name) for name in ("x", "t", "zy")] == [3, 3, 3]
    assert all(roots.x.blocks.count() == 4 for roots in seen)
    other = inv_sqrt(m, 3, options=Options(keep=False))
    assert np.array_equal(dense(one.root()), dense(other.root())) and np.array_equal(dense(one.x), dense(other.x))


def test_only_tables_of_the_shared_folder_are_forgotten(spark, folder, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("own") / "table")
    spark.range(3).write.parquet(path)
    with pytest.raises(ValueError):
        session.forget(spark.read.parquet(path))
    assert spark.read.parquet(path).count() == 3
    table = session.written(spark.range(3), "gone", shuffles_go=True)
    assert table.count() == 3 and _tables(folder) == ["gone"]
    session.forget(table)
    assert _tables(folder) == []
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") != "true"


def test_the_rank_log_leaves_one_round(spark, folder):
    """Tables of earlier rounds are gone at the end: at most one of each is left."""
    from rankgrid.workloads import lowrank

    rows = lowrank.invsqrt_rank_log(spark, DATA).collect()
    left = [p.name.rsplit("-", 1)[0] for p in folder.iterdir()]
    assert rows and all(left.count(t) <= 1 for t in ("x", "t", "zy"))


def test_a_residual_leaves_no_product(spark, folder):
    from rankgrid.operators.iterate import residual

    a = np.diag([4.0, 9.0, 16.0, 25.0]) + 0.5
    m, r = matrix(spark, a, Axis.uniform(4, 2), Axis.uniform(4, 2)), matrix(spark, np.eye(4) / 3, Axis.uniform(4, 2), Axis.uniform(4, 2))
    assert residual(r, m, keep=False) == pytest.approx(residual(r, m)) == pytest.approx(np.linalg.norm(a / 9 - np.eye(4)))
    assert sum(p.name.startswith("residual") for p in folder.iterdir()) == 1
