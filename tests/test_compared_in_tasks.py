"""Kernel tiles are compressed and compared in the tasks that make them."""

import numpy as np
import pytest

from rankgrid.functions import tiles
from rankgrid.operators import lrb
from rankgrid.plans import costs
from rankgrid.schema import BlockMatrix
from rankgrid.session import written
from rankgrid.sources import matrices as mx
from rankgrid.workloads import lowrank

DATA = "/root/testdata/sf0.001"


def _dense(spark, kind="longrange"):
    m, _ = mx.kernel_matrix(mx.positions(spark, DATA, "customer"), kind, by="nation")
    return m


def test_the_sweep_compresses_and_compares_at_each_threshold(spark, monkeypatch):
    seen, compared = [], []
    compress, block_errors = lrb.compress, getattr(lrb, "block_errors", None)
    monkeypatch.setattr(lrb, "compress", lambda m, e: seen.append(e) or compress(m, e))
    monkeypatch.setattr(lrb, "block_errors", lambda m, lows: compared.extend(lows) or block_errors(m, lows), raising=False)
    got = lowrank.eps_sweep(spark, DATA).collect()
    assert seen == [1e-1, 1e-3, 1e-5, 1e-7] == [r["eps"] for r in got] and len(compared) == 4


def test_errors_are_measured_on_the_compressed_tiles():
    z = np.linspace(-1, 10, 120)
    a = 1 / np.sqrt(1 + 4 + (z[:, None] - z[None]) ** 2)
    for t, err in tiles.compress_all(a, (1e-1, 1e-3, 1e-5, 1e-7)):
        assert err == np.linalg.norm(a - t.dense())


def test_errors_in_tasks_are_those_of_the_join(spark):
    m = _dense(spark)
    stored = BlockMatrix(written(m.blocks, "kernel"), m.rows, m.cols)
    lows = [1e-1, 1e-5]
    together = lrb.block_errors(m, [lrb.compress(m, e) for e in lows]).collect()
    for k, e in enumerate(lows):
        want = {(r["bi"], r["bj"]): r for r in lrb.block_error(stored, lrb.compress(stored, e)).collect()}
        for got in ([r for r in together if r["matrix"] == k], lrb.block_error(m, lrb.compress(m, e)).collect()):
            assert len(got) == len(want) == m.rows.blocks**2
            for r in got:
                w = want[r["bi"], r["bj"]]
                assert (r["rank"], r["repr"], r["m"], r["n"]) == (w["rank"], w["repr"], w["m"], w["n"])
                assert r["err"] == pytest.approx(w["err"], abs=1e-12, rel=1e-9)


def test_pairs_of_blocks_are_spread_over_the_cores(spark):
    m = _dense(spark)
    assert m.made.rows.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism


def test_natural_errors_store_no_payload(spark, monkeypatch):
    names = []
    monkeypatch.setattr(lowrank, "written", lambda df, name, **how: names.append(df.columns) or written(df, name, **how))
    assert lowrank.lrb_compress(spark, DATA).collect() and lowrank.lrb_error(spark, DATA).collect()
    assert not any("x" in columns for columns in names)


def test_flops_of_tiles_that_are_alike(spark):
    rows = [(i, j, 4 + i % 2, 4 + j % 2, "L" if (i + j) % 3 else "F", 1 + (i * j) % 2 if (i + j) % 3 else 4) for i in range(5) for j in range(5)]
    want = 0
    for i, k, m, kk, form, r in rows:
        for k2, _, _, n, form2, r2 in rows:
            if k == k2:
                x, y = (tiles.Tile(np.ones((p, q))) if f == "F" else tiles.Tile(np.ones((p, s)), np.ones((q, s))) for p, q, f, s in ((m, kk, form, r), (kk, n, form2, r2)))
                want += tiles.product_flops(x, y)
    t = spark.createDataFrame(rows, "bi int, bj int, m int, n int, repr string, rank int")
    assert costs.flops_lrb(t, t).first()["flops"] == want
