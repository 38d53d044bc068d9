"""Tiles of natural blocks that are cut into parts, and tasks that hold a few tiles whatever a batch has."""

import shutil

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rankgrid.functions import tiles
from rankgrid.schema import ARROW_BLOCKS, block_batch, map_tiles, tile_row
from rankgrid.sources import matrices as mx


@pytest.mark.parametrize("name", ["lrb_compress", "lrb_error"])
def test_natural_tiles_of_many_points(spark, tmp_path, name):
    """650 points a region are cut into parts; the rows are about whole regions."""
    from rankgrid import registry

    shutil.copy("/root/testdata/sf0.001/nation.parquet", tmp_path / "nation.parquet")
    nations = spark.read.parquet(f"{tmp_path}/nation.parquet").where("n_regionkey in (1, 3)").groupBy("n_regionkey").agg(F.min("n_nationkey").alias("n")).collect()
    first, second = (r["n"] for r in nations)
    i = F.col("id")
    supp = spark.range(1300).select(i.alias("s_suppkey"), F.when(i % 2 == 0, first).otherwise(second).alias("s_nationkey"), (i * 37 % 9999 - 999).cast("double").alias("s_acctbal"))
    supp.coalesce(1).write.parquet(f"{tmp_path}/supplier.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW supplier AS SELECT * FROM read_parquet('{tmp_path}/supplier.parquet/*.parquet')")
    con.execute(f"CREATE VIEW nation AS SELECT * FROM read_parquet('{tmp_path}/nation.parquet')")
    df = registry.queries()[name](spark, str(tmp_path))
    want = con.execute(f"SELECT {', '.join(df.columns)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert [tuple(r) for r in df.collect()] == want and want[0][0] == 4


class _Plan:
    """Stands for a DataFrame: gives the function of a task instead of running it."""

    def mapInArrow(self, f, schema):
        return f


def test_a_task_sends_tiles_on_before_its_batch_ends():
    rows = [tile_row(0, k, tiles.Tile(np.full((512, 256), float(k)))) for k in range(24)]
    sent = list(map_tiles(_Plan(), lambda row: [row])(iter([block_batch(rows, ARROW_BLOCKS)])))
    assert len(sent) > 2 and [r for b in sent for r in b.column("bj").to_pylist()] == list(range(24))


def test_kernel_tiles_are_sent_on_before_their_batch_ends(monkeypatch):
    """A batch of many pairs of blocks: their tiles are not all held at once."""
    rng = np.random.default_rng(3)
    points = [[{"pos": k, **dict(zip(("px", "py", "pz"), map(float, p)))} for k, p in enumerate(rng.normal(size=(400, 3)))] for _ in range(2)]
    batch = pa.RecordBatch.from_pylist([{"b": k % 2, "pts": points[k % 2], "b2": k // 2 % 2, "pts2": points[k // 2 % 2]} for k in range(20)])
    monkeypatch.setattr(mx, "_paired", lambda *_: (_Plan(), None, None), raising=False)
    monkeypatch.setattr(mx, "BlockMatrix", lambda blocks, *_: blocks)
    sent = list(mx.kernel_matrix(None, "decay")[0](iter([batch])))
    assert len(sent) > 2
    x, y = (np.array([[p[c] for c in ("px", "py", "pz")] for p in points[k]]) for k in (1, 0))
    want = np.exp(-((x[:, None] - y[None]) ** 2).sum(axis=2))
    assert np.allclose(np.frombuffer(sent[0].column("x")[1].as_py()).reshape(400, 400), want, atol=1e-14)


def test_one_factorization_for_all_thresholds():
    rng = np.random.default_rng(1)
    eps = (1e-1, 1e-3, 1e-5, 1e-7)
    z, y = np.sort(rng.uniform(-1, 10, 120)), np.sort(rng.uniform(-1, 10, 90))
    smooth = 1 / np.sqrt(1 + (z[:, None] - y[None]) ** 2)
    for a in (smooth, smooth * 1e-6, rng.normal(size=(30, 40)), np.outer(z, y), smooth[:1], np.zeros((5, 4))):
        for e, (kind, rank, err) in zip(eps, tiles.compress_each(a, eps)):
            t = tiles.compress(a, e)
            assert (kind, rank) == (t.kind, t.rank) and abs(err - np.linalg.norm(a - t.dense())) <= 1e-9 + 1e-6 * e


def test_the_sweep_makes_no_dense_matrix(spark, monkeypatch):
    """Every customer's tile is compared inside its task."""
    from rankgrid.workloads import lowrank

    monkeypatch.setattr(lowrank, "customer", None)
    got = lowrank.eps_sweep(spark, "/root/testdata/sf0.001").collect()
    assert [r["eps"] for r in got] == [1e-1, 1e-3, 1e-5, 1e-7] and all(r["error"] >= 0 and r["storage"] > 0 for r in got)
