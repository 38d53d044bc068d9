"""Whole matrices: variants agree, edge cases, plans, the iteration by hand."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankgrid.functions.tiles import Tile
from rankgrid.operators import blocking, lrb
from rankgrid.operators.iterate import Options, inv_sqrt, residual
from rankgrid.operators.multiply import CELL_BYTES, Grid, default_grid, mm_auto, mm_entries, mm_panels, mm_shift, mm_split, shift_step
from rankgrid.operators.screening import screen_product
from rankgrid.schema import BLOCKS, COO, Axis, BlockMatrix, tile_row


def matrix(spark, a, rows, cols, keep_zero=False):
    r, c = rows.starts, cols.starts
    out = []
    for i in range(rows.blocks):
        for j in range(cols.blocks):
            x = a[r[i] : r[i + 1], c[j] : c[j + 1]]
            if x.any() or keep_zero:
                out.append(tile_row(i, j, Tile(x.astype(float))))
    return BlockMatrix(spark.createDataFrame([tuple(x[k] for k in ("bi", "bj", "m", "n", "repr", "rank", "norm", "x", "w")) for x in out], BLOCKS), rows, cols)


def dense(m):
    a = np.zeros((m.rows.n, m.cols.n))
    for r in m.to_coo().collect():
        a[r["i"], r["j"]] = r["v"]
    return a


@pytest.fixture(scope="module")
def pair(spark):
    rng = np.random.default_rng(3)
    rows, mid, cols = Axis((0, 1, 4, 9)), Axis((0, 5, 6, 8, 14)), Axis((0, 3, 7))
    a, b = rng.integers(-3, 4, (9, 14)), rng.integers(-3, 4, (14, 7))
    a[:, 5:6] = 0  # an absent column panel
    return a, b, matrix(spark, a, rows, mid), matrix(spark, b, mid, cols)


@pytest.mark.parametrize("options", [{"depth": 1}, {"depth": 2, "order": "by_owner"}, {"depth": "all"}, {"depth": 2, "mode": "sliding"}, {"depth": "all", "stationary": "A"}, {"depth": "all", "stationary": "B"}, {"depth": "all", "row_step": 1}, {"depth": 99}, {"depth": "all", "sparse": True}])
def test_variants_agree_on_uneven_tiles(pair, options):
    a, b, x, y = pair
    assert np.array_equal(dense(mm_panels(x, y, Grid(2, 3), **options)), a @ b)


def test_grid_larger_than_the_matrix_and_layers(pair):
    a, b, x, y = pair
    assert np.array_equal(dense(mm_panels(x, y, Grid(7, 5), "all")), a @ b)
    assert np.array_equal(dense(mm_panels(x, y, Grid(1, 2, 3), "all")), a @ b)
    assert np.array_equal(dense(mm_auto(x, y, hot=2)), a @ b)
    assert np.array_equal(dense(mm_split(y.T, x.T)), (a @ b).T)


def test_blockings_must_conform(pair):
    _, _, x, _ = pair
    with pytest.raises(ValueError, match="blockings"):
        mm_panels(x, x)


def test_empty_matrix(spark):
    axis = Axis.uniform(4, 2)
    empty = BlockMatrix(spark.createDataFrame([], BLOCKS), axis, axis)
    assert mm_panels(empty, empty, depth="all").to_coo().count() == 0


def test_nan_is_rejected(spark):
    with pytest.raises(Exception, match="NaN"):
        blocking.validate_coo(spark.createDataFrame([(0, 0, float("nan"))], COO)).collect()


def test_screening_edge(spark):
    one = spark.createDataFrame([(0, 0, 2, 2.0, 1, "F"), (0, 1, 4, 1.505, 1, "F")], "bi int, bj int, area long, norm double, rank int, repr string")
    b = spark.createDataFrame([(0, 0, 6, 1.5, 1, "F"), (1, 1, 6, 2.0, 1, "F")], "bi int, bj int, area long, norm double, rank int, repr string")
    # estimates 3.0 and 3.01 on area 6 at 0.5: the first is left out
    kept = screen_product(one, b, Axis((0, 2)), Axis((0, 3, 6)), 0.5).collect()
    assert [(r["bi"], r["bj"]) for r in kept] == [(0, 1)]


def test_metadata_queries_read_no_payload(spark, tmp_path):
    axis = Axis.uniform(4, 2)
    m = matrix(spark, np.arange(16).reshape(4, 4) + 1, axis, axis)
    m.blocks.write.parquet(str(tmp_path / "t"))
    stored = BlockMatrix(spark.read.parquet(str(tmp_path / "t")), axis, axis)
    plan = screen_product(stored.norms(), stored.norms(), axis, axis, 0.0)._jdf.queryExecution().executedPlan().toString()
    assert "x#" not in plan.split("ReadSchema")[-1]
    assert "CartesianProduct" not in plan


def plan_of(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("depth", ["all", 2, None])
def test_one_shuffle_for_all_rounds(pair, depth):
    _, _, x, y = pair
    plan = plan_of(mm_panels(x, y, Grid(2, 2), depth).blocks)
    assert plan.count("Repartition") == 1 or plan.count("RepartitionByExpression") == 1


def test_jobs_read_their_own_rounds(spark, pair, monkeypatch):
    """Each job of the synchronous product reads one folder of the written operands."""
    from rankgrid.operators import multiply

    read = []
    placed = multiply._placed

    def spy(cells, parts):
        read.append(cells._jdf.queryExecution().executedPlan().toString())
        return placed(cells, parts)

    monkeypatch.setattr(multiply, "_placed", spy)
    a, b, x, y = pair
    assert np.array_equal(dense(mm_panels(x, y, Grid(2, 2), depth=2, mode="waves")), a @ b)
    assert len(read) == 2
    for job, plan in enumerate(read):
        filters = re.findall(r"PartitionFilters: \[([^\]]*)\]", plan)
        assert filters
        assert all(re.search(rf"\(job#\d+ = {job}\)", f) for f in filters)


def test_panels_are_gathered_before_they_are_sent(pair):
    _, _, x, y = pair
    plans = {k: plan_of(mm_panels(x, y, Grid(2, 3), bcast=k).blocks) for k in ("tiles", "panel")}
    assert "Aggregate" not in plans["tiles"]
    assert "Aggregate" in plans["panel"]


def test_cells_follow_the_cores_and_the_result():
    axis = Axis.uniform(4096, 128)
    one, many = (default_grid(axis, axis, cores) for cores in (4, 64))
    assert one.pr * one.pc >= 8
    assert many.pr * many.pc >= 128
    large = Axis.uniform(1 << 20, 4096)
    g = default_grid(large, large, 4)
    assert 8 * (1 << 40) / (g.pr * g.pc) <= 2 * CELL_BYTES
    assert default_grid(Axis.uniform(4, 4), Axis.uniform(4, 4), 64) == Grid(1, 1)


def test_screened_tiles_are_not_formed(spark, pair, monkeypatch):
    """The automatic update forms each tile once; a list of tiles limits the product to them."""
    a, b, x, y = pair
    only = spark.createDataFrame([(0, 0), (2, 1)], "bi int, bj int")
    c = dense(mm_panels(x, y, Grid(2, 2), "all", only=only))
    want = np.zeros_like(a @ b)
    want[:1, :3], want[4:, 3:] = (a @ b)[:1, :3], (a @ b)[4:, 3:]
    assert np.array_equal(c, want)
    tiles = mm_auto(x, y, hot=2).blocks.select("bi", "bj").collect()
    assert len(tiles) == len(set(tiles))


def test_every_product_meets_at_one_step_of_the_shift(pair):
    a, b, x, y = pair
    met = [(r["bi"], r["bk"], r["bj"]) for s in range(2) for r in shift_step(x, y, 2, s).select("bi", "bk", "bj").collect()]
    there = {(r["bi"], r["bj"]) for r in x.blocks.collect()}, {(r["bi"], r["bj"]) for r in y.blocks.collect()}
    assert sorted(met) == sorted((i, k, j) for i, k in there[0] for k2, j in there[1] if k == k2)
    assert np.array_equal(dense(mm_shift(x, y, 2)), a @ b)


@pytest.mark.parametrize("options", [{"depth": 1, "prefetch": 2}, {"depth": 3}, {"depth": 2, "order": "release"}, {"bcast": "panel", "depth": 2}, {"bcast": "panel", "depth": 1}, {"depth": 2, "mode": "waves"}, {"depth": 1, "mode": "stream"}])
def test_ways_to_issue_rounds_agree(pair, options):
    a, b, x, y = pair
    assert np.array_equal(dense(mm_panels(x, y, Grid(2, 3), **options)), a @ b)


def test_entries_without_an_index_stand_nowhere(spark):
    rows = spark.createDataFrame([(0, 1, 2.0), (0, 1, 3.0), (None, 1, 4.0), (1, None, 5.0), (1, 0, None)], "i long, j long, v double")
    m = blocking.coo(rows, "i", "j", F.col("v"))
    assert sorted((r["i"], r["j"], r["v"]) for r in m.collect()) == [(0, 1, 5.0), (1, 0, None)]
    for axis in (Axis.uniform(4, 2), Axis((0, 1, 4))):
        assert np.array_equal(dense(blocking.to_blocks(rows, axis, axis))[0], [0, 5, 0, 0])
        assert blocking.to_blocks(rows.limit(0), axis, axis).blocks.count() == 0
    assert mm_entries(m, m.limit(0)).count() == 0
    assert [(r["i"], r["j"], r["v"]) for r in mm_entries(rows.where("v IS NOT NULL"), rows).where("i = 0 AND j = 0").collect()] == [(0, 0, None)]


def test_kernel_blocks_are_bounded(spark):
    from rankgrid.sources.matrices import kernel_matrix, positions

    p = positions(spark, "/root/testdata/sf0.001", "customer")
    whole, _ = kernel_matrix(p, "longrange", by="region")
    cut, _ = kernel_matrix(p, "longrange", by="region", most=7)
    assert max(cut.rows.length(b) for b in range(cut.rows.blocks)) <= 7
    assert np.array_equal(dense(whole), dense(cut))


def test_iteration_by_hand(spark):
    axis = Axis((0, 1, 2))
    m = matrix(spark, np.diag([1.0, 0.25]), axis, axis)
    one = inv_sqrt(m, 1, alpha=1.0)
    assert np.allclose(dense(one.z), np.diag([1, 1.5859375]))
    assert np.allclose(dense(one.y), np.diag([1, 0.396484375]))
    assert np.allclose(dense(inv_sqrt(m, 6, alpha=1.0).inverse()), np.diag([1, 2]), atol=1e-6)


def test_low_rank_iteration_stays_within_its_bound(spark):
    x = np.linspace(0, 6, 24)
    a = 1 / np.sqrt(1 + (x[:, None] - x[None, :]) ** 2) + np.eye(24)
    axis = Axis.uniform(24, 12)
    m = lrb.compress(matrix(spark, a, axis, axis), 1e-6)
    r = inv_sqrt(m, 8, options=Options(eps_lr=1e-6))
    assert residual(r.inverse(), m) <= 100 * 1e-6
    w, v = np.linalg.eigh(a)
    assert np.abs(dense(r.inverse()) - (v / np.sqrt(w)) @ v.T).max() < 1e-4


def test_orderings_and_splits(spark):
    t = spark.createDataFrame([(1, "b", 2.0), (2, "a", 1.0), (3, "b", 1.0)], "k long, g string, v double")
    o = {r["key"]: (r["pos"], r["b"], r["off"]) for r in blocking.ordering(t, "t", "k", ["g"], ["v"]).collect()}
    assert o == {2: (0, 0, 0), 3: (1, 1, 0), 1: (2, 1, 1)}
    cut = blocking.overdecompose(blocking.uniform_blocking(spark, "x", 10, 7), 3).orderBy("start").collect()
    assert [(r["start"], r["len"]) for r in cut] == [(0, 2), (2, 2), (4, 3), (7, 3)]


def test_customer_kernel_has_every_customer(spark):
    from rankgrid.session import table
    from rankgrid.workloads.lowrank import customer

    sf_dir = "/root/testdata/sf0.001"
    n = table(spark, sf_dir, "customer").count()
    for by in ("region", "nation"):
        m = customer(spark, sf_dir, "longrange", eps_lr=0.0, by=by)
        assert (m.rows.n, m.cols.n) == (n, n)
        assert m.blocks.selectExpr("sum(m * n)").first()[0] == n * n
