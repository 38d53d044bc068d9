"""Tiles that store few entries are multiplied by entries, and a cell without an order among rounds holds entries, not sums."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankgrid.functions.tiles import Sum, Tile
from rankgrid.operators import multiply
from rankgrid.operators.blocking import to_blocks
from rankgrid.operators.multiply import Grid, Update, _Cell, mm_panels
from rankgrid.schema import Axis, BlockMatrix, sparse_row, tile_row


def _rows(rng, rounds, tiles, side, fill):
    """Sparse tiles of a left and a right operand by round, and both as arrays."""
    a, b = (np.where(rng.random((s, t)) < fill, rng.integers(1, 9, (s, t)), 0).astype(float) for s, t in ((tiles * side, rounds * side), (rounds * side, tiles * side)))
    rows = []
    for k in range(rounds):
        for which, x in enumerate((a[:, k * side : (k + 1) * side], b[k * side : (k + 1) * side].T)):
            for o in range(tiles):
                own = x[o * side : (o + 1) * side] if which == 0 else x[o * side : (o + 1) * side].T
                i, j = np.nonzero(own)
                if len(i):
                    rows.append({"side": which, "turn": k, "k": k, "o": o, **sparse_row(0, 0, side, side, i, j, own[i, j])})
    return rows, a @ b


def _result(cell, n, side):
    out = np.zeros((n, n))
    for r in cell.results():
        out[r["bi"] * side : (r["bi"] + 1) * side, r["bj"] * side : (r["bj"] + 1) * side] = np.frombuffer(r["x"]).reshape(side, side)
    return out


@pytest.mark.parametrize("any_order", [True, False])
def test_few_entries_make_no_arrays_of_operands(monkeypatch, any_order):
    monkeypatch.setattr(multiply, "read_tile", None)
    monkeypatch.setattr(multiply, "multiply", None)
    rows, want = _rows(np.random.default_rng(1), 12, 3, 20, 0.03)
    cell = _Cell(Update(alpha=2.0, open_rounds=4, any_order=any_order))
    for r in rows:
        cell.take(r)
    # without an order among rounds no sum is held, and a tile of the result is worked out when it is asked for
    assert bool(cell.sums) is not any_order
    assert np.array_equal(_result(cell, 60, 20), 2 * want)


def test_many_pairs_go_in_pieces(monkeypatch):
    from rankgrid.functions import tiles

    monkeypatch.setattr(tiles, "PAIRS", 7)
    rows, want = _rows(np.random.default_rng(2), 5, 2, 20, 0.05)
    cell = _Cell(Update(open_rounds=8))
    for r in rows:
        cell.take(r)
    assert np.array_equal(_result(cell, 40, 20), want)


def test_entries_beyond_their_bytes_become_sums(monkeypatch):
    monkeypatch.setattr(multiply, "ENTRY_BYTES", 500)
    rows, want = _rows(np.random.default_rng(3), 12, 2, 20, 0.05)
    cell = _Cell(Update(open_rounds=2, any_order=True))
    for r in rows:
        cell.take(r)
    assert cell.sums and np.array_equal(_result(cell, 40, 20), want)


def test_entries_meet_full_and_low_rank_tiles():
    rng = np.random.default_rng(4)
    side, x, y = 20, rng.normal(size=(20, 2)), rng.normal(size=(20, 2))
    rows, want = _rows(rng, 3, 1, side, 0.05)
    full = rng.normal(size=(side, side))
    extra = [{"side": 0, "turn": 3, "k": 3, "o": 0, **tile_row(0, 0, Tile(x, y))}, {"side": 1, "turn": 3, "k": 3, "o": 0, **tile_row(0, 0, Tile(full))}]
    cell = _Cell(Update(open_rounds=2, any_order=True))
    for r in [*rows, *extra]:
        cell.take(r)
    assert np.allclose(_result(cell, side, side), want + x @ y.T @ full)


def test_a_low_rank_sum_takes_entries():
    s = Sum()
    s.take(Tile(np.ones((4, 1)), np.ones((4, 1))))
    s.add_at((4, 4), np.array([0, 5, 5]), np.array([1.0, 2.0, 3.0]))
    assert np.array_equal(s.result().dense(), np.ones((4, 4)) + np.diag([1.0, 5.0, 0.0, 0.0]))


def test_a_screened_product_by_entries(spark):
    rng = np.random.default_rng(5)
    n = 60
    a = np.where(rng.random((n, n)) < 0.03, rng.integers(1, 9, (n, n)), 0).astype(float)
    i, j = np.nonzero(a)
    entries = spark.createDataFrame([(int(p), int(q), float(v)) for p, q, v in zip(i, j, a[i, j])], "i long, j long, v double")
    m = to_blocks(entries, Axis.uniform(n, 20), Axis.uniform(n, 20), sparse=True)
    only = spark.createDataFrame([(0, 0), (1, 2)], "bi int, bj int")
    for kept, mask in ((None, np.ones((n, n))), (only, np.kron(np.array([[1, 0, 0], [0, 0, 1], [0, 0, 0]]), np.ones((20, 20))))):
        got = np.zeros((n, n))
        for r in mm_panels(m, m, Grid(3, 1), depth="all", only=kept).to_coo().collect():
            got[r["i"], r["j"]] = r["v"]
        assert np.array_equal(got, (a @ a) * mask)


def test_few_places_make_few_cells(spark, monkeypatch):
    """A block diagonal product has as many cells as its own places need, and a full one as many as default_grid says."""
    monkeypatch.setattr(multiply, "CELL_BYTES", 64 * 8 * 8)
    monkeypatch.setattr(multiply, "CELLS_PER_CORE", 1)
    axis = Axis.uniform(24 * 8, 8)
    most = multiply.default_grid(axis, axis, spark.sparkContext.defaultParallelism)
    for places, few in ((F.col("bi") == F.col("bj"), True), (F.lit(True), False)):
        t = spark.range(24 * 24).select(F.floor(F.col("id") / 24).cast("int").alias("bi"), (F.col("id") % 24).cast("int").alias("bj"), F.lit(8).alias("m"), F.lit(8).alias("n")).where(places)
        m = BlockMatrix(t, axis, axis)
        got = multiply.places_grid(m, m)
        assert (got.pr * got.pc < most.pr * most.pc) is few


def test_the_default_rounds_on_a_grid_of_places(spark, monkeypatch):
    from rankgrid.workloads import products

    grids = []
    mm = multiply.mm_panels
    monkeypatch.setattr(multiply, "mm_panels", lambda a, b, grid=None, **how: grids.append((grid, how)) or mm(a, b, grid, **how))
    assert products.mm_multi_issue(spark, "/root/testdata/sf0.001").count() and grids[0][0] and not grids[0][1]
