"""Products of few rounds: cells hold their operands, and no part of the result."""

import numpy as np
from pyspark.sql import functions as F

from rankgrid.functions.tiles import Tile
from rankgrid.operators import multiply
from rankgrid.operators.multiply import Grid, Update, default_grid, mm_panels
from rankgrid.schema import Axis, tile_row
from tests.test_matrices import dense, matrix


def test_copies_do_not_grow_with_the_result():
    """120,000 by 120,000 through 64: 60 copies of each tile before, for both operands together."""
    axis = Axis.uniform(120_000, 250)
    g = default_grid(axis, axis, 6, summed=64)
    assert g.pr * g.pc >= 12 and g.pr + g.pc <= 8
    assert 8 * 64 * (axis.n / g.pr + axis.n / g.pc) <= multiply.CELL_BYTES
    large = Axis.uniform(1 << 20, 1 << 10)
    assert default_grid(large, large, 4, summed=1 << 20) == default_grid(large, large, 4)


def test_a_cell_works_out_a_tile_when_it_is_asked_for(monkeypatch):
    made = []
    monkeypatch.setattr(multiply, "Sum", type("Counted", (multiply.Sum,), {"__init__": lambda s, eps=0.0: (made.append(1), super(multiply.Sum, s).__init__(), setattr(s, "eps", eps), setattr(s, "tile", None))[0]}))
    cell = multiply._Cell(Update(open_rounds=2))
    a, b = np.arange(24.0).reshape(6, 4), np.arange(24.0).reshape(4, 6) + 1
    for k in range(2):
        for o in range(3):
            for side, t in ((0, a[2 * o : 2 * o + 2, 2 * k : 2 * k + 2]), (1, b[2 * k : 2 * k + 2, 2 * o : 2 * o + 2])):
                cell.take({"side": side, "turn": k, "k": k, "o": o, **tile_row(0, 0, Tile(t.copy()))})
    rows = cell.results()
    first = next(rows)
    assert len(made) == 1
    got = np.zeros((6, 6))
    for r in [first, *rows]:
        got[2 * r["bi"] : 2 * r["bi"] + 2, 2 * r["bj"] : 2 * r["bj"] + 2] = np.frombuffer(r["x"]).reshape(2, 2)
    assert np.array_equal(got, a @ b) and len(made) == 9


def test_entries_leave_the_task_that_made_their_tile(spark):
    rng = np.random.default_rng(5)
    a, b = rng.integers(-3, 4, (20, 12)).astype(float), rng.integers(-3, 4, (12, 10)).astype(float)
    x, y = matrix(spark, a, Axis.uniform(20, 6), Axis.uniform(12, 4)), matrix(spark, b, Axis.uniform(12, 4), Axis.uniform(10, 3))
    for grid, depth in ((None, "all"), (Grid(2, 2), "all"), (Grid(2, 2), 2)):
        c = mm_panels(x, y, grid, depth=depth)
        assert np.array_equal(dense(c), a @ b)
        for zeros in (True, False):
            got = {(r["i"], r["j"]): r["v"] for r in c.to_coo(drop_zeros=zeros).collect()}
            assert got == {(i, j): v for (i, j), v in np.ndenumerate(a @ b) if v or not zeros}
    plan = mm_panels(x, y, depth="all").to_coo().groupBy().agg(F.sum("v"))._jdf.queryExecution().optimizedPlan().toString()
    of_blocks = mm_panels(x, y, depth="all").blocks.groupBy().agg(F.sum("norm"))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == of_blocks.count("MapInArrow") > 0
