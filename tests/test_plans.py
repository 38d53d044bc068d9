"""Formulas and schedules against the values computed by hand."""

import pytest

from rankgrid.operators.multiply import round_order
from rankgrid.plans import costs, planner, schedule


@pytest.mark.parametrize(("pr", "pc", "depth"), [(1, 1, 2), (2, 8, 2), (3, 5, 3), (8, 8, 8), (8, 16, 8)])
def test_default_depth(pr, pc, depth):
    assert costs.optimal_depth(pr, pc) == depth


def test_dense_memory_by_hand():
    fixed = costs.mem_dense(32768, 32768, 32768, 256, 8, 8, 0)
    assert costs.mem_dense(32768, 32768, 32768, 256, 8, 8, 8) - fixed == 16_777_216
    assert fixed == 50_331_648
    assert costs.mem_overhead_ratio(32768, 256, 64, 8) == pytest.approx(1 / 3)
    assert costs.mem_square(32768, 256, 64, 8) == costs.mem_dense(32768, 32768, 32768, 256, 8, 8, 8)
    assert costs.mem_sparse(100, 100, 100, 10, 2, 2, 2, 1, 1, 1, 2, 2) == costs.mem_dense(100, 100, 100, 10, 2, 2, 2)


def test_apparent_flops():
    assert costs.flops_iteration(26790, 10) == pytest.approx(1.538e15, rel=1e-3)


def test_depth_for_memory_is_the_largest_that_fits():
    d = costs.depth_for_memory(4096, 4096, 4096, 128, 4, 4, 5e6)
    assert costs.mem_dense(4096, 4096, 4096, 128, 4, 4, d) <= 5e6 < costs.mem_dense(4096, 4096, 4096, 128, 4, 4, d + 1)


def test_makespans(spark):
    rows = [(k, p, float((4, 1)[(k + p) % 2])) for k in range(4) for p in range(2)]
    c = spark.createDataFrame(rows, "k int, p int, cost double")
    r = schedule.makespan(c, 2).first()
    assert (r["sync"], r["waves"], r["decoupled"], r["mean"]) == (16, 10, 10, 10)
    assert schedule.sliding_times(c, 2).agg({"finish": "max"}).first()[0] == 10
    assert schedule.sliding_times(c, 1).agg({"finish": "max"}).first()[0] == 16


def test_barriers_and_orders():
    assert [schedule.count_barriers(10, 4, m) for m in ("sync", "waves", "decoupled")] == [10, 3, 1]
    assert round_order(6, 3, "by_owner") == [0, 3, 1, 4, 2, 5]


def test_chain_and_variant():
    assert planner.chain_order([(40, 20), (20, 30), (30, 10), (10, 30)]) == (26000, "((M0 (M1 M2)) M3)")
    big = planner.choose_variant(10**9, 10**9, 10**9, (10**5, 10**5, 10**5), 512, 64, 1e12)
    assert big.grid.pr * big.grid.pc * big.grid.layers == 64
    assert planner.choose_variant(10**9, 1000, 10**6, (10**5, 10, 10**5), 512, 64, 1e9).variant == "broadcast"
