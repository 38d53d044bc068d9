"""Schedules read the shapes of tiles alone, and no entry of the table is shuffled for them."""

import pytest

from rankgrid.operators import blocking
from rankgrid.schema import Axis
from rankgrid.workloads import measures, products

DATA = "/root/testdata/sf0.001"


def test_shapes_are_those_of_the_skeleton(spark):
    rows = [(0, 0, 1.0), (0, 0, 2.0), (3, 4, 0.0), (5, 1, None), (None, 1, 1.0), (6, 4, None), (6, 4, 1.0)]
    entries = spark.createDataFrame(rows, "i long, j long, v double")
    got = blocking.shapes(entries, Axis.uniform(7, 3), Axis.uniform(5, 2)).blocks.select("bi", "bj", "m", "n").collect()
    assert sorted(map(tuple, got)) == [(0, 0, 3, 2), (1, 2, 3, 1), (2, 2, 1, 1)]


def test_of_a_table_too(spark):
    shape = ("bi", "bj", "m", "n")
    got, want = (sorted(map(tuple, f(spark, DATA).blocks.select(*shape).collect())) for f in (products.d1_shapes, products.d1_skeleton))
    assert got == want and len(got) > 1


@pytest.mark.parametrize("run", [measures.sched_makespan, measures.effective_depth, measures.sched_balance])
def test_schedules_sum_no_entries(spark, monkeypatch, run):
    """Sums by part and supplier were shuffled before, one row for each pair that occurs."""
    monkeypatch.setattr(products.mx, "part_supp", None)
    assert run(spark, DATA).count() >= 1
