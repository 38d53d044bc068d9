"""Experiments that SQL cannot follow, against NumPy on the smallest tables, and measures that are random or approximate."""

import duckdb
import numpy as np
import pytest

from rankgrid import registry
from rankgrid.functions import tiles
from rankgrid.operators import iterate, lrb
from rankgrid.operators.iterate import choose_alpha, inv_sqrt
from rankgrid.plans import planner
from rankgrid.schema import Axis
from rankgrid.workloads.experiments import _digits, inverse_roots
from rankgrid.workloads.lowrank import EPS_LR, customer, supplier
from tests.test_matrices import dense, matrix

DATA = "/root/testdata/sf0.001"


def run(spark, name):
    return registry.queries()[name](spark, DATA).collect()


def inverse_root(a):
    w, v = np.linalg.eigh(a)
    return (v / np.sqrt(w)) @ v.T


def test_inverse_roots_of_every_customer(spark):
    m, found = inverse_roots(spark, DATA, "decay", 6)
    a = dense(m)
    want = inverse_root(a)
    for form, r in found:
        z = dense(r.inverse())
        error = np.linalg.norm(z @ a @ z - np.eye(len(a)))
        assert np.abs(z - want).max() < (1e-8 if form == "F" else 1e-4)
        assert _digits(iterate.residual(r.inverse(), m)) == _digits(error) or error < 1e-9
        assert error <= 100 * EPS_LR


def test_histogram_counts_the_ranks_of_the_stored_tiles(spark):
    m = customer(spark, DATA, by="nation")
    n = m.rows.blocks
    by = {}
    for r in run(spark, "w3_hist"):
        by.setdefault(r["matrix"], {})[r["bin"]] = r["blocks"]
    assert set(by) == {"input", "x", "t", "z", "y"}
    assert all(sum(h.values()) == n * n and h[0] > 0 for h in by.values())
    kinds = [(r["repr"], r["rank"], min(r["m"], r["n"])) for r in m.blocks.select("repr", "rank", "m", "n").collect()]
    want = np.bincount([11 if k == "F" else -(-10 * rank // full) for k, rank, full in kinds], minlength=12)
    assert {k: v for k, v in by["input"].items() if k} == {k: int(v) for k, v in enumerate(want) if v}


def test_errors_fall_with_the_threshold(spark):
    rows = run(spark, "eps_sweep")
    a, starts = dense(customer(spark, DATA, "longrange", eps_lr=0.0, by="nation")), customer(spark, DATA, "longrange", eps_lr=0.0, by="nation").rows.starts
    for r in rows:
        parts = [a[i:j, k:n] for i, j in zip(starts, starts[1:], strict=False) for k, n in zip(starts, starts[1:], strict=False)]
        low = [tiles.compress(p, r["eps"]) for p in parts]
        assert r["error"] == pytest.approx(np.sqrt(sum(np.linalg.norm(p - t.dense()) ** 2 for p, t in zip(parts, low, strict=True))), rel=1e-6, abs=1e-12)
        assert r["storage"] == pytest.approx(sum(t.stored for t in low) / a.size)
    errors, stored = [r["error"] for r in rows], [r["storage"] for r in rows]
    assert errors == sorted(errors, reverse=True)
    assert stored == sorted(stored)
    assert errors[0] > 100 * errors[1]


@pytest.mark.parametrize("name", ["w7_eps", "lrb_exact_limit"])
def test_products_become_exact(spark, name):
    rows = run(spark, name)
    for kind in {r.asDict().get("kind") for r in rows}:
        errors = [r["error"] for r in rows if r.asDict().get("kind") == kind]
        assert errors == sorted(errors, reverse=True)
        assert errors[-1] < 1e-9 < errors[0]


def test_ranks_are_logged_in_each_round(spark):
    rows = run(spark, "invsqrt_rank_log")
    n = customer(spark, DATA, by="nation").rows.blocks
    sums = {}
    for r in rows:
        sums[r["round"], r["matrix"]] = sums.get((r["round"], r["matrix"]), 0) + r["blocks"]
    assert sums == {(k, m): n * n for k in range(1, 6) for m in "xtzy"}


def test_scaling_factors(spark):
    m = supplier(spark, DATA, by="nation")
    w = np.linalg.eigvalsh(dense(m))
    assert choose_alpha(m) == pytest.approx(1 / np.abs(dense(m)).sum(1).max())
    power = choose_alpha(m, "power", 12)
    assert power == pytest.approx(1 / w[-1], rel=0.02)
    assert np.abs(power * w - 1).max() <= 1
    both = choose_alpha(m, "two_sided", 12)
    assert both == pytest.approx(2 / (w[0] + w[-1]), rel=0.1)
    assert np.abs(both * w - 1).max() <= 1


def test_low_rank_tiles_give_the_same_factors(spark):
    m = supplier(spark, DATA, "longrange", by="region", eps_lr=1e-10)
    full = lrb.with_repr(m, "F")
    assert choose_alpha(m) == pytest.approx(choose_alpha(full))
    assert choose_alpha(m, "power", 5) == pytest.approx(choose_alpha(full, "power", 5))


def test_two_sided_factor_needs_fewer_rounds(spark):
    a = np.diag(np.linspace(1, 30, 12)) + 0.5
    m = matrix(spark, a, Axis.uniform(12, 4), Axis.uniform(12, 4))
    far = {how: iterate.distance_from_identity(inv_sqrt(m, 2, alpha=choose_alpha(m, how, 8)).x) for how in ("inf", "two_sided")}
    assert far["two_sided"] < far["inf"]


def test_approximate_counts_are_near(spark):
    r = run(spark, "agg_approx_distinct")[0]
    parts, pairs = duckdb.sql(f"SELECT count(DISTINCT l_partkey), count(DISTINCT (l_partkey, l_suppkey)) FROM '{DATA}/lineitem.parquet'").fetchall()[0]
    assert abs(r["parts"] - parts) <= 0.15 * parts
    assert abs(r["pairs"] - pairs) <= 0.08 * pairs


def test_stream_drops_repeats(spark):
    got = [tuple(r) for r in run(spark, "stream_dedup")]
    batch = spark.read.parquet(f"{DATA}/events.parquet").select("user_id", "event_type")
    assert set(got) == {tuple(r) for r in batch.distinct().collect()}
    assert len(got) < batch.count()


def test_explain_names_the_plan(spark):
    m = matrix(spark, np.arange(36.0).reshape(6, 6) + 1, Axis.uniform(6, 2), Axis.uniform(6, 2))
    text = planner.explain_mm(m, m, 4)
    assert "rounds in flight" in text
    assert "432 apparent flops" in text
