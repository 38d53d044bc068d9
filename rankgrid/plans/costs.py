"""Closed formulas of memory, work and communication, as plain functions and as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankgrid.schema import Axis


def optimal_depth(pr: int, pc: int) -> int:
    """Rounds in flight by default."""
    return max(2, min(pr, pc))


def mem_dense(m, n, k, block, pr, pc, depth):
    """Numbers a process holds for a product of dense m x k and k x n matrices with tiles of side block: the copied panels
    of `depth` rounds, and its share of the three matrices. Works on numbers and on columns."""
    return depth * (m * block / pr + n * block / pc) + (m * n + m * k + k * n) / (pr * pc)


def mem_square(n, block, p, depth):
    """mem_dense for square matrices on a square grid of p processes."""
    root = F.sqrt(p) if isinstance(p, Column) else math.sqrt(p)
    return depth * 2 * n * block / root + 3 * n * n / p


def mem_sparse(m, n, k, block, pr, pc, depth, fill_a, fill_b, fill_c, active_rows, active_cols):
    """mem_dense with each matrix scaled by its fill, and panels by the share of grid columns (rows) that take part in a round."""
    panels = fill_a * (active_cols / pc) * m * block / pr + fill_b * (active_rows / pr) * n * block / pc
    return depth * panels + (fill_c * m * n + fill_a * m * k + fill_b * k * n) / (pr * pc)


def mem_overhead_ratio(n, block, p, depth):
    """Copied panels against resident matrices, square form."""
    return depth * 2 * n * block / math.sqrt(p) / (3 * n * n / p)


def depth_for_memory(m: int, n: int, k: int, block: int, pr: int, pc: int, budget: float) -> int:
    """The most rounds in flight whose memory stays within the budget, and one at least."""
    fixed = mem_dense(m, n, k, block, pr, pc, 0)
    return max(1, int((budget - fixed) // (mem_dense(m, n, k, block, pr, pc, 1) - fixed)))


def flops_dense(m, n, k):
    return 2 * m * n * k


def flops_iteration(n, rounds=1):
    """Apparent work of the inverse square root: four dense products a round."""
    return 4 * 2 * n**3 * rounds


def flops_lrb(a: DataFrame, b: DataFrame) -> DataFrame:
    """Work of the products of stored tiles (full or low-rank), from metadata alone: one row, flops. Tiles of a block column
    (row) that are alike are counted before they meet, as the pairs of tiles are the cube of the blocks."""
    x = a.groupBy("bj", "m", "n", "repr", "rank").agg(F.count("*").alias("many"))
    y = b.groupBy(F.col("bi").alias("k"), F.col("n").alias("n2"), F.col("repr").alias("repr2"), F.col("rank").alias("rank2")).agg(F.count("*").alias("many2"))
    both = x.join(y, F.col("bj") == F.col("k"))
    m, k, n, ra, rb = (F.col(c).cast("double") for c in ("m", "n", "n2", "rank", "rank2"))
    fa, fb = F.col("repr") != "L", F.col("repr2") != "L"
    side = F.when(rb <= ra, m).otherwise(n)
    work = F.when(fa & fb, 2 * m * k * n).when(fa, 2 * m * k * rb).when(fb, 2 * k * n * ra).otherwise(2 * k * ra * rb + 2 * side * ra * rb)
    return both.agg(F.sum(F.col("many") * F.col("many2") * work).alias("flops"))


def throughput(flops: float, seconds: float) -> float:
    return flops / seconds


def peak_share(flops_per_second: float, peak: float) -> float:
    return flops_per_second / peak


def stored_numbers() -> Column:
    """Numbers a tile stores, from its metadata."""
    return F.when(F.col("repr") == "L", F.col("rank").cast("long") * (F.col("m") + F.col("n"))).otherwise(F.col("m").cast("long") * F.col("n"))


def active_grid(a: DataFrame, b: DataFrame, pr: int, pc: int, rounds: int) -> DataFrame:
    """Grid rows that hold a tile of a round's column panel, and grid columns that hold one of its row panel: expectation over the rounds."""
    r = a.groupBy("bj").agg(F.count_distinct(F.pmod("bi", F.lit(pr))).alias("n")).agg((F.sum("n") / rounds).alias("active_rows"))
    c = b.groupBy("bi").agg(F.count_distinct(F.pmod("bj", F.lit(pc))).alias("n")).agg((F.sum("n") / rounds).alias("active_cols"))
    return r.crossJoin(c)


def comm_volume(a: DataFrame, b: DataFrame, pr: int, pc: int, variant: str = "2d", layers: int = 1, c: DataFrame | None = None) -> DataFrame:
    """k, moved: numbers sent for each round (k = -1: for the reduction of partial results), from norm tables with area.

    2d copies a tile of a to the other grid columns and one of b to the other rows; 2.5d does so within one layer and adds
    the result once a layer; shift sends every tile once a step.
    """
    left = a.groupBy(F.col("bj").alias("k")).agg(F.sum("area").alias("x"))
    right = b.groupBy(F.col("bi").alias("k2")).agg(F.sum("area").alias("y"))
    both = left.join(right, F.col("k") == F.col("k2"), "full_outer")
    x, y = F.coalesce("x", F.lit(0)), F.coalesce("y", F.lit(0))
    out = both.select(F.coalesce("k", "k2").cast("int").alias("k"), (x * (pc - 1) + y * (pr - 1)).cast("long").alias("moved"))
    if variant == "shift":
        out = both.select(F.coalesce("k", "k2").cast("int").alias("k"), ((x + y) * (pr - 1)).cast("long").alias("moved"))
    if layers > 1 and c is not None:
        out = out.unionByName(c.agg(F.lit(-1).alias("k"), (F.sum("area") * (layers - 1)).cast("long").alias("moved")))
    return out


def temp_tiles(a: DataFrame, b: DataFrame, depth: int) -> DataFrame:
    """Temporary numbers of a split update: for each wave of rounds a copy of each tile of the result that two or more of its products meet in."""
    right = b.select(F.col("bi").alias("k"), F.col("bj").alias("j"), "n")
    rows = a.select("bi", F.col("bj").alias("k1"), "m").join(right, F.col("k1") == F.col("k"))
    each = rows.groupBy("bi", "j", F.floor(F.col("k") / depth).alias("wave")).agg(F.count("*").alias("terms"), F.max(F.col("m").cast("long") * F.col("n")).alias("area"))
    return each.groupBy("wave").agg(F.sum(F.when(F.col("terms") > 1, F.col("terms") * F.col("area")).otherwise(0)).cast("long").alias("temporary"))


def panel_shape(rows: Axis, cols: Axis, k: int) -> tuple[int, int]:
    return rows.n * cols.length(k), cols.length(k)
