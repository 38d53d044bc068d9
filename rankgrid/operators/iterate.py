"""The inverse square root by a third-order coupled iteration, four products a round."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankgrid.operators.lrb import frobenius, identity, lincomb, scale
from rankgrid.operators.multiply import Grid, mm_panels
from rankgrid.schema import Axis, BlockMatrix, map_tiles, read_tile
from rankgrid.session import forget, written


def row_sums(m: BlockMatrix) -> DataFrame:
    """i, s: the absolute row sums, worked out tile by tile; one number a tile and row is shuffled, no entry."""
    starts = m.rows.starts

    def one(row: dict) -> list[dict]:
        sums = np.abs(read_tile(row).dense()).sum(axis=1)
        return [{"i": starts[row["bi"]] + k, "s": float(v)} for k, v in enumerate(sums)]

    return map_tiles(m.blocks, one, "i long, s double", pa.schema([("i", pa.int64()), ("s", pa.float64())])).groupBy("i").agg(F.sum("s").alias("s"))


def choose_alpha(m: BlockMatrix, how: str = "inf", steps: int = 20) -> float:
    """A factor with ‖alpha m − I‖₂ ≤ 1 for a positive definite m.

    'inf': one over the largest absolute row sum, which bounds the largest eigenvalue. 'power': one over the estimate of
    a power iteration, raised by its residual; any estimate above half of the largest eigenvalue keeps the bound. 'two_sided': two over the sum of the largest and
    the smallest eigenvalue, which makes the norm smallest; the smallest is found by a second power iteration, on what
    the largest leaves.
    """
    if how == "inf":
        return 1.0 / row_sums(m).agg(F.max("s")).first()[0]
    high = power_norm(m, steps)
    if how == "power":
        return 1.0 / high
    # the spectrum of high - m lies between 0 and high - low: its upper estimate is a lower one of low
    low = high - power_norm(m, steps, shift=high)
    return 2.0 / (high + max(low, 0.0))


_PIECE = pa.schema([("b", pa.int32()), ("piece", pa.binary())])


def vector(spark: SparkSession, axis: Axis) -> DataFrame:
    """b, piece: a first vector of unequal entries, one row a block."""
    starts, n = axis.starts, max(axis.n, 1)

    def one(row: dict) -> list[dict]:
        i = np.arange(starts[row["id"]], starts[row["id"] + 1])
        return [{"b": row["id"], "piece": ((1 + i % 7 / 10) / math.sqrt(n)).tobytes()}]

    return map_tiles(spark.range(axis.blocks), one, "b int, piece binary", _PIECE)


def tile_matvec(m: BlockMatrix, x: DataFrame, shift: float = 0.0) -> DataFrame:
    """b, piece of m x (of shift x - m x, if shift is not 0); a low-rank tile multiplies by its factors one after the other."""
    pieces = m.blocks.join(x.select(F.col("b").alias("xb"), F.col("piece").alias("xp")), F.col("bj") == F.col("xb"))

    def one(row: dict) -> list[dict]:
        t, v = read_tile(row), np.frombuffer(row["xp"], np.float64)
        y = t.x @ v if t.w is None else t.x @ (t.w.T @ v)
        return [{"b": row["bi"], "piece": (-y if shift else y).tobytes()}]

    parts = map_tiles(pieces, one, "b int, piece binary", _PIECE)
    if shift:
        parts = parts.unionByName(map_tiles(x, lambda r: [{"b": r["b"], "piece": (shift * np.frombuffer(r["piece"], np.float64)).tobytes()}], "b int, piece binary", _PIECE))

    def total(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        y = sum(np.frombuffer(v, np.float64) for v in sorted(v for b in batches for v in b.column("piece").to_pylist()))
        yield pa.RecordBatch.from_pylist([{"b": key[0].as_py(), "piece": y.tobytes()}], schema=_PIECE)

    return parts.groupBy("b").applyInArrow(total, "b int, piece binary")


def power_norm(m: BlockMatrix, steps: int = 20, shift: float = 0.0) -> float:
    """An upper estimate of the largest eigenvalue of a symmetric matrix of tiles (of shift I - m): Rayleigh quotient plus residual norm.

    A vector has one row a block; it is written after each step.
    """
    x = written(vector(m.blocks.sparkSession, m.rows), "vector")
    dots = pa.schema([("xy", pa.float64()), ("xx", pa.float64()), ("yy", pa.float64())])

    def products(row: dict) -> list[dict]:
        u, v = (np.frombuffer(row[c], np.float64) for c in ("piece", "yp"))
        return [{"xy": float(u @ v), "xx": float(u @ u), "yy": float(v @ v)}]

    bound = 0.0
    for _ in range(steps):
        y = written(tile_matvec(m, x, shift), "vector")
        both = y.select(F.col("b").alias("yb"), F.col("piece").alias("yp")).join(x, F.col("b") == F.col("yb"))
        r = map_tiles(both, products, "xy double, xx double, yy double", dots).agg(*[F.sum(c).alias(c) for c in ("xy", "xx", "yy")]).first()
        value = r["xy"] / r["xx"]
        bound = value + math.sqrt(max(r["yy"] / r["xx"] - value * value, 0.0))
        if not r["yy"]:
            break
        unit = 1 / math.sqrt(r["yy"])
        x = map_tiles(y, lambda row, c=unit: [{"b": row["b"], "piece": (c * np.frombuffer(row["piece"], np.float64)).tobytes()}], "b int, piece binary", _PIECE)
    return bound


@dataclass
class Options:
    grid: Grid | None = None
    depth: int | str | None = "all"
    eps_lr: float = 0.0
    eps_sp: float = 0.0
    mode: str | None = None
    #: Whether every round's tables and shuffle files stay; else those that no later round reads are deleted as it goes on.
    keep: bool = True


@dataclass
class Roots:
    """z * sqrt(alpha) is the inverse root, y * sqrt(alpha) the root; x and t are the last round's."""

    z: BlockMatrix
    y: BlockMatrix
    x: BlockMatrix
    t: BlockMatrix
    alpha: float
    rounds: int

    def inverse(self) -> BlockMatrix:
        return scale(self.z, math.sqrt(self.alpha))

    def root(self) -> BlockMatrix:
        return scale(self.y, math.sqrt(self.alpha))


def _kept(m: BlockMatrix, name: str, shuffles_go: bool = False) -> BlockMatrix:
    return BlockMatrix(written(m.blocks, name, shuffles_go=shuffles_go), m.rows, m.cols)


def inv_sqrt(m: BlockMatrix, iters: int = 10, alpha: float | str = "inf", options: Options | None = None, tol: float = 0.0, each: Callable[[int, Roots], None] | None = None) -> Roots:
    """Iterates for at most iters rounds, or until ‖X − I‖_F ≤ tol. Every matrix of a round is written to the shared
    folder, which cuts the lineage and survives lost executors; the two last products of a round are one job. Without
    options.keep the roots that each gets are there until the next round's are."""
    o = options or Options()
    spark = m.blocks.sparkSession
    a = choose_alpha(m, alpha) if isinstance(alpha, str) else alpha

    def mm(p: BlockMatrix, q: BlockMatrix, c: float = 1.0) -> BlockMatrix:
        return mm_panels(p, q, o.grid, o.depth, o.mode, alpha=c, eps_lr=o.eps_lr, eps_sp=o.eps_sp)

    z, y = identity(spark, m.rows), m
    roots = both = None
    for k in range(iters):
        if roots and not o.keep:
            forget(roots.x.blocks)
            forget(roots.t.blocks)
        # with z the identity the first product is a scaling
        x = _kept(scale(y, a) if k == 0 else mm(y, z, a), "x", not o.keep)
        t = _kept(lincomb([(3 / 8, mm(x, x)), (-10 / 8, x)], 15 / 8, o.eps_lr), "t", not o.keep)
        if k == 0:
            new = t.blocks.withColumn("product", F.lit(0)).unionByName(mm(t, y).blocks.withColumn("product", F.lit(1)))
        else:
            new = mm(z, t).blocks.withColumn("product", F.lit(0)).unionByName(mm(t, y).blocks.withColumn("product", F.lit(1)))
        old, both = both, written(new, "zy", shuffles_go=not o.keep)
        if old is not None and not o.keep:
            forget(old)
        z, y = (BlockMatrix(both.where(F.col("product") == p).drop("product"), m.rows, m.cols) for p in (0, 1))
        roots = Roots(z, y, x, t, a, k + 1)
        if each:
            each(k + 1, roots)
        if tol and distance_from_identity(x) <= tol:
            break
    return roots


def distance_from_identity(x: BlockMatrix) -> float:
    d = lincomb([(1.0, x)], -1.0)
    return d.blocks.agg(F.sqrt(F.sum(F.col("norm") * F.col("norm")))).first()[0] or 0.0


def residual(r: BlockMatrix, m: BlockMatrix, grid: Grid | None = None, keep: bool = True) -> float:
    """‖R M R − I‖_F, in full precision. Without keep, tables and shuffle files of the two products go when they are read."""
    rm = _kept(mm_panels(r, m, grid, "all"), "residual", not keep)
    if keep:
        return distance_from_identity(mm_panels(rm, r, grid, "all"))
    # only the norms are kept
    norms = _kept(BlockMatrix(lincomb([(1.0, mm_panels(rm, r, grid, "all"))], -1.0).blocks.select("norm"), m.rows, m.cols), "distance", True)
    forget(rm.blocks)
    return frobenius(norms).first()[0] or 0.0
