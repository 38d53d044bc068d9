"""The methods compared with, on the same tiles and grid."""

from __future__ import annotations

from pyspark.sql import DataFrame

from rankgrid.operators.blocking import to_blocks
from rankgrid.operators.lrb import with_repr
from rankgrid.operators.multiply import Grid, mm_25d, mm_panels
from rankgrid.schema import Axis, BlockMatrix


def dense2d(a: DataFrame, b: DataFrame, m: int, k: int, n: int, block: int, grid: Grid | None = None) -> BlockMatrix:
    """Bulk-synchronous product of entries put into equal full tiles dealt cyclically: one round at a time, no structure used."""
    x, y = to_blocks(a, Axis.uniform(m, block), Axis.uniform(k, block)), to_blocks(b, Axis.uniform(k, block), Axis.uniform(n, block))
    return mm_panels(x, y, grid, depth=1)


def dense25d(a: DataFrame, b: DataFrame, m: int, k: int, n: int, block: int, grid: Grid | None = None, layers: int = 2) -> BlockMatrix:
    """Equal full tiles, layers of the grid that share the rounds."""
    x, y = to_blocks(a, Axis.uniform(m, block), Axis.uniform(k, block)), to_blocks(b, Axis.uniform(k, block), Axis.uniform(n, block))
    return mm_25d(x, y, grid, layers)


def single_issue(a: BlockMatrix, b: BlockMatrix, grid: Grid | None = None, **options) -> BlockMatrix:
    return mm_panels(a, b, grid, depth=1, **options)


def full_rank(m: BlockMatrix) -> BlockMatrix:
    return with_repr(m, "F")
