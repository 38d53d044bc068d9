"""The SQL surface: functions over tiles and the product as text."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from rankgrid.functions.tiles import pivoted_qr
from rankgrid.schema import read_tile
from rankgrid.sources.matrices import kernel_value


@F.udtf(returnType="i int, j int, v double")
class ExplodeTile:
    """The entries of a tile that are not zero, by place within the tile."""

    def eval(self, m: int, n: int, kind: str, rank: int, x: bytes, w: bytes):
        a = read_tile({"m": m, "n": n, "repr": kind, "rank": rank, "x": x, "w": w}).dense()
        for i, j in zip(*np.nonzero(a), strict=True):
            yield int(i), int(j), float(a[i, j])


@F.udtf(returnType="i int, j int, v double")
class KernelBlock:
    """The values of a kernel ('decay' or 'longrange') between two lists of points, by place within the block."""

    def eval(self, kind: str, points, others):
        for i, p in enumerate(points):
            for j, q in enumerate(others):
                yield i, j, float(kernel_value(kind, sum((a - b) ** 2 for a, b in zip(p, q, strict=True))))


@F.udf("int")
def lr_rank(m: int, n: int, values: list, eps: float) -> int:
    """Least rank within eps (Frobenius) of an m x n block, given row by row."""
    return pivoted_qr(np.array(values, np.float64).reshape(m, n), eps)[0].shape[1]


def register(spark: SparkSession) -> None:
    """explode_tile(m, n, repr, rank, x, w) and kernel_block(kind, points, points) as table functions; lr_rank(m, n, values,
    eps), default_depth(pr, pc) and keeps_low(rank, m, n) as SQL functions."""
    spark.udtf.register("explode_tile", ExplodeTile)
    spark.udtf.register("kernel_block", KernelBlock)
    spark.udf.register("lr_rank", lr_rank)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION default_depth(pr INT, pc INT) RETURNS INT RETURN greatest(2, least(pr, pc))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION keeps_low(r INT, m INT, n INT) RETURNS BOOLEAN RETURN 2 * r <= least(m, n)")


def product_sql(a: str, b: str) -> str:
    """The entry-wise product of two views (i, j, v)."""
    return f"SELECT a.i, b.j, SUM(a.v * b.v) AS v FROM {a} a JOIN {b} b ON a.j = b.i GROUP BY a.i, b.j"
