"""Which tiles are worth working out, from norms alone. No payload column is read here."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.schema import Axis


def _pairs(a: DataFrame, b: DataFrame) -> DataFrame:
    right = b.select(F.col("bi").alias("k"), F.col("bj").alias("j"), F.col("norm").alias("norm_b"))
    return a.select("bi", F.col("bj").alias("k1"), "norm").join(right, F.col("k1") == F.col("k")).select("bi", F.col("j").alias("bj"), "k", (F.col("norm") * F.col("norm_b")).alias("bound"))


def product_estimates(a: DataFrame, b: DataFrame) -> DataFrame:
    """bi, bj, est, terms: the sum over k of the products of norms bounds the norm of each tile of the product."""
    return _pairs(a, b).groupBy("bi", "bj").agg(F.sum("bound").alias("est"), F.count("*").alias("terms"))


def contributions(a: DataFrame, b: DataFrame) -> DataFrame:
    return _pairs(a, b).groupBy("bi", "bj").agg(F.count("*").alias("products"))


def _areas(estimates: DataFrame, rows: Axis, cols: Axis) -> DataFrame:
    def length(axis: Axis, b: str) -> F.Column:
        starts = F.lit(list(axis.starts))
        return F.element_at(starts, F.col(b) + 2) - F.element_at(starts, F.col(b) + 1)

    return estimates.withColumn("area", (length(rows, "bi") * length(cols, "bj")).cast("long"))


def screen_product(a: DataFrame, b: DataFrame, rows: Axis, cols: Axis, eps_sp: float) -> DataFrame:
    """bi, bj, est, area of the tiles of a product whose estimate is above eps_sp times their area; the rest is left out."""
    return _areas(product_estimates(a, b), rows, cols).where(F.col("est") > eps_sp * F.col("area")).select("bi", "bj", "est", "area")


def screen_sum(a: DataFrame, b: DataFrame, eps_sp: float) -> DataFrame:
    """bi, bj, est, area of the tiles of a sum that pass, by the triangle inequality."""
    right = b.select(F.col("bi").alias("i2"), F.col("bj").alias("j2"), F.col("norm").alias("norm2"), F.col("area").alias("area2"))
    both = a.join(right, (F.col("bi") == F.col("i2")) & (F.col("bj") == F.col("j2")), "full_outer")
    rows = both.select(F.coalesce("bi", "i2").alias("bi"), F.coalesce("bj", "j2").alias("bj"), (F.coalesce("norm", F.lit(0.0)) + F.coalesce("norm2", F.lit(0.0))).alias("est"), F.coalesce("area", "area2").alias("area"))
    return rows.where(F.col("est") > eps_sp * F.col("area"))


def screen_terms(a: DataFrame, b: DataFrame, floor: float) -> DataFrame:
    """bi, bj, terms: products of single tiles whose bound is above floor, counted for each tile of the result."""
    return _pairs(a, b).where(F.col("bound") > floor).groupBy("bi", "bj").agg(F.count("*").alias("terms"))


def check_bounds(estimates: DataFrame, true: DataFrame) -> DataFrame:
    """Tiles compared, and those whose true norm exceeds the estimate by more than rounding."""
    t = true.select(F.col("bi").alias("i2"), F.col("bj").alias("j2"), F.col("norm").alias("true_norm"))
    both = t.join(estimates, (F.col("bi") == F.col("i2")) & (F.col("bj") == F.col("j2")), "left")
    return both.agg(F.count("*").alias("tiles"), F.count_if(F.col("true_norm") > F.coalesce("est", F.lit(0.0)) * (1 + 1e-12)).alias("violations"))


def screen_savings(a: DataFrame, b: DataFrame, rows: Axis, cols: Axis, eps_sp: float) -> DataFrame:
    """Tiles and tile products of the unscreened product, and how many of them screening leaves out."""
    e = _areas(product_estimates(a, b), rows, cols)
    gone = F.col("est") <= eps_sp * F.col("area")
    return e.agg(F.count("*").alias("tiles"), F.count_if(gone).alias("tiles_skipped"), F.sum("terms").alias("products"), F.sum(F.when(gone, F.col("terms")).otherwise(0)).alias("products_skipped"))
