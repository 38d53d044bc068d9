"""Small models fitted on the driver: bounded samples of labelled rows and logistic regression."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo modulus."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(modulus))


def labelled_sample(labels: DataFrame, label: str, modulus: int, held_out: int, bound: int, id_col: str = "doc_id") -> DataFrame:
    """sample_id, label of at most bound training rows, those of the smallest hashes of their ids; a repeated id counts once.

    The result is small by that bound, so it may be broadcast. Null ids and labels other than 0 and 1 are left out.
    """
    rows = labels.select(F.col(id_col).cast("long").alias("sample_id"), F.col(label).cast("int").alias("label")).where("sample_id IS NOT NULL AND label IN (0, 1)")
    rows = rows.where(fold(F.col("sample_id"), modulus) != held_out).groupBy("sample_id").agg(F.max("label").alias("label"))
    return rows.orderBy(F.xxhash64("sample_id"), "sample_id").limit(bound)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> np.ndarray:
    """Weights with a last one for the intercept, by Newton's method; without both labels the intercept alone."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    if not len(y) or y.min() == y.max():
        w[-1] = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
        return w
    penalty = np.full(len(w), ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty), x.T @ (y - p) - penalty * w)
        w = w + step
        if np.abs(step).max() < 1e-6:
            break
    return w


def probability(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w[:-1] + w[-1], -30, 30)))
