"""What keeps a few keys that hold a large share of all rows from landing in one task, and filters of a checked size."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Keys that hold more than one in HEAVY of all rows are heavy: fewer than HEAVY of them whatever the input, so they may be broadcast.
HEAVY = 10_000
#: Copies of what rows of a heavy key are joined with, where it is too wide to broadcast.
COPIES = 32
#: Least and most bits of a broadcast filter: 8 KB and 32 MB.
FEWEST_BITS, MOST_BITS = 1 << 16, 1 << 28


def left_join(left: DataFrame, right: DataFrame, on: dict[str, str], values: list[str], weight: str, total: int, spread: Column) -> DataFrame:
    """left with values of the row of right that has its keys, null without one.

    right has one row a key; its column weight is the number of left rows of the key, and total at least the number of
    all. Rows of heavy keys find their values in a broadcast table and go through the join with the others under spread, a
    number that differs from row to row and has no partner there. The first key is a long.
    """
    first, *others = on.items()
    heavy_key = F.col(weight) * F.lit(HEAVY) > F.lit(total)
    heavy = right.where(heavy_key).select(*[F.col(r).alias(f"__h{k}") for k, r in enumerate(on.values())], *[F.col(v).alias(f"__hv_{v}") for v in values])
    light = right.where(~heavy_key).select(*[F.col(r).alias(f"__l{k}") for k, r in enumerate(on.values())], *[F.col(v).alias(f"__lv_{v}") for v in values])
    columns = left.columns
    same_heavy, same_light = F.lit(True), F.col("__key") == F.col("__l0")
    for k, c in enumerate(on):
        same_heavy = same_heavy & (F.col(c) == F.col(f"__h{k}"))
        if k:
            same_light = same_light & (F.col(c) == F.col(f"__l{k}"))
    found = F.col("__h0").isNotNull()
    x = left.join(F.broadcast(heavy), same_heavy, "left").withColumn("__key", F.when(found, spread).otherwise(F.col(first[0])))
    x = x.join(light, same_light & ~found, "left")
    return x.select(*columns, *[F.when(found, F.col(f"__hv_{v}")).otherwise(F.col(f"__lv_{v}")).alias(v) for v in values])


def heavy_keys(counts: DataFrame, key: str, weight: str, total: int) -> DataFrame:
    """The heavy keys as a broadcast table with the column heavy."""
    return F.broadcast(counts.where(F.col(weight) * F.lit(HEAVY) > F.lit(total)).select(F.col(key).alias("heavy")))


def dealt(rows: DataFrame, key: str, heavy: DataFrame, by: Column, name: str) -> DataFrame:
    """rows with a number called name: which copy a row of a heavy key is joined with, 0 for others."""
    columns = rows.columns
    x = rows.join(heavy, F.col(key) == F.col("heavy"), "left")
    return x.select(*columns, F.when(F.col("heavy").isNotNull(), F.pmod(F.xxhash64(by), F.lit(COPIES))).otherwise(F.lit(0)).cast("int").alias(name))


def copied(rows: DataFrame, key: str, heavy: DataFrame, name: str) -> DataFrame:
    """rows once, those of heavy keys COPIES times, numbered by name."""
    columns = rows.columns
    x = rows.join(heavy, F.col(key) == F.col("heavy"), "left")
    return x.select(*columns, F.explode(F.when(F.col("heavy").isNotNull(), F.sequence(F.lit(0), F.lit(COPIES - 1))).otherwise(F.array(F.lit(0)))).alias(name))


def filter_bits(entries: int) -> int:
    """Bits of a filter for so many entries: eight or more each, up to MOST_BITS; a fuller filter lets more pass, and joins decide."""
    return min(MOST_BITS, max(FEWEST_BITS, 1 << (8 * max(entries, 1) - 1).bit_length()))


def bitmap(rows: DataFrame, place: Column, bits: int) -> np.ndarray:
    """A bitmap of so many bits in which all places (0 to bits - 1) are set; bytes whose lowest bit is the first."""
    found = rows.select((place + 1).alias("p")).groupBy(F.bitmap_bucket_number("p").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bits")).toLocalIterator()
    out = np.zeros(bits // 8, np.uint8)
    for r in found:
        part = np.frombuffer(bytes(r["bits"]), np.uint8)
        out[(r["k"] - 1) * 4096 : (r["k"] - 1) * 4096 + len(part)] |= part[: len(out) - (r["k"] - 1) * 4096]
    return out


def is_set(bits: np.ndarray, places: np.ndarray) -> np.ndarray:
    return ((bits[places >> 3] >> (places & 7).astype(np.uint8)) & 1).astype(bool)
