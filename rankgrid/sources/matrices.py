"""The matrices that the workloads use, from the given tables, as entries or as tiles."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankgrid.functions.tiles import Tile, compress
from rankgrid.operators.blocking import coo, locate, natural_blocking, ordering, overdecompose, to_blocks
from rankgrid.schema import BLOCKS, Axis, BlockMatrix, Made, batched, block_batch, tile_row
from rankgrid.session import table, written

#: Points of a block at most: longer natural blocks are cut, so that a tile and the task that makes it stay small.
MOST_POINTS = 512
#: Bytes of a point of a block, and of all blocks up to which they may be broadcast.
POINT_BYTES, SMALL_BYTES = 48, 32 << 20
#: Ranges of pairs of blocks for each core: tiles of near points take longer than others.
PARTS_PER_CORE = 4
#: Fixed values of the test kernels: length, added diagonal, spacing of regions and of nations within a region.
LENGTH, DIAGONAL, SPACING = 1.0, 1.0, 3.0


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summed quantity by part and supplier."""
    return coo(table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", F.col("l_quantity"))


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summed quantity by customer and part."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    return coo(lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), "o_custkey", "l_partkey", F.col("l_quantity"))


def brand_number(column: str = "p_brand") -> F.Column:
    return F.regexp_extract(column, r"(\d+)", 1).cast("long") - 1


def brand_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summed quantity by brand number and supplier nation: a dense integer matrix of 25 x 25."""
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_quantity")
    parts = table(spark, sf_dir, "part").select("p_partkey", brand_number().alias("brand"))
    supp = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    joined = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    return coo(joined, "brand", "s_nationkey", F.col("l_quantity"))


def embedding_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("i"), F.posexplode("embedding"))
    return e.select("i", F.col("pos").cast("long").alias("j"), F.col("col").cast("double").alias("v"))


def user_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by user and day since 2024-01-01."""
    e = table(spark, sf_dir, "events").select("user_id", F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("day"))
    return coo(e, "user_id", "day", F.lit(1))


def tokens(docs: DataFrame) -> DataFrame:
    """doc_id, lang and each ASCII word of three letters or more, lower-cased."""
    words = F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]{3,}"), F.lit(0))
    return docs.select("doc_id", "lang", F.explode(words).alias("token"))


def dense_integers(spark: SparkSession, n: int, seed: int = 0) -> DataFrame:
    """A full n x n matrix of integers from -8 to 8 by an arithmetic mix of its indices."""
    r = spark.range(n * n).select(F.floor(F.col("id") / n).cast("long").alias("i"), (F.col("id") % n).alias("j"))
    mixed = (F.col("i") * 31 + F.col("j") * 17 + F.col("i") * F.col("j") * 7 + seed) % 17 - 8
    return r.select("i", "j", mixed.cast("double").alias("v"))


def dense_integer_tiles(spark: SparkSession, n: int, b: int, seed: int = 0) -> BlockMatrix:
    """The same matrix made tile by tile inside tasks; nothing is shuffled."""
    axis = Axis.uniform(n, b)
    starts, blocks = axis.starts, axis.blocks

    def make(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in batch.column("id").to_pylist():
                bi, bj = divmod(t, blocks)
                i, j = np.arange(starts[bi], starts[bi + 1])[:, None], np.arange(starts[bj], starts[bj + 1])[None, :]
                yield block_batch([tile_row(bi, bj, Tile(((i * 31 + j * 17 + i * j * 7 + seed) % 17 - 8).astype(np.float64)))])

    return BlockMatrix(spark.range(blocks * blocks).mapInArrow(make, BLOCKS), axis, axis)


def positions(spark: SparkSession, sf_dir: str, of: str = "supplier", where: str | None = None) -> DataFrame:
    """key, region, nation, x, y, z of customers or suppliers: regions and nations set the cluster, the balance the place in it."""
    p = of[0]
    t = table(spark, sf_dir, of)
    t = t.where(where) if where else t
    n = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    joined = t.join(n, F.col(f"{p}_nationkey") == F.col("n_nationkey"))
    key = "c_custkey" if of == "customer" else "s_suppkey"
    return joined.select(F.col(key).alias("key"), F.col("n_regionkey").alias("region"), F.col("n_nationkey").alias("nation"), F.col(f"{p}_acctbal").alias("bal"),
                         (SPACING * F.col("n_regionkey")).cast("double").alias("px"), (SPACING * F.floor(F.col("n_nationkey") / 5)).cast("double").alias("py"), (F.col(f"{p}_acctbal") / 1000).alias("pz"))


def kernel_value(kind: str, d2):
    """exp(-d²/L²) for 'decay', 1/sqrt(1 + d²/L²) for 'longrange', of squared distances (numbers, arrays)."""
    s = d2 / LENGTH**2
    return np.exp(-s) if kind == "decay" else 1 / np.sqrt(1 + s)


def _gathered(points: DataFrame, by: str, most: int) -> tuple[DataFrame, Axis, DataFrame]:
    """The points of each block (b, pts), the axis, and the ordering."""
    groups = ["region", "nation"] if by == "nation" else ["region"]
    inner = ["bal"] if by == "nation" else ["nation", "bal"]
    order = written(ordering(points, "points", "key", groups, inner), "ordering")
    blocking = written(overdecompose(natural_blocking(order), most), "blocking")
    axis = Axis.of(blocking)
    placed = points.join(locate(order.select(F.col("key").alias("okey"), "pos"), "pos", blocking, "bucket", most), F.col("key") == F.col("okey"))
    block = written(placed.groupBy("b").agg(F.array_sort(F.collect_list(F.struct("pos", "px", "py", "pz"))).alias("pts")), "points")
    return block, axis, order


def _pairs(block: DataFrame, n: int, size: int | None = None, parts: int | None = None) -> DataFrame:
    """Every pair of blocks with the columns of both: those of the second one end in 2. size: about the bytes of block,
    which up to SMALL_BYTES goes to every task, so that each core has a range of pairs and none is shuffled. parts: ranges
    of pairs, one a core by default."""
    block = F.broadcast(block) if size is not None and size <= SMALL_BYTES else block
    ids = block.sparkSession.range(0, n * n, 1, parts).select(F.floor(F.col("id") / F.lit(max(n, 1))).cast("int").alias("i1"), (F.col("id") % max(n, 1)).cast("int").alias("i2"))
    second = block.select(*[F.col(c).alias(f"{c}2") for c in block.columns])
    second = F.broadcast(second) if size is not None and size <= SMALL_BYTES else second
    return ids.join(block, F.col("i1") == F.col("b")).join(second, F.col("i2") == F.col("b2"))


def _paired(points: DataFrame, by: str, most: int) -> tuple[DataFrame, Axis, DataFrame]:
    """Every pair of blocks with the points of both (b, pts, b2, pts2), the axis, and the ordering. The work of a pair is
    that of its tile: small points are broadcast, as a shuffle of them would be coalesced into one task for all pairs."""
    block, axis, order = _gathered(points, by, most)
    return _pairs(block, axis.blocks, POINT_BYTES * axis.n, PARTS_PER_CORE * block.sparkSession.sparkContext.defaultParallelism), axis, order


def _places(batch: pa.RecordBatch, column: str, k: int) -> list[np.ndarray]:
    return [batch.column(column)[k].values.field(f).to_numpy(zero_copy_only=False) for f in ("px", "py", "pz")]


def _between(kind: str, x: list[np.ndarray], y: list[np.ndarray]) -> np.ndarray:
    return kernel_value(kind, sum((u[:, None] - v[None, :]) ** 2 for u, v in zip(x, y)))


def _kernel_arrays(batches: Iterable[pa.RecordBatch], kind: str) -> Iterator[tuple[int, int, np.ndarray]]:
    """The tile of each pair, one after the other; points are read as columns and never become Python objects."""
    for batch in batches:
        b, b2 = (batch.column(c).to_pylist() for c in ("b", "b2"))
        for k in range(batch.num_rows):
            a = _between(kind, *(_places(batch, c, k) for c in ("pts", "pts2")))
            yield b[k], b2[k], a + DIAGONAL * np.eye(len(a)) if b[k] == b2[k] else a


def kernel_matrix(points: DataFrame, kind: str, eps_lr: float = 0.0, by: str = "nation", zero_below: float = 0.0, most: int = MOST_POINTS) -> tuple[BlockMatrix, DataFrame]:
    """The kernel matrix of points, and their ordering. Points are gathered per block, numbers of blocks are paired, the
    points join them by equality, and each pair's tile is worked out, and compressed, inside a task; no pair of points is
    ever a row, and no task holds more than two blocks of at most `most` points and a few tiles that are on their way out.

    by: 'nation' or 'region' as natural blocks. zero_below: tiles of a smaller norm are left out. Without points there
    are no tiles; points at one place are points like others; a null coordinate gives a tile of NaN.
    """
    pairs, axis, order = _paired(points, by, most)

    def tiles(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, int, Tile]]:
        for bi, bj, a in _kernel_arrays(batches, kind):
            t = compress(a, eps_lr) if eps_lr > 0 else Tile(a)
            if t.rank and np.linalg.norm(a) > zero_below * a.size:
                yield bi, bj, t

    blocks = pairs.mapInArrow(lambda batches: batched(tile_row(*x) for x in tiles(batches)), BLOCKS)
    return BlockMatrix(blocks, axis, axis, None, Made(pairs, tiles)), order


def tiles_of(entries: DataFrame, n: int, m: int, b: int, c: int | None = None, sparse: bool = False) -> BlockMatrix:
    return to_blocks(entries, Axis.uniform(n, b), Axis.uniform(m, c or b), sparse)
