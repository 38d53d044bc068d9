"""From tables to tiles: entries, orderings, blockings, placement on a process grid."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rankgrid.functions.tiles import SPARSE, Tile, sparse_columns
from rankgrid.schema import BLOCKS, Axis, BlockMatrix, Skeleton, block_batch, each_row, read_entries, read_tile, sparse_row, tile_row


def coo(df: DataFrame, row: str, col: str, val: Column) -> DataFrame:
    """Entries (i, j, v), summed where a pair occurs again; partial sums before the only shuffle.

    Rows with a null index stand nowhere in the matrix and are left out; null values add nothing, and a place with null
    values alone is a null entry. An empty table has no entries.
    """
    return df.where(F.col(row).isNotNull() & F.col(col).isNotNull()).groupBy(F.col(row).cast("long").alias("i"), F.col(col).cast("long").alias("j")).agg(F.sum(val).cast("double").alias("v"))


def validate_coo(m: DataFrame) -> DataFrame:
    """Entries without NaN; rows with one fail the query that reads them."""
    return m.withColumn("v", F.when(F.isnan("v"), F.raise_error(F.lit("NaN entry"))).otherwise(F.col("v")))


def ordering(df: DataFrame, axis: str, key: str, group: list[str], order: list[str]) -> DataFrame:
    """axis, pos, key, b, off: rows ranked within their group, groups placed one after another by a prefix sum of their sizes.

    No window runs over all rows: ranks are per group, and the prefix sum has one row a group.
    """
    ranked = df.select(*group, *order, F.col(key).cast("long").alias("key")).withColumn("off", F.row_number().over(Window.partitionBy(*group).orderBy(*order, "key")) - 1)
    sizes = df.groupBy(*group).agg(F.count("*").alias("size"))
    w = Window.orderBy(*group)
    starts = sizes.select(*[F.col(g).alias(f"g_{g}") for g in group], (F.row_number().over(w) - 1).alias("b"), (F.sum("size").over(w) - F.col("size")).alias("start"))
    joined = ranked.join(starts, [F.col(g).eqNullSafe(F.col(f"g_{g}")) for g in group])
    return joined.select(F.lit(axis).alias("axis"), (F.col("start") + F.col("off")).alias("pos"), "key", F.col("b").cast("int").alias("b"), F.col("off").cast("int").alias("off"))


def uniform_blocking(spark: SparkSession, axis: str, n: int, b: int) -> DataFrame:
    start = F.col("id") * b
    return spark.range((n + b - 1) // b).select(F.lit(axis).alias("axis"), F.col("id").cast("int").alias("b"), start.alias("start"), F.least(F.lit(b), F.lit(n) - start).cast("int").alias("len"), F.lit("").alias("tag"))


def natural_blocking(order: DataFrame) -> DataFrame:
    """One block for each group of an ordering."""
    return order.groupBy("axis", "b").agg(F.min("pos").alias("start"), F.count("*").cast("int").alias("len")).select("axis", "b", "start", "len", F.col("b").cast("string").alias("tag"))


def overdecompose(blocking: DataFrame, max_len: int) -> DataFrame:
    """The blocking with blocks longer than max_len cut into equal parts, numbered anew; the tag names the old block."""
    parts = F.ceil(F.col("len") / F.lit(max_len)).cast("int")
    cut = blocking.withColumn("parts", parts).withColumn("p", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    lo, hi = F.floor(F.col("p") * F.col("len") / F.col("parts")), F.floor((F.col("p") + 1) * F.col("len") / F.col("parts"))
    rows = cut.select("axis", (F.col("start") + lo).alias("start"), (hi - lo).cast("int").alias("len"), F.col("b").cast("string").alias("tag"))
    return rows.select("axis", (F.row_number().over(Window.partitionBy("axis").orderBy("start")) - 1).cast("int").alias("b"), "start", "len", "tag")


def owner(bi: Column, bj: Column, pr: int, pc: int, rblk: int = 1, cblk: int = 1) -> tuple[Column, Column]:
    """Grid row and column of a tile, cyclic or block-cyclic."""
    return F.pmod(F.floor(bi / rblk), F.lit(pr)).cast("int"), F.pmod(F.floor(bj / cblk), F.lit(pc)).cast("int")


def blocks_per_process(blocks: DataFrame, pr: int, pc: int) -> DataFrame:
    gr, gc = owner(F.col("bi"), F.col("bj"), pr, pc)
    return blocks.groupBy(gr.alias("gr"), gc.alias("gc")).agg(F.count("*").alias("blocks"), F.sum(F.col("m").cast("long") * F.col("n")).alias("area"))


def _at_tiles(entries: DataFrame, rows: Axis, cols: Axis) -> DataFrame:
    there = entries.where(F.col("i").isNotNull() & F.col("j").isNotNull() & F.col("v").isNotNull()).select("i", "j", "v")
    return _in_blocks(_in_blocks(there, "i", rows, "bi"), "j", cols, "bj")


def skeleton(entries: DataFrame, rows: Axis, cols: Axis) -> Skeleton:
    """Shapes and norms of the tiles that to_blocks makes, from partial sums: no tile is filled, and no task holds one.

    Each place occurs once in entries, as it does in those of coo.
    """
    m, n = _length(rows, "bi"), _length(cols, "bj")
    norms = _at_tiles(entries, rows, cols).groupBy("bi", "bj").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    return Skeleton(norms.select("bi", "bj", m.alias("m"), n.alias("n"), F.lit("F").alias("repr"), F.least(m, n).alias("rank"), "norm"), rows, cols)


def shapes(entries: DataFrame, rows: Axis, cols: Axis) -> Skeleton:
    """Shapes of the tiles that to_blocks makes, without their norms. A place may occur more than once in entries: tiles
    are told apart within the map tasks, so that neither sums nor entries are shuffled or held.
    """
    there = _at_tiles(entries, rows, cols).select("bi", "bj").distinct()
    m, n = _length(rows, "bi"), _length(cols, "bj")
    return Skeleton(there.select("bi", "bj", m.alias("m"), n.alias("n"), F.lit("F").alias("repr"), F.least(m, n).alias("rank"), F.lit(None).cast("double").alias("norm")), rows, cols)


def _length(axis: Axis, b: str) -> Column:
    starts = F.lit(list(axis.starts))
    return (F.element_at(starts, F.col(b) + 2) - F.element_at(starts, F.col(b) + 1)).cast("int")


def to_blocks(entries: DataFrame, rows: Axis, cols: Axis, sparse: bool = False) -> BlockMatrix:
    """Tiles of entries (i, j, v) by position: one shuffle on the tile, then each tile is filled in one task.

    Entries with a null index or value are left out, those of one place are added up; without entries there are no tiles.
    sparse: tiles store their entries alone, so that a tile takes 16 bytes an entry whatever its area.
    """
    r, c = np.array(rows.starts), np.array(cols.starts)
    placed = _at_tiles(entries, rows, cols)

    def fill(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bi, bj = key[0].as_py(), key[1].as_py()
        if sparse:
            parts = [((b.column("i").to_numpy() - r[bi]).astype(np.int32), (b.column("j").to_numpy() - c[bj]).astype(np.int32), b.column("v").to_numpy()) for b in batches]
            yield block_batch([sparse_row(bi, bj, int(r[bi + 1] - r[bi]), int(c[bj + 1] - c[bj]), *(np.concatenate(x) for x in zip(*parts)))])
            return
        a = np.zeros((r[bi + 1] - r[bi], c[bj + 1] - c[bj]))
        for b in batches:
            np.add.at(a, (b.column("i").to_numpy() - r[bi], b.column("j").to_numpy() - c[bj]), b.column("v").to_numpy())
        yield block_batch([tile_row(bi, bj, Tile(a))])

    return BlockMatrix(placed.groupBy("bi", "bj").applyInArrow(fill, BLOCKS), rows, cols)


def _in_blocks(entries: DataFrame, pos: str, axis: Axis, name: str) -> DataFrame:
    """entries with the block of a position: arithmetic for equal blocks, a binary search in the starts for others, a
    column at a time."""
    if axis.sides:
        b, c = axis.sides
        strip = F.floor(F.col(pos) / b) * axis.strips_each + F.floor(F.pmod(pos, F.lit(b)) / c)
        return entries.withColumn(name, strip.cast("int"))
    width = axis.starts[1] - axis.starts[0] if axis.blocks else 1
    if all(axis.length(b) == width for b in range(axis.blocks - 1)) and axis.blocks and axis.length(axis.blocks - 1) <= width:
        return entries.withColumn(name, F.floor(F.col(pos) / width).cast("int"))
    starts = np.array(axis.starts[:-1])

    def search(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            block = np.searchsorted(starts, b.column(pos).to_numpy(zero_copy_only=False), "right") - 1
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(block.astype(np.int32))], [*b.schema.names, name])

    return entries.mapInArrow(search, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in entries.schema) + f", {name} int")


def locate(entries: DataFrame, pos: str, blocking: DataFrame, how: str = "range", bucket: int = 64) -> DataFrame:
    """entries with the block b of a position: a range join, or an equi join on coarse buckets that the blocks are spread over."""
    b = blocking.select("b", "start", (F.col("start") + F.col("len")).alias("stop"))
    inside = (F.col(pos) >= F.col("start")) & (F.col(pos) < F.col("stop"))
    if how == "range":
        return entries.join(b, inside).drop("start", "stop")
    spread = b.withColumn("k", F.explode(F.sequence(F.floor(F.col("start") / bucket), F.floor((F.col("stop") - 1) / bucket))))
    return entries.withColumn("k2", F.floor(F.col(pos) / bucket)).join(spread, (F.col("k") == F.col("k2")) & inside).drop("k", "k2", "start", "stop")


def to_dcsc(m: BlockMatrix) -> DataFrame:
    """bi, bj and the doubly compressed columns of each tile: columns with entries, their starts, row numbers, values."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in each_row(batches):
            found = _entry_columns(row) if row["repr"] == SPARSE else sparse_columns(read_tile(row).dense())
            lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x, t)) for x, t in zip(found, (pa.int32(), pa.int32(), pa.int32(), pa.float64()))]
            yield pa.RecordBatch.from_arrays([pa.array([row["bi"]], pa.int32()), pa.array([row["bj"]], pa.int32()), *lists], schema=_DCSC)

    return m.blocks.mapInArrow(each, "bi int, bj int, jc array<int>, cp array<int>, ir array<int>, num array<double>")


def _entry_columns(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """What sparse_columns gives, from the entries of a sparse tile; the tile is not filled."""
    i, j, v = read_entries(row)
    i, j, v = i[v != 0], j[v != 0], v[v != 0]
    columns, starts = np.unique(j, return_index=True)
    return columns, np.append(starts, len(j)), i, v


_DCSC = pa.schema([("bi", pa.int32()), ("bj", pa.int32()), ("jc", pa.list_(pa.int32())), ("cp", pa.list_(pa.int32())), ("ir", pa.list_(pa.int32())), ("num", pa.list_(pa.float64()))])


def from_dcsc(tiles: DataFrame, rows: Axis, cols: Axis) -> BlockMatrix:
    """The inverse of to_dcsc, as entries put into tiles again."""
    r, c = F.lit(list(rows.starts)), F.lit(list(cols.starts))
    columns = tiles.select("bi", "bj", "cp", "ir", "num", F.posexplode("jc").alias("p", "col"))
    first, last = F.element_at("cp", F.col("p") + 1), F.element_at("cp", F.col("p") + 2)
    each = columns.select("bi", "bj", "col", F.explode(F.arrays_zip(F.slice("ir", first + 1, last - first).alias("row"), F.slice("num", first + 1, last - first).alias("v"))).alias("e"))
    return to_blocks(each.select((F.element_at(r, F.col("bi") + 1) + F.col("e.row")).cast("long").alias("i"), (F.element_at(c, F.col("bj") + 1) + F.col("col")).cast("long").alias("j"), F.col("e.v").alias("v")), rows, cols)


def fill(m: BlockMatrix, spark: SparkSession) -> DataFrame:
    """Shares of stored blocks, of the area they cover, and of the numbers they store."""
    area, blocks = m.rows.n * m.cols.n, m.rows.blocks * m.cols.blocks
    numbers = F.when(F.col("repr") == "L", F.col("rank").cast("long") * (F.col("m") + F.col("n"))).otherwise(F.col("m").cast("long") * F.col("n"))
    return m.blocks.agg(F.count("*").alias("stored_blocks"), F.sum(F.col("m").cast("long") * F.col("n")).alias("stored_area"), F.sum(numbers).alias("stored_numbers")).select("stored_blocks", "stored_area", "stored_numbers", (F.col("stored_blocks") / blocks).alias("block_fill"), (F.col("stored_area") / area).alias("area_fill"))


def contract(a: DataFrame, b: DataFrame, dims: dict[str, int], spec: str) -> DataFrame:
    """A contraction such as 'ab,bc->ac' or 'xya,ab->xyb' of index tables (one long column a letter, and v).

    Letters that both sides have and the result lacks are summed. Kept letters of each side, and the summed ones, are
    fused into one index each, so that the work is one matrix product.
    """
    left, right = spec.split("->")[0].split(",")
    out = spec.split("->")[1]
    summed = [x for x in left if x in right and x not in out]
    rows, cols = [x for x in left if x not in summed], [x for x in right if x not in summed]

    def fused(letters: list[str]) -> Column:
        index = F.lit(0).cast("long")
        for x in letters:
            index = index * dims[x] + F.col(x)
        return index

    from rankgrid.operators.multiply import mm_entries

    c = mm_entries(a.select(fused(rows).alias("i"), fused(summed).alias("j"), "v"), b.select(fused(summed).alias("i"), fused(cols).alias("j"), "v"))
    parts = {}
    for letters, name in ((rows, "i"), (cols, "j")):
        rest = F.col(name)
        for x in reversed(letters):
            parts[x] = (rest % dims[x]).cast("long")
            rest = F.floor(rest / dims[x])
    return c.select(*[parts[x].alias(x) for x in out], "v")
