"""Schemas of the tables that carry a matrix, and the matrix itself: tiles, and the blocking of both axes."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.functions.tiles import FULL, SPARSE, Entries, Tile

COO = "i long, j long, v double"
BLOCKS = "bi int, bj int, m int, n int, repr string, rank int, norm double, x binary, w binary"
BLOCKING = "axis string, b int, start long, len int, tag string"
ORDERING = "axis string, pos long, key long, b int, off int"
ARROW_BLOCKS = pa.schema([("bi", pa.int32()), ("bj", pa.int32()), ("m", pa.int32()), ("n", pa.int32()), ("repr", pa.string()), ("rank", pa.int32()), ("norm", pa.float64()), ("x", pa.binary()), ("w", pa.binary())])


@dataclass(frozen=True)
class Axis:
    """Where the blocks of one axis start, and the length of the axis last. One number a block; the driver holds it."""

    starts: tuple[int, ...]
    #: Of equal blocks that are cut into equal strips: the lengths of both.
    sides: tuple[int, int] | None = None

    @staticmethod
    def uniform(n: int, b: int) -> Axis:
        return Axis((*range(0, n, b), n))

    @staticmethod
    def strips(n: int, b: int, c: int) -> Axis:
        """Equal blocks of length b, each cut into strips of length c; the last strip of a block may be shorter."""
        return Axis((*(s for lo in range(0, n, b) for s in range(lo, min(lo + b, n), c)), n), (b, c))

    @property
    def strips_each(self) -> int:
        """Strips of a whole block."""
        return -(-self.sides[0] // self.sides[1]) if self.sides else 1

    @staticmethod
    def of(blocking: DataFrame) -> Axis:
        rows = blocking.select("start", "len").orderBy("start").collect()
        return Axis((*(r["start"] for r in rows), rows[-1]["start"] + rows[-1]["len"])) if rows else Axis((0,))

    @property
    def n(self) -> int:
        return self.starts[-1]

    @property
    def blocks(self) -> int:
        return len(self.starts) - 1

    def length(self, b: int) -> int:
        return self.starts[b + 1] - self.starts[b]


def read_entries(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, columns and values of a sparse tile, by column and row."""
    count = len(row["x"]) // 16
    at = np.frombuffer(row["x"], np.int32, 2 * count)
    return at[:count], at[count:], np.frombuffer(row["x"], np.float64, count, 8 * count)


def read_tile(row: dict) -> Tile:
    m, n, r = row["m"], row["n"], row["rank"]
    if row["repr"] == SPARSE:
        i, j, v = read_entries(row)
        a = np.zeros((m, n))
        a[i, j] = v
        return Tile(a)
    x = np.frombuffer(row["x"], np.float64)
    return Tile(x.reshape(m, n)) if row["repr"] == FULL else Tile(x.reshape(m, r), np.frombuffer(row["w"], np.float64).reshape(n, r))


#: Tiles that store fewer of their places than one in so many are multiplied by entries; fuller ones as arrays are faster.
SPARSE_ONE_IN = 16


def read_sparse(row: dict) -> Tile | Entries:
    """read_tile, but a tile that stores few entries stays as it is."""
    if row["repr"] != SPARSE or len(row["x"]) // 16 * SPARSE_ONE_IN > row["m"] * row["n"]:
        return read_tile(row)
    return Entries((row["m"], row["n"]), *read_entries(row))


def tile_row(bi: int, bj: int, t: Tile) -> dict:
    m, n = t.shape
    w = None if t.w is None else np.ascontiguousarray(t.w).tobytes()
    return {"bi": bi, "bj": bj, "m": m, "n": n, "repr": t.kind, "rank": t.rank, "norm": t.norm(), "x": np.ascontiguousarray(t.x).tobytes(), "w": w}


def sparse_row(bi: int, bj: int, m: int, n: int, i: np.ndarray, j: np.ndarray, v: np.ndarray) -> dict:
    """A tile that stores its entries alone, ordered by column and row; those of one place are added up."""
    order = np.lexsort((i, j))
    i, j, v = i[order], j[order], v[order]
    first = np.flatnonzero(np.append(True, (i[1:] != i[:-1]) | (j[1:] != j[:-1]))) if len(v) else np.zeros(0, np.int64)
    v = np.add.reduceat(v, first) if len(v) else v
    x = b"".join(c.tobytes() for c in (i[first].astype(np.int32), j[first].astype(np.int32), v.astype(np.float64)))
    return {"bi": bi, "bj": bj, "m": m, "n": n, "repr": SPARSE, "rank": min(m, n), "norm": float(np.sqrt((v * v).sum())), "x": x, "w": None}


def block_batch(rows: list[dict], schema: pa.Schema = ARROW_BLOCKS) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, schema=schema)


#: Bytes of tiles, and rows, after which a batch is sent on.
BATCH_BYTES, BATCH_ROWS = 8 << 20, 10_000


def each_row(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
    """The rows of batches, of which only one at a time is a Python object: a batch may hold many tiles."""
    for b in batches:
        for k in range(b.num_rows):
            yield b.slice(k, 1).to_pylist()[0]


def batched(rows: Iterable[dict], schema: pa.Schema = ARROW_BLOCKS) -> Iterator[pa.RecordBatch]:
    """Tiles in batches of about BATCH_BYTES."""
    held, size = [], 0
    for r in rows:
        held.append(r)
        size += len(r["x"]) + len(r["w"] or b"")
        if size > BATCH_BYTES:
            yield block_batch(held, schema)
            held, size = [], 0
    if held:
        yield block_batch(held, schema)


def map_tiles(df: DataFrame, f, schema: str = BLOCKS, arrow: pa.Schema = ARROW_BLOCKS) -> DataFrame:
    """df with f(row dict) -> rows applied to each row, a batch at a time; absent and zero tiles are f's to leave out."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for row in each_row(batches):
            for r in f(row):
                held.append(r)
                size += sum(len(v) for v in r.values() if isinstance(v, bytes))
            if size > BATCH_BYTES or len(held) >= BATCH_ROWS:
                yield block_batch(held, arrow)
                held, size = [], 0
        if held:
            yield block_batch(held, arrow)

    return df.mapInArrow(each, schema)


def entry_batches(row_axis: Axis, col_axis: Axis, drop_zeros: bool = True, above: float = 0.0) -> Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """What takes batches of tiles apart into batches of entries (i, j, v), one a tile; see BlockMatrix.to_coo."""
    rows, cols = np.array(row_axis.starts), np.array(col_axis.starts)

    def entries(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in each_row(batches):
            if row["repr"] == SPARSE and drop_zeros:
                i, j, v = (x.astype(t) for x, t in zip(read_entries(row), (np.int64, np.int64, np.float64)))
                there = ~(np.abs(v) <= above)
                yield pa.RecordBatch.from_arrays([pa.array(i[there] + rows[row["bi"]]), pa.array(j[there] + cols[row["bj"]]), pa.array(v[there])], ["i", "j", "v"])
                continue
            a = read_tile(row).dense()
            i, j = np.nonzero(~(np.abs(a) <= above)) if drop_zeros else (x.ravel() for x in np.indices(a.shape))
            yield pa.RecordBatch.from_arrays([pa.array(i + rows[row["bi"]]), pa.array(j + cols[row["bj"]]), pa.array(a[i, j] + 0.0)], ["i", "j", "v"])

    return entries


@dataclass(frozen=True)
class Made:
    """Tiles (bi, bj, tile) that tasks make from rows far smaller than a tile. What follows on a tile can be done in the task
    that makes it, so that no payload is written or shuffled."""

    rows: DataFrame
    tiles: Callable[[Iterable[pa.RecordBatch]], Iterator[tuple[int, int, Tile]]]


@dataclass
class BlockMatrix:
    """A matrix of tiles. A tile that is not in blocks is zero."""

    blocks: DataFrame
    rows: Axis
    cols: Axis
    #: What to_coo gives of its two arguments, where the tasks that make the tiles can take them apart: no tile goes from one to another.
    entries: Callable[[bool, float], DataFrame] | None = None
    #: How tasks make the tiles, where they do so from small rows.
    made: Made | None = None
    #: The matrix that this one is compressed from, and the threshold.
    of: tuple[BlockMatrix, float] | None = None

    @property
    def T(self) -> BlockMatrix:
        """Index columns swapped; full tiles are transposed in the kernel, low-rank ones by swapping factors."""
        b = self.blocks
        low = F.col("repr") == "L"
        swapped = b.select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), F.col("n").alias("m"), F.col("m").alias("n"), "repr", "rank", "norm", F.when(low, F.col("w")).otherwise(F.col("x")).alias("x"), F.when(low, F.col("x")).alias("w"))

        def turn(row: dict) -> list[dict]:
            if row["repr"] == FULL:
                row["x"] = np.ascontiguousarray(np.frombuffer(row["x"], np.float64).reshape(row["n"], row["m"]).T).tobytes()
            elif row["repr"] == SPARSE:
                i, j, v = read_entries(row)
                row = sparse_row(row["bi"], row["bj"], row["m"], row["n"], j, i, v)
            return [row]

        return BlockMatrix(map_tiles(swapped, turn), self.cols, self.rows)

    def norms(self) -> DataFrame:
        """bi, bj, area, norm, rank: what screening and cost measures read; payloads are not."""
        return self.blocks.select("bi", "bj", (F.col("m").cast("long") * F.col("n")).alias("area"), "norm", "rank", "repr")

    def to_coo(self, drop_zeros: bool = True, above: float = 0.0) -> DataFrame:
        """i, j, v. above: places of this or a smaller absolute value are left out with the zeros."""
        if self.entries:
            return self.entries(drop_zeros, above)
        return self.blocks.mapInArrow(entry_batches(self.rows, self.cols, drop_zeros, above), COO)


@dataclass
class Skeleton:
    """What is known of a matrix of tiles without their payloads: bi, bj, m, n, repr, rank, norm. Measures and schedules read no more."""

    blocks: DataFrame
    rows: Axis
    cols: Axis

    @property
    def T(self) -> Skeleton:
        swapped = self.blocks.select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), F.col("n").alias("m"), F.col("m").alias("n"), "repr", "rank", "norm")
        return Skeleton(swapped, self.cols, self.rows)

    norms = BlockMatrix.norms
