"""Products of block matrices on a virtual process grid.

One physical form serves most variants: tiles are copied to the grid cells that need them, one shuffle brings them there,
and a cell streams its tiles round by round of the summed index while it adds into its own tiles of the result. What
varies is how many rounds a cell has open at once, how many jobs issue them and what they wait for, in what form panels
travel, whether partial results are reduced in a second shuffle, which operand stays in place, and how many layers of the
grid share the rounds. The torus-shift and the split products have plans of their own.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankgrid.functions.tiles import Entries, Sum, Tile, entry_products, joined, multiply, sparse_multiply
from rankgrid.operators.screening import screen_product
from rankgrid.plans.costs import optimal_depth
from rankgrid.plans.schedule import release_order
from rankgrid.schema import ARROW_BLOCKS, BLOCKS, COO, Axis, BlockMatrix, batched, each_row, entry_batches, read_sparse, read_tile, tile_row
from rankgrid.session import written

_PARTIAL = pa.schema([("k", pa.int32()), *ARROW_BLOCKS])
PARTIAL = "k int, " + BLOCKS


def mm_entries(a: DataFrame, b: DataFrame) -> DataFrame:
    """The product entry by entry: join on the summed index, partial sums, final sums.

    Entries with a null summed index meet nothing; a null value adds nothing; an empty operand gives no entries.
    """
    right = b.select(F.col("i").alias("k"), F.col("j").alias("j2"), F.col("v").alias("v2"))
    return a.join(right, F.col("j") == F.col("k")).groupBy("i", F.col("j2").alias("j")).agg(F.sum(F.col("v") * F.col("v2")).alias("v"))


@dataclass(frozen=True)
class Grid:
    pr: int
    pc: int
    layers: int = 1


#: Bytes of the result, were it full, that one cell holds at most, and cells for each core where the matrix has so many tiles.
CELL_BYTES, CELLS_PER_CORE = 128 << 20, 2
#: Rounds that a cell has open at most where nothing else bounds them.
OPEN_ROUNDS = 8
#: Bytes of stored entries up to which a cell has more rounds than that open, where there is no order among rounds.
ENTRY_BYTES = 256 << 20


def default_grid(rows: Axis, cols: Axis, cores: int, summed: int = 0) -> Grid:
    """A grid with a few cells for each core, and so many that a cell's part of the result stays small; no larger than the
    result in tiles, and as square as that allows. Only the blockings are looked at.

    summed: the length of the summed index of a product whose cells hold their operands and no sums (see _Cell.results):
    these are to stay small instead, so that far fewer cells, and copies of tiles, do.
    """
    held = 8 * rows.n * cols.n / CELL_BYTES
    if summed:
        # a square grid of c cells gives each of them 1 / sqrt(c) of both operands
        held = min(held, (8 * summed * (rows.n + cols.n) / CELL_BYTES) ** 2)
    need = max(CELLS_PER_CORE * cores, math.ceil(held), 1)
    need = min(need, max(1, rows.blocks * cols.blocks))
    pr = min(max(rows.blocks, 1), max(1, round(math.sqrt(need * max(rows.blocks, 1) / max(cols.blocks, 1)))))
    return Grid(pr, min(max(cols.blocks, 1), math.ceil(need / pr)))


def places_grid(a: BlockMatrix, b: BlockMatrix) -> Grid:
    """The smallest grid whose fullest cell has at most CELL_BYTES of the result, by the places that tiles of a and b can add
    to, and no larger than default_grid, which takes every place to be full: where many stay empty, fewer cells, and copies
    of tiles, do. Only metadata is read."""
    cores = a.blocks.sparkSession.sparkContext.defaultParallelism
    most = default_grid(a.rows, b.cols, cores)
    left = a.blocks.select("bi", F.col("bj").alias("k"), "m")
    right = b.blocks.select(F.col("bi").alias("k2"), "bj", "n")
    areas = written(left.join(right, F.col("k") == F.col("k2")).select("bi", "bj", (F.col("m").cast("long") * F.col("n")).alias("area")).distinct(), "places")
    cells = CELLS_PER_CORE * cores
    while cells < most.pr * most.pc:
        pr = min(a.rows.blocks, max(1, round(math.sqrt(cells * a.rows.blocks / b.cols.blocks))))
        grid = Grid(pr, min(b.cols.blocks, math.ceil(cells / pr)))
        held = areas.groupBy(F.pmod("bi", F.lit(grid.pr)), F.pmod("bj", F.lit(grid.pc))).agg(F.sum("area").alias("s")).agg(F.max("s")).first()[0]
        if 8 * (held or 0) <= CELL_BYTES:
            return grid
        cells *= 2
    return most


def _grid_for(a: BlockMatrix, b: BlockMatrix, grid: Grid | None, summed: int = 0) -> Grid:
    return grid or default_grid(a.rows, b.cols, a.blocks.sparkSession.sparkContext.defaultParallelism, summed)


def round_order(blocks: int, p: int, kind: str = "natural", released: dict[int, float] | None = None) -> list[int]:
    """The order in which rounds are issued: as numbered, all rounds of one owner after another ('by_owner'), or those
    first that free most for their work ('release', by what each round releases for a unit of cost)."""
    if kind == "by_owner":
        return sorted(range(blocks), key=lambda k: (k % p, k))
    if kind == "release":
        return sorted(range(blocks), key=lambda k: (-(released or {}).get(k, 0.0), k))
    return list(range(blocks))


def _released(a: BlockMatrix, b: BlockMatrix) -> dict[int, float]:
    """What each round frees for a unit of its cost, from shapes alone: one number a block of the summed index."""
    shape = ("bi", "bj", "m", "n", (F.col("m").cast("long") * F.col("n")).alias("area"))
    rows = release_order(a.blocks.select(*shape), b.blocks.select(*shape)).select("k", "released", "cost").collect()
    return {r["k"]: r["released"] / r["cost"] for r in rows if r["cost"]}


PAYLOAD = ("m", "n", "repr", "rank", "norm", "x", "w")


def _sides(a: BlockMatrix, b: BlockMatrix, turn: list[int]) -> DataFrame:
    """Tiles of both operands: side, k (of the summed index), turn (the place of round k in the order), o (the other index), then the tile."""
    left = a.blocks.select(F.lit(0).alias("side"), F.col("bj").alias("k"), F.col("bi").alias("o"), *PAYLOAD)
    right = b.blocks.select(F.lit(1).alias("side"), F.col("bi").alias("k"), F.col("bj").alias("o"), *PAYLOAD)
    place = F.element_at(F.lit(turn), F.col("k") + 1) if turn != list(range(len(turn))) else F.col("k")
    return left.unionByName(right).withColumn("turn", place.cast("int"))


def _cells(sides: DataFrame, grid: Grid, stationary: str, kept: DataFrame | None, panel: bool = False) -> DataFrame:
    """Tiles at the cells that need them: cell, turn, side, k, o, then the tile. Of a screened product only tiles of block
    rows and columns that something is kept of travel, and each cell first gets the list of the tiles it is to work out.

    panel: the tiles of a round that go to one grid row or column are put into one record before they are sent.
    """
    pr, pc, layers = grid.pr, grid.pc, grid.layers
    if kept is not None:
        named = kept.select(F.explode(F.array(F.struct(F.lit(0).alias("s"), F.col("bi").alias("t")), F.struct(F.lit(1).alias("s"), F.col("bj").alias("t")))).alias("x")).select("x.s", "x.t").distinct()
        sides = sides.join(named, (F.col("side") == F.col("s")) & (F.col("o") == F.col("t")), "left_semi")
    row, col = F.sequence(F.lit(0), F.lit(pr - 1)), F.sequence(F.lit(0), F.lit(pc - 1))
    every_layer = F.sequence(F.lit(0), F.lit(layers - 1))
    is_left = F.col("side") == 0
    own_row, own_col = F.array(F.pmod("o", F.lit(pr))), F.array(F.pmod("o", F.lit(pc)))
    k_row, k_col = F.array(F.pmod("k", F.lit(pr))), F.array(F.pmod("k", F.lit(pc)))
    rows, cols = {
        "C": (F.when(is_left, own_row).otherwise(row), F.when(is_left, col).otherwise(own_col)),
        "A": (F.when(is_left, own_row).otherwise(row), k_col),
        "B": (k_row, F.when(is_left, col).otherwise(own_col)),
    }[stationary]
    names = [*PAYLOAD]
    if panel:
        group = F.when(is_left, F.pmod("o", F.lit(pr))).otherwise(F.pmod("o", F.lit(pc)))
        sides = sides.groupBy("side", "k", "turn", group.alias("group")).agg(F.sort_array(F.collect_list(F.struct("o", *PAYLOAD))).alias("tiles")).withColumn("o", F.col("tiles")[0]["o"])
        names = ["tiles"]
    cell = lambda layer: ((layer * pr + F.col("gr")) * pc + F.col("gc")).cast("int")
    placed = sides.withColumn("gr", F.explode(rows)).withColumn("gc", F.explode(cols)).withColumn("cell", cell(F.pmod("k", F.lit(layers))))
    placed = placed.select("cell", "turn", "side", "k", "o", *names)
    if kept is None:
        return placed
    at_row, at_col = F.array(F.pmod("bi", F.lit(pr))), F.array(F.pmod("bj", F.lit(pc)))
    asked = kept.withColumn("gr", F.explode(row if stationary == "B" else at_row)).withColumn("gc", F.explode(col if stationary == "A" else at_col)).withColumn("layer", F.explode(every_layer))
    asked = asked.select(cell(F.col("layer")).alias("cell"), F.lit(-1).alias("turn"), F.lit(-1).alias("side"), F.col("bj").alias("k"), F.col("bi").alias("o"))
    return placed.unionByName(asked, allowMissingColumns=True)


@dataclass(frozen=True)
class Update:
    """What a cell does with the tiles of its rounds. open_rounds: rounds it has at hand at once; screened: whether it gets
    the list of its tiles first; any_order: whether it may have all rounds open."""

    alpha: float = 1.0
    eps_lr: float = 0.0
    sparse: bool = False
    screened: bool = False
    term_floor: float = 0.0
    open_rounds: int = 1
    any_order: bool = False


def _pair(x: Tile, y: Tile, u: Update) -> Tile:
    if u.sparse and x.w is None and y.w is None:
        return Tile(sparse_multiply(x.x, y.x))
    return multiply(x, y)


class _Cell:
    """One cell at work: the tiles of its open rounds, and its sums."""

    def __init__(self, u: Update):
        self.u, self.wanted, self.sums, self.last = u, set(), {}, None
        self.left: dict[tuple[int, int], dict[int, tuple[Tile | Entries, float]]] = {}
        self.right: dict[tuple[int, int], dict[int, tuple[Tile | Entries, float]]] = {}
        # bytes of the entries at hand; whether all tiles at hand are entries
        self.held, self.by_entries = 0, True

    def take(self, row: dict) -> None:
        if row["side"] < 0:
            self.wanted.add((row["o"], row["k"]))
            return
        at = row["turn"], row["k"]
        if at != self.last:
            few = self.u.any_order and self.by_entries and self.held <= ENTRY_BYTES
            if self.last is not None and not few and len({*self.left, *self.right, at}) > self.u.open_rounds:
                self.update()
            self.last = at
        side = (self.right if row["side"] else self.left).setdefault(at, {})
        for t in row.get("tiles") or [row]:
            x = read_sparse(t) if self.u.term_floor <= 0 else read_tile(t)
            side[t["o"]] = (x, t["norm"])
            if isinstance(x, Entries):
                self.held += len(t["x"])
            else:
                self.by_entries = False

    def entry_sums(self) -> Iterator[tuple[tuple[int, int], tuple[int, int], Iterator[tuple[np.ndarray, np.ndarray]]]]:
        """Place, shape and products of entries of the open rounds, where all tiles are entries: those of a block row and of a
        block column meet once, over all rounds."""
        start, lefts, rights, heights, widths = 0, {}, {}, {}, {}
        for at in sorted(set(self.left) & set(self.right)):
            for i, (x, _) in sorted(self.left[at].items()):
                lefts.setdefault(i, []).append((start, x.j, x.i, x.v))
                heights[i], length = x.shape
            for j, (y, _) in sorted(self.right[at].items()):
                rights.setdefault(j, []).append((start, y.i, y.j, y.v))
                widths[j] = y.shape[1]
            start += length
        rights = {j: joined(parts) for j, parts in sorted(rights.items())}
        for i, parts in sorted(lefts.items()):
            strip = joined(parts)
            for j, other in rights.items():
                if not self.u.screened or (i, j) in self.wanted:
                    yield (i, j), (heights[i], widths[j]), entry_products(strip, other, widths[j])

    def add_entries(self, total: Sum | None, shape: tuple[int, int], products: Iterator[tuple[np.ndarray, np.ndarray]]) -> Sum | None:
        for places, values in products:
            total = total or Sum(self.u.eps_lr)
            total.add_at(shape, places, self.u.alpha * values)
        return total

    def terms(self) -> dict[tuple[int, int], list[tuple[Tile, Tile]]]:
        """The pairs of tiles of the open rounds by the place that their products add to."""
        u = self.u
        rounds = sorted(set(self.left) & set(self.right))
        places: dict[tuple[int, int], list[tuple[Tile, Tile]]] = {}
        for at in rounds:
            for i, (x, norm_x) in sorted(self.left[at].items()):
                for j, (y, norm_y) in sorted(self.right[at].items()):
                    if (not u.screened or (i, j) in self.wanted) and not norm_x * norm_y <= u.term_floor:
                        x, y = (Tile(t.dense()) if isinstance(t, Entries) else t for t in (x, y))
                        places.setdefault((i, j), []).append((x, y))
        return places

    def add(self, total: Sum, pairs: list[tuple[Tile, Tile]]) -> Sum:
        """total with the products of pairs. Full tiles of several rounds make one product of joined tiles."""
        u = self.u
        full = [(x, y) for x, y in pairs if x.w is None and y.w is None and not u.sparse]
        if len(full) > 1:
            total.take(Tile(np.hstack([x.x for x, _ in full]) @ np.vstack([y.x for _, y in full])).scaled(u.alpha))
            pairs = [(x, y) for x, y in pairs if x.w is not None or y.w is not None]
        for x, y in pairs:
            total.take(_pair(x, y, u).scaled(u.alpha))
        return total

    def update(self) -> None:
        """Adds the products of the open rounds."""
        if self.by_entries:
            for place, shape, products in self.entry_sums():
                total = self.add_entries(self.sums.get(place), shape, products)
                if total is not None:
                    self.sums[place] = total
        else:
            for place, pairs in self.terms().items():
                self.add(self.sums.setdefault(place, Sum(self.u.eps_lr)), pairs)
        self.left, self.right, self.last, self.held, self.by_entries = {}, {}, None, 0, True

    def results(self) -> Iterator[dict]:
        """The tiles of the result. Where all rounds are open still, each is worked out when it is asked for, and no sum is held."""
        if self.sums:
            self.update()
            sums = sorted(self.sums.items())
        elif self.by_entries:
            found = ((place, self.add_entries(None, shape, products)) for place, shape, products in self.entry_sums())
            sums = ((place, s) for place, s in found if s is not None)
        else:
            sums = ((place, self.add(Sum(self.u.eps_lr), pairs)) for place, pairs in sorted(self.terms().items()))
        for (i, j), s in sums:
            t = s.result()
            if t.rank:
                yield tile_row(i, j, t)


def _placed(cells: DataFrame, parts: int) -> DataFrame:
    return cells.repartitionById(parts, F.pmod("cell", F.lit(parts))).sortWithinPartitions("cell", "turn", "side", "o")


def _streamed(placed: DataFrame, u: Update, order: int = 0, then: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]] | None = None, schema: str = PARTIAL) -> DataFrame:
    """Partial results of each cell. Rows come sorted by cell, turn and side; a cell holds the tiles of its open rounds and
    its own tiles of the result. order tells the partial results of one tile apart, by the layer or the job they are of.
    then: what becomes of them in the same task, with its schema."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, cell = None, None

        def close() -> Iterator[pa.RecordBatch]:
            if cell is not None:
                yield from batched(({"k": order + now, **t} for t in cell.results()), _PARTIAL)

        for row in each_row(batches):
            if row["cell"] != now:
                yield from close()
                now, cell = row["cell"], _Cell(u)
            cell.take(row)
        yield from close()

    return placed.mapInArrow((lambda batches: then(work(batches))) if then else work, schema)


def reduce_partials(partials: DataFrame, eps_lr: float = 0.0) -> DataFrame:
    """One tile for each place, partial tiles added in the order of k so that a rerun agrees bit for bit."""

    def sums(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        at, total = None, None
        for r in each_row(batches):
            if (r["bi"], r["bj"]) != at:
                if at is not None and (t := total.result()).rank:
                    yield tile_row(*at, t)
                at, total = (r["bi"], r["bj"]), Sum(eps_lr)
            total.take(read_tile(r))
        if at is not None and (t := total.result()).rank:
            yield tile_row(*at, t)

    placed = partials.repartition(F.col("bi"), F.col("bj")).sortWithinPartitions("bi", "bj", "k")
    return placed.mapInArrow(lambda batches: batched(sums(batches)), BLOCKS)


def _survivors(a: BlockMatrix, b: BlockMatrix, eps_sp: float) -> DataFrame | None:
    """The tiles (bi, bj) of the result that pass screening, from norm tables alone."""
    if eps_sp <= 0:
        return None
    return written(screen_product(a.norms(), b.norms(), a.rows, b.cols, eps_sp).select("bi", "bj"), "survivors")


def mm_panels(
    a: BlockMatrix, b: BlockMatrix, grid: Grid | None = None, depth: int | str | None = None, mode: str | None = None, stationary: str = "C",
    order: str = "natural", prefetch: int = 0, alpha: float = 1.0, eps_lr: float = 0.0, eps_sp: float = 0.0, screen: str = "block",
    sparse: bool = False, row_step: int = 0, bcast: str = "tiles", only: DataFrame | None = None,
) -> BlockMatrix:
    """The panel-broadcast product alpha a b.

    grid: None for default_grid. depth: rounds of the summed index in flight; None for max(2, min(pr, pc)), 'all' for no
    order among rounds at all. mode 'stream', the default from depth 2 on, is one job: every cell has that many rounds
    open, and takes in the next ones when those are done, whatever other cells do. mode 'waves', the default at depth 1,
    issues depth rounds as one job and waits for its end before the next; 'sliding' keeps depth jobs of one round running
    and starts another when one ends. prefetch: panels that are sent while the running job works, with mode 'waves'.

    order: see round_order. bcast 'tiles' sends each tile by itself, 'panel' a round's tiles of a grid row or column as
    one record. row_step: block rows of the result that a cell holds at most, by more rows of cells. only: the tiles
    (bi, bj) of the result to work out. A matrix without tiles gives one without tiles; a tile that is not there is zero.
    """
    if a.cols.starts != b.rows.starts:
        raise ValueError("the blockings of the summed index differ")
    spark, n = a.blocks.sparkSession, a.cols.blocks
    in_task = depth == "all" and mode in (None, "stream") and stationary == "C" and n <= OPEN_ROUNDS
    grid = _grid_for(a, b, grid, a.cols.n if in_task else 0)
    if row_step:
        grid = Grid(max(grid.pr, math.ceil(a.rows.blocks / row_step)), grid.pc, grid.layers)
    kept = only if only is not None else _survivors(a, b, eps_sp if screen != "none" else 0.0)
    any_order = depth == "all" and mode in (None, "stream")
    depth = n if depth == "all" else max(1, min(n, depth or optimal_depth(grid.pr, grid.pc)))
    mode = mode or ("waves" if depth == 1 and n > 1 else "stream")
    u = Update(alpha, eps_lr, sparse, kept is not None, eps_sp if screen == "term" else 0.0, min(depth, OPEN_ROUNDS), any_order)
    parts = grid.pr * grid.pc * grid.layers
    rounds = round_order(n, grid.pc, order, _released(a, b) if order == "release" else None)
    turn = [0] * n
    for place, k in enumerate(rounds):
        turn[k] = place
    sides = _sides(a, b, turn)
    alone = stationary == "C" and grid.layers == 1
    if mode == "stream" or depth >= n:
        placed = _placed(_cells(sides, grid, stationary, kept, bcast == "panel"), parts)
        if not alone:
            return BlockMatrix(reduce_partials(_streamed(placed, u), eps_lr), a.rows, b.cols)
        return BlockMatrix(_streamed(placed, u).drop("k"), a.rows, b.cols, lambda *how: _streamed(placed, u, then=entry_batches(a.rows, b.cols, *how), schema=COO))
    # several jobs: the operands are written once, by job, so that each job reads its own rounds and no others
    step = depth if mode == "waves" else 1
    jobs = math.ceil(n / step)
    by_job = sides.withColumn("job", F.floor(F.col("turn") / step).cast("int"))
    by_job = written(by_job.repartition(F.col("job"), F.pmod("o", F.lit(max(1, parts // jobs)))), "operands", ("job",))

    def place(job: int) -> DataFrame:
        return _placed(_cells(by_job.where(F.col("job") == job).drop("job"), grid, stationary, kept, bcast == "panel"), parts)

    def update(job: int, placed: DataFrame) -> DataFrame:
        return written(_streamed(placed, u, job * parts), "round")

    own = inheritable_thread_target(spark)
    if mode == "waves" and prefetch:
        done = _prefetched(jobs, prefetch, place, update, own)
    else:
        # at width 1 a job waits for the one before it: the barrier of the synchronous method
        with ThreadPoolExecutor(depth if mode == "sliding" else 1) as pool:
            done = list(pool.map(own(lambda job: update(job, place(job))), range(jobs)))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return BlockMatrix(reduce_partials(out, eps_lr), a.rows, b.cols)


def _prefetched(jobs: int, ahead: int, place, update, own) -> list[DataFrame]:
    """One job after another, while the panels of the next ones are brought to their cells beside it. What is brought is
    kept by the executors; a lost part is brought again from the written operands."""
    from pyspark import StorageLevel

    def bring(job: int) -> DataFrame:
        kept = place(job).persist(StorageLevel.MEMORY_AND_DISK)
        kept.count()
        return kept

    done = []
    with ThreadPoolExecutor(ahead) as pool:
        coming = [pool.submit(own(bring), job) for job in range(min(ahead, jobs))]
        for job in range(jobs):
            panels = coming.pop(0).result()
            if job + ahead < jobs:
                coming.append(pool.submit(own(bring), job + ahead))
            done.append(update(job, panels))
            panels.unpersist()
    return done


def mm_split(a: BlockMatrix, b: BlockMatrix, alpha: float = 1.0, eps_lr: float = 0.0, sparse: bool = False, pairs: DataFrame | None = None) -> BlockMatrix:
    """Every product of two tiles is a row of its own, reduced afterwards: the split update, and the 3D product.

    pairs limits the work to some tiles (bi, bj) of the result.
    """
    return BlockMatrix(reduce_partials(_products(a, b, Update(alpha, eps_lr, sparse), pairs, F.col("bk")), eps_lr), a.rows, b.cols)


def _products(a: BlockMatrix, b: BlockMatrix, u: Update, pairs: DataFrame | None, order: F.Column) -> DataFrame:
    x = a.blocks.select("bi", F.col("bj").alias("bk"), *[F.col(c).alias(f"a_{c}") for c in ("m", "n", "repr", "rank", "x", "w")])
    y = b.blocks.select(F.col("bi").alias("bk2"), "bj", *[F.col(c).alias(f"b_{c}") for c in ("m", "n", "repr", "rank", "x", "w")])
    both = x.join(y, F.col("bk") == F.col("bk2"))
    if pairs is not None:
        p = pairs.select(F.col("bi").alias("pi"), F.col("bj").alias("pj"))
        both = both.join(p, (F.col("bi") == F.col("pi")) & (F.col("bj") == F.col("pj")), "left_semi")
    return _multiplied(both, u, order)


def _multiplied(pairs: DataFrame, u: Update, order: F.Column) -> DataFrame:
    """The product of each pair of tiles, as a partial result of its place."""
    both = pairs.withColumn("k", order.cast("int"))

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for r in each_row(batches):
            t = _pair(*(read_tile({c: r[f"{s}_{c}"] for c in ("m", "n", "repr", "rank", "x", "w")}) for s in "ab"), u).scaled(u.alpha)
            if t.rank:
                yield {"k": r["k"], **tile_row(r["bi"], r["bj"], t)}

    return both.mapInArrow(lambda batches: batched(work(batches), _PARTIAL), PARTIAL)


def mm_auto(a: BlockMatrix, b: BlockMatrix, grid: Grid | None = None, hot: int = 8, **options) -> BlockMatrix:
    """Fused updates, but for tiles of the result that more than `hot` products meet in: those are split and reduced.
    Each tile is worked out in one of the two ways only."""
    from rankgrid.operators.screening import contributions

    counts = written(contributions(a.norms(), b.norms()), "contributions")
    many, few = (counts.where(x).select("bi", "bj") for x in (F.col("products") > hot, F.col("products") <= hot))
    fused = mm_panels(a, b, grid, depth="all", only=few, **options)
    return BlockMatrix(fused.blocks.unionByName(mm_split(a, b, options.get("alpha", 1.0), options.get("eps_lr", 0.0), options.get("sparse", False), many).blocks), a.rows, b.cols)


def mm_25d(a: BlockMatrix, b: BlockMatrix, grid: Grid | None = None, layers: int = 2, eps_lr: float = 0.0) -> BlockMatrix:
    """Layers of the grid take the rounds in turn, and their partial results are added."""
    grid = _grid_for(a, b, grid)
    return mm_panels(a, b, Grid(grid.pr, grid.pc, layers), depth="all", eps_lr=eps_lr)


def mm_3d(a: BlockMatrix, b: BlockMatrix, eps_lr: float = 0.0) -> BlockMatrix:
    """A cell for each round and place: the split product, every tile product in a place of its own before the sum."""
    return mm_split(a, b, eps_lr=eps_lr)


def shift_step(a: BlockMatrix, b: BlockMatrix, q: int, step: int) -> DataFrame:
    """Step `step` of the torus shift on q x q cells: the pairs of tiles that meet, after the operands were set off by a
    grid row (column) each and have moved on `step` times. bi, bk, bj, gr, gc, then both tiles."""
    own = lambda c: F.pmod(F.col(c), F.lit(q))
    x = a.blocks.select("bi", F.col("bj").alias("bk"), *[F.col(c).alias(f"a_{c}") for c in PAYLOAD]).withColumns({"gr": own("bi"), "gc": F.pmod(F.col("bk") - F.col("bi") - step, F.lit(q))})
    y = b.blocks.select(F.col("bi").alias("bk2"), "bj", *[F.col(c).alias(f"b_{c}") for c in PAYLOAD]).withColumns({"gr2": F.pmod(F.col("bk2") - F.col("bj") - step, F.lit(q)), "gc2": own("bj")})
    return x.join(y, (F.col("gr") == F.col("gr2")) & (F.col("gc") == F.col("gc2")) & (F.col("bk") == F.col("bk2")))


def mm_shift(a: BlockMatrix, b: BlockMatrix, q: int) -> BlockMatrix:
    """The torus-shift product on a q x q grid. Left tiles start as many columns to the left as their grid row has, right
    tiles as many rows up as their column; each of the q steps multiplies what lies in the same cell, then all left tiles
    go one column on and all right tiles one row. A step is a job that waits for the step before it."""
    steps = [written(_multiplied(shift_step(a, b, q, s), Update(), F.lit(s) * F.lit(1 << 20) + F.col("bk")), "shift") for s in range(q)]
    out = steps[0]
    for s in steps[1:]:
        out = out.unionByName(s)
    return BlockMatrix(reduce_partials(out), a.rows, b.cols)


def mm_sparse(a: BlockMatrix, b: BlockMatrix, grid: Grid | None = None, depth: int | str | None = "all") -> BlockMatrix:
    """The panel product with kernels that go over the entries of doubly compressed tiles."""
    return mm_panels(a, b, grid, depth, sparse=True)


#: Bytes of stored tiles up to which an operand may be broadcast whole.
BROADCAST_BYTES = 64 << 20


def mm_broadcast(a: BlockMatrix, b: BlockMatrix) -> BlockMatrix:
    """The smaller operand b goes whole to every task; past BROADCAST_BYTES the panel product takes over."""
    size = b.blocks.agg(F.sum(F.octet_length("x") + F.coalesce(F.octet_length("w"), F.lit(0)))).first()[0] or 0
    if size > BROADCAST_BYTES:
        return mm_panels(a, b)
    small = BlockMatrix(F.broadcast(b.blocks), b.rows, b.cols)
    return mm_split(a, small)


def axpy(c: BlockMatrix, ab: BlockMatrix, beta: float = 1.0, eps_lr: float = 0.0) -> BlockMatrix:
    """beta c + ab."""
    from rankgrid.operators.lrb import lincomb

    return lincomb([(beta, c), (1.0, ab)], eps_lr=eps_lr)


def multiply_blocks(a: BlockMatrix, b: BlockMatrix, ta: bool = False, tb: bool = False, alpha: float = 1.0, beta: float = 0.0, c: BlockMatrix | None = None, **options) -> BlockMatrix:
    """alpha op(a) op(b) + beta c."""
    out = mm_panels(a.T if ta else a, b.T if tb else b, alpha=alpha, **options)
    return out if c is None or beta == 0 else axpy(c, out, beta, options.get("eps_lr", 0.0))


def run_concurrently(*thunks) -> list[BlockMatrix]:
    """Independent products of one expression as jobs that overlap; each result is written."""
    own = inheritable_thread_target(SparkSession.active())
    with ThreadPoolExecutor(len(thunks)) as pool:
        done = [pool.submit(own(lambda t=t: (m := t(), written(m.blocks, "concurrent")))) for t in thunks]
        return [BlockMatrix(blocks, m.rows, m.cols) for m, blocks in (f.result() for f in done)]
