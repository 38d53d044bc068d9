"""The choice of a plan for a product: variant, grid, depth, placement, order of a chain."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rankgrid.operators.multiply import BROADCAST_BYTES, Grid, mm_25d, mm_broadcast, mm_panels, mm_split
from rankgrid.plans.costs import depth_for_memory, mem_dense, optimal_depth, stored_numbers
from rankgrid.schema import BlockMatrix


@dataclass
class Choice:
    variant: str
    grid: Grid
    depth: int
    moved: int
    memory: float


def choose_variant(size_a: int, size_b: int, size_c: int, shape: tuple[int, int, int], block: int, tasks: int, task_numbers: float) -> Choice:
    """The grid (rows x columns x layers with as many cells as tasks) that moves the fewest stored numbers and fits in a
    task: pc copies of a, pr copies of b, and for layers a copy of the result each."""
    m, n, k = shape
    if size_b * 8 <= BROADCAST_BYTES:
        return Choice("broadcast", Grid(tasks, 1), 1, size_b * tasks, mem_dense(m, n, k, block, tasks, 1, 1))
    best = None
    for layers in (x for x in range(1, tasks + 1) if tasks % x == 0):
        for pr in (x for x in range(1, tasks // layers + 1) if (tasks // layers) % x == 0):
            pc = tasks // layers // pr
            moved = pc * size_a + pr * size_b + (layers * size_c if layers > 1 else 0)
            depth = optimal_depth(pr, pc)
            memory = mem_dense(m, n, k, block, pr, pc, depth)
            if memory > task_numbers:
                depth = depth_for_memory(m, n, k, block, pr, pc, task_numbers)
                memory = mem_dense(m, n, k, block, pr, pc, depth)
            fits = memory <= task_numbers
            key = (not fits, moved, layers)
            if best is None or key < best[0]:
                best = (key, Choice("2d" if layers == 1 else "25d", Grid(pr, pc, layers), depth, moved, memory))
    if best[0][0]:
        return Choice("split", Grid(tasks, 1), 1, size_a + size_b + size_c, float(3 * block * block))
    return best[1]


def plan_product(a: BlockMatrix, b: BlockMatrix, tasks: int, task_numbers: float = 2e8) -> Choice:
    """choose_variant on the stored sizes of two matrices; reads metadata columns only."""
    sizes = [m.blocks.agg(F.sum(stored_numbers())).first()[0] or 0 for m in (a, b)]
    block = max((a.cols.length(k) for k in range(a.cols.blocks)), default=1)
    return choose_variant(*sizes, a.rows.n * b.cols.n, (a.rows.n, b.cols.n, a.cols.n), block, tasks, task_numbers)


def product(a: BlockMatrix, b: BlockMatrix, tasks: int | None = None, **options) -> BlockMatrix:
    """a b by the plan that plan_product chooses; tasks: None for the session's cores."""
    c = plan_product(a, b, tasks or a.blocks.sparkSession.sparkContext.defaultParallelism)
    if c.variant == "broadcast":
        return mm_broadcast(a, b)
    if c.variant == "split":
        return mm_split(a, b)
    return mm_25d(a, b, c.grid, c.grid.layers) if c.variant == "25d" else mm_panels(a, b, c.grid, c.depth, **options)


def explain_mm(a: BlockMatrix, b: BlockMatrix, tasks: int | None = None) -> str:
    c = plan_product(a, b, tasks or a.blocks.sparkSession.sparkContext.defaultParallelism)
    return f"{c.variant}: grid {c.grid.pr} x {c.grid.pc} x {c.grid.layers}, {c.depth} rounds in flight, {8 * c.moved} bytes moved, {8 * c.memory:.0f} bytes a task, {2 * a.rows.n * a.cols.n * b.cols.n} apparent flops"


def chain_order(shapes: list[tuple[int, int]]) -> tuple[int, str]:
    """Fewest multiplications of a chain of dense products, and its bracketing, by dynamic programming."""
    n = len(shapes)
    best = {(i, i): (0, f"M{i}") for i in range(n)}
    for span in range(1, n):
        for i in range(n - span):
            j = i + span
            best[i, j] = min((best[i, k][0] + best[k + 1, j][0] + shapes[i][0] * shapes[k][1] * shapes[j][1], f"({best[i, k][1]} {best[k + 1, j][1]})") for k in range(i, j))
    return best[0, n - 1]


def balance_cells(costs: DataFrame, cells: int) -> DataFrame:
    """item, cell: items dealt to cells by descending cost in a snake, so that no cell is far above the mean; a sort and
    arithmetic instead of a greedy loop on the driver."""
    rank = F.row_number().over(Window.orderBy(F.desc("cost"), "item")) - 1
    at = F.pmod(rank, F.lit(2 * cells))
    return costs.select("item", "cost", F.when(at < cells, at).otherwise(2 * cells - 1 - at).cast("int").alias("cell"))
