"""Cost and accuracy measures, schedules and plans."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.operators import lrb, screening
from rankgrid.plans import costs, planner, schedule
from rankgrid.plans import measures as ms
from rankgrid.registry import query
from rankgrid.schema import Skeleton
from rankgrid.session import table
from rankgrid.workloads import fragments as s
from rankgrid.workloads import products
from rankgrid.workloads.lowrank import integer_tiles
from rankgrid.workloads.products import D4_GRAM, ROUNDS, d1_rounds, d1_shapes, d1_skeleton, d4

_PB, _SB, _D1N = products.PB, products.SB, products.D1N
#: Costs of the product of D1 transposed with D1 on a 2 x 2 grid by round and process.
_COSTS = f"""(SELECT k, p, coalesce(cost, 0) AS cost FROM (SELECT unnest(range((SELECT 1 + max(bi) FROM {_D1N}))) AS k) r CROSS JOIN (SELECT unnest(range(4)) AS p) q
  LEFT JOIN (SELECT a.bi AS wk, (a.bj % 2) * 2 + b.bj % 2 AS wp, CAST(SUM(a.n * a.m * b.n) AS DOUBLE) AS cost FROM {_D1N} a JOIN {_D1N} b ON a.bi = b.bi GROUP BY 1, 2) w ON k = wk AND p = wp)"""


def _sets():
    return [(m, n, k, b, pr, pc, i) for m, n, k in ((4096, 4096, 4096), (1500, 2000, 100)) for b in (128, 256) for pr, pc in ((1, 1), (2, 4), (8, 8)) for i in (1, 2, 8)]


_SETS = "(VALUES " + ", ".join(str(tuple(map(float, x))) for x in _sets()) + ") AS t(m, n, k, b, pr, pc, i)"
_AS = ", ".join(f"CAST({c} AS INTEGER) AS {c}" for c in ("m", "n", "k", "b", "pr", "pc", "i"))


@query(f"SELECT {_AS}, i * (m * b / pr + n * b / pc) + (m * n + m * k + k * n) / (pr * pc) AS numbers FROM {_SETS}")
def mem_dense(spark, sf_dir):
    t = spark.createDataFrame(_sets(), "m int, n int, k int, b int, pr int, pc int, i int")
    d = [F.col(c).cast("double") for c in ("m", "n", "k", "b", "pr", "pc", "i")]
    return t.select("*", costs.mem_dense(*d).alias("numbers"))


@query("SELECT CAST(n AS INTEGER) AS n, CAST(p AS INTEGER) AS p, CAST(i AS INTEGER) AS i, i * 2 * n * 256 / sqrt(p) + 3 * n * n / p AS numbers FROM (SELECT unnest([1024.0, 32768.0]) AS n) a, (SELECT unnest([1.0, 4.0, 64.0]) AS p) b, (SELECT unnest([1.0, 2.0, 8.0]) AS i) c")
def mem_square(spark, sf_dir):
    t = spark.createDataFrame([(n, p, i) for n in (1024, 32768) for p in (1, 4, 64) for i in (1, 2, 8)], "n int, p int, i int")
    d = [F.col(c).cast("double") for c in "npi"]
    return t.select("*", costs.mem_square(d[0], F.lit(256.0), d[1], d[2]).alias("numbers"))


@query(f"""
WITH a AS {_D1N}, z AS (SELECT SUM(m * n) / (CAST((SELECT count(*) FROM part) AS DOUBLE) * (SELECT count(*) FROM supplier)) AS f FROM a),
r AS (SELECT SUM(x) / CAST((SELECT 1 + max(bi) FROM a) AS DOUBLE) AS act FROM (SELECT bi, count(DISTINCT bj % 2) AS x FROM a GROUP BY bi)), s AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM supplier), p AS (SELECT CAST(count(*) AS DOUBLE) AS k FROM part)
SELECT round(2 * (f * (act / 2) * n * {_PB} / 2 + f * (act / 2) * n * {_PB} / 2) + (n * n + f * n * k + f * k * n) / 4, 6) AS numbers FROM z, r, s, p""")
def mem_sparse(spark, sf_dir):
    """Memory of a process for D1 transposed with D1 on a 2 x 2 grid, two rounds in flight, fills measured on tiles."""
    m = d1_skeleton(spark, sf_dir)
    n = m.norms()
    f = n.agg(F.sum("area")).first()[0] / (m.rows.n * m.cols.n)
    act = costs.active_grid(m.T.norms(), n, 2, 2, m.rows.blocks).first()
    v = costs.mem_sparse(m.cols.n, m.cols.n, m.rows.n, m.rows.length(0), 2, 2, 2, f, f, 1.0, act["active_rows"], act["active_cols"])
    return spark.createDataFrame([(round(float(v), 6),)], "numbers double")


@query(f"SELECT SUM(x) / CAST(max(k) AS DOUBLE) AS active_rows, SUM(x) / CAST(max(k) AS DOUBLE) AS active_cols FROM (SELECT bi, count(DISTINCT bj % 2) AS x FROM {_D1N} GROUP BY bi), (SELECT 1 + max(bi) AS k FROM {_D1N})")
def active_grid(spark, sf_dir):
    m = d1_skeleton(spark, sf_dir)
    return costs.active_grid(m.T.norms(), m.norms(), 2, 2, m.rows.blocks)


@query("SELECT CAST(p AS INTEGER) AS p, CAST(i AS INTEGER) AS i, 2 * i * 256 * 32768 / sqrt(p) / (3 * 32768.0 * 32768 / p) AS ratio FROM (SELECT unnest([1.0, 16.0, 64.0]) AS p) a, (SELECT unnest([1.0, 2.0, 8.0]) AS i) b")
def mem_overhead(spark, sf_dir):
    return spark.createDataFrame([(p, i, costs.mem_overhead_ratio(32768.0, 256, p, i)) for p in (1, 16, 64) for i in (1, 2, 8)], "p int, i int, ratio double")


@query("SELECT CAST(r AS INTEGER) AS rank, CAST(9 * r * 16 AS BIGINT) AS stored, CAST(24 * 24 AS BIGINT) AS dense FROM (SELECT unnest([1, 2]) AS r)")
def mem_bound(spark, sf_dir):
    """Stored numbers of nine tiles of 8 x 8 and a known rank, against those of the dense form."""
    out = None
    for r in (1, 2):
        part = lrb.compress(integer_tiles(spark, r), 1e-9).blocks.agg(F.sum(costs.stored_numbers()).alias("stored")).select(F.lit(r).alias("rank"), "stored", F.lit(576).cast("long").alias("dense"))
        out = part if out is None else out.union(part)
    return out


@query(f"WITH c AS {_D1N} SELECT CAST(SUM(m * n) AS BIGINT) AS stored, SUM(m * n) / (CAST((SELECT count(*) FROM part) AS DOUBLE) * (SELECT count(*) FROM supplier)) AS ratio FROM c")
def storage_ratio(spark, sf_dir):
    m = d1_skeleton(spark, sf_dir)
    return ms.storage(m.blocks, m.rows.n * m.cols.n)


@query("SELECT CAST(n AS BIGINT) AS n, 2 * n * n * n AS product, 8 * power(n, 3) * 10 AS ten_rounds FROM (SELECT CAST(unnest([count(DISTINCT l_partkey), count(DISTINCT l_suppkey), count(DISTINCT l_orderkey)]) AS DOUBLE) AS n FROM lineitem)")
def flops_apparent(spark, sf_dir):
    """Work of a dense product and of ten rounds of the iteration over the parts, the suppliers and the orders that have lines."""
    d = table(spark, sf_dir, "lineitem").agg(*[F.count_distinct(c).cast("double") for c in ("l_partkey", "l_suppkey", "l_orderkey")]).first()
    return spark.createDataFrame([(int(n), costs.flops_dense(n, n, n), costs.flops_iteration(n, 10)) for n in d], "n long, product double, ten_rounds double")


@query(f"WITH c AS {_COSTS}, t AS (SELECT SUM(cost) AS work, (SELECT SUM(x) FROM (SELECT MAX(cost) AS x FROM c GROUP BY k)) AS sync FROM c) SELECT round(work / sync, 6) AS rate, round(work / sync / 4, 6) AS share FROM t")
def flops_peak(spark, sf_dir):
    """Work of D1 transposed with D1 for a unit of time with a barrier after each round, and its share of what four processes could do."""
    t = schedule.makespan(_costs(spark, sf_dir), 4).first()
    rate = costs.throughput(4 * t["mean"], t["sync"])
    return spark.createDataFrame([(round(rate, 6), round(costs.peak_share(rate, 4), 6))], "rate double, share double")


_TIMES = [("multi", 1, 80.0), ("multi", 1, 84.0), ("multi", 4, 25.0), ("multi", 4, 23.0), ("single", 1, 82.0), ("single", 4, 48.0)]
_TIMES_SQL = "(SELECT variant, p, avg(seconds) AS seconds FROM (VALUES " + ", ".join(f"('{v}', {p}, CAST({x} AS DOUBLE))" for v, p, x in _TIMES) + ") AS t(variant, p, seconds) GROUP BY 1, 2)"


_LINES = "(SELECT l_returnflag AS variant, l_linenumber AS p, avg(l_quantity) AS seconds FROM lineitem GROUP BY 1, 2)"


@query(f"WITH t AS {_LINES}, f AS (SELECT variant, MIN(p) AS p FROM t GROUP BY 1), b AS (SELECT t.* FROM t JOIN f ON t.variant = f.variant AND t.p = f.p) SELECT t.variant, CAST(t.p AS INTEGER) AS p, t.seconds, b.seconds / t.seconds AS speedup, b.seconds * b.p / (t.seconds * t.p) AS efficiency FROM t JOIN b ON t.variant = b.variant")
def efficiency_formula(spark, sf_dir):
    """Lines as timed runs: quantities by return flag (the variant) and line number (the processes)."""
    return ms.efficiency(table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("variant"), F.col("l_linenumber").cast("int").alias("p"), F.col("l_quantity").alias("seconds")))


@query(f"SELECT t.variant, CAST(t.p AS INTEGER) AS p, t.seconds / b.seconds AS times_longer, 100 * (t.seconds / b.seconds - 1) AS percent_slower FROM {_TIMES_SQL} t JOIN {_TIMES_SQL} b ON t.p = b.p AND b.variant = 'multi' WHERE t.variant = 'single'")
def slowdown_formula(spark, sf_dir):
    return ms.slowdown(spark.createDataFrame(_TIMES, "variant string, p int, seconds double"), "multi")


@query("SELECT CAST(r AS INTEGER) AS rank, CAST(b AS INTEGER) AS bin, CAST(CASE WHEN b = 0 THEN 0 ELSE 9 END AS BIGINT) AS blocks FROM (SELECT unnest([1, 2]) AS r) x, (SELECT unnest([0, 1, 2, 3]) AS k) y, (SELECT unnest([0, 2, 3]) AS b) z WHERE k = b AND (b = 0 OR b = ceil(10 * r / 8.0))")
def rank_histogram(spark, sf_dir):
    """Bins of nine tiles of known rank: no absent one, and all in the bin of their share of the full rank."""
    out = None
    for r in (1, 2):
        part = ms.rank_histogram(lrb.compress(integer_tiles(spark, r), 1e-9).blocks, 9).select(F.lit(r).alias("rank"), "bin", "blocks")
        out = part if out is None else out.union(part)
    return out


@query(f"WITH c AS (SELECT (bi % 2) * 2 + bj % 2 AS cell, SUM(m * n) AS s FROM {_D1N} GROUP BY 1) SELECT MAX(s) * 4 / CAST(SUM(s) AS DOUBLE) AS imbalance FROM c")
def imbalance(spark, sf_dir):
    return ms.imbalance(d1_skeleton(spark, sf_dir).blocks, 2, 2)


@query(f"SELECT CAST(bi AS INTEGER) AS k, CAST(SUM(m * n) * 3 AS BIGINT) AS moved FROM {_D1N} GROUP BY 1")
def comm_volume(spark, sf_dir):
    """Numbers sent in each round of D1 transposed with D1 on a 2 x 3 grid."""
    m = d1_skeleton(spark, sf_dir)
    return costs.comm_volume(m.T.norms(), m.norms(), 2, 3)


@query(f"SELECT mode, CAST(i AS INTEGER) AS depth, CAST(CASE mode WHEN 'sync' THEN n WHEN 'waves' THEN ceil(n / CAST(i AS DOUBLE)) ELSE 1 END AS INTEGER) AS barriers FROM (SELECT unnest(['sync', 'waves', 'sliding', 'decoupled']) AS mode) a, (SELECT unnest([1, 2, 4, 10]) AS i) b, (SELECT {ROUNDS} AS n) c")
def barriers(spark, sf_dir):
    """Barriers of a product over parts, with the rounds that D1 has tiles in."""
    n = d1_rounds(spark, sf_dir)
    return spark.createDataFrame([(m, i, schedule.count_barriers(n, i, m)) for m in ("sync", "waves", "sliding", "decoupled") for i in (1, 2, 4, 10)], "mode string, depth int, barriers int")


_N4 = f"(SELECT i // 5 AS bi, j // 5 AS bj, sqrt(SUM(v * v)) AS norm FROM {s.D4} GROUP BY 1, 2)"
_E4 = f"(SELECT a.bi, b.bi AS bj, SUM(a.norm * b.norm) AS est, count(*) AS terms FROM {_N4} a JOIN {_N4} b ON a.bj = b.bj GROUP BY 1, 2)"


@query(f"WITH e AS {_E4}, f AS (SELECT median(est / 25) * (1 + 1e-9) AS f FROM e) SELECT CAST(count(*) AS BIGINT) AS tiles, CAST(count(CASE WHEN est <= f * 25 THEN 1 END) AS BIGINT) AS tiles_skipped, CAST(SUM(terms) AS BIGINT) AS products, CAST(SUM(CASE WHEN est <= f * 25 THEN terms ELSE 0 END) AS BIGINT) AS products_skipped FROM e, f")
def screen_savings(spark, sf_dir):
    m = d4(spark, sf_dir)
    a, b = m.norms(), m.T.norms()
    f = screening.product_estimates(a, b).agg(F.expr("percentile(est / 25, 0.5)")).first()[0] * (1 + 1e-9)
    return screening.screen_savings(a, b, m.rows, m.rows, f)


@query(f"WITH x AS (SELECT a.bj AS i, b.bj AS j, a.bi // 4 AS w, count(*) AS t, MAX(a.n * b.n) AS area FROM {_D1N} a JOIN {_D1N} b ON a.bi = b.bi GROUP BY 1, 2, 3) SELECT CAST(w AS BIGINT) AS wave, CAST(SUM(CASE WHEN t > 1 THEN t * area ELSE 0 END) AS BIGINT) AS temporary FROM x GROUP BY 1")
def temp_c(spark, sf_dir):
    m = d1_skeleton(spark, sf_dir)
    return costs.temp_tiles(m.T.blocks.select("bi", "bj", "m", "n"), m.blocks.select("bi", "bj", "m", "n"), 4)


def _costs(spark, sf_dir):
    m = d1_shapes(spark, sf_dir)
    shape = ("bi", "bj", "m", "n")
    return schedule.task_costs(m.T.blocks.select(*shape), m.blocks.select(*shape), 2, 2, m.rows.blocks)


@query(f"""
WITH c AS {_COSTS}
SELECT (SELECT SUM(x) FROM (SELECT MAX(cost) AS x FROM c GROUP BY k)) AS sync, (SELECT SUM(x) FROM (SELECT w, MAX(y) AS x FROM (SELECT k // 4 AS w, p, SUM(cost) AS y FROM c GROUP BY 1, 2) GROUP BY w)) AS waves,
  (SELECT MAX(y) FROM (SELECT SUM(cost) AS y FROM c GROUP BY p)) AS decoupled, (SELECT AVG(y) FROM (SELECT SUM(cost) AS y FROM c GROUP BY p)) AS mean""")
def sched_makespan(spark, sf_dir):
    return schedule.makespan(_costs(spark, sf_dir), 4)


_SMALL = [(k, p, float((4, 1)[(k + p) % 2])) for k in range(4) for p in range(2)]
_SMALL_SQL = "(VALUES " + ", ".join(f"({k}, {p}, CAST({c} AS DOUBLE))" for k, p, c in _SMALL) + ") AS t(k, p, cost)"


@query(f"""
WITH RECURSIVE c AS (SELECT k, MAX(CASE WHEN p = 0 THEN cost END) AS c0, MAX(CASE WHEN p = 1 THEN cost END) AS c1 FROM {_SMALL_SQL} GROUP BY k),
r AS (SELECT 0 AS k, c0 AS e0, c1 AS e1, CAST(0 AS DOUBLE) AS s0, CAST(0 AS DOUBLE) AS s1, greatest(c0, c1) AS g1, CAST(0 AS DOUBLE) AS g2 FROM c WHERE k = 0
  UNION ALL SELECT c.k, greatest(r.e0, r.g2) + c.c0, greatest(r.e1, r.g2) + c.c1, greatest(r.e0, r.g2), greatest(r.e1, r.g2),
    greatest(greatest(r.e0, r.g2) + c.c0, greatest(r.e1, r.g2) + c.c1), r.g1 FROM r JOIN c ON c.k = r.k + 1)
SELECT CAST(k AS INTEGER) AS k, CAST(0 AS INTEGER) AS p, s0 AS start, e0 AS finish FROM r UNION ALL SELECT CAST(k AS INTEGER), CAST(1 AS INTEGER), s1, e1 FROM r""")
def sched_sliding(spark, sf_dir):
    """Start and finish of each round with two in flight, two processes with costs 4,1,4,1 and 1,4,1,4."""
    return schedule.sliding_times(spark.createDataFrame(_SMALL, "k int, p int, cost double"), 2)


def _each_process(f: str) -> str:
    return ", ".join(f.format(p=p) for p in range(4))


@query(f"""
WITH RECURSIVE c AS (SELECT k, {_each_process("MAX(CASE WHEN p = {p} THEN cost END) AS c{p}")} FROM {_COSTS} GROUP BY k),
r AS (SELECT CAST(0 AS BIGINT) AS k, {_each_process("c{p} AS e{p}")}, {_each_process("CAST(0 AS DOUBLE) AS s{p}")}, greatest({_each_process("c{p}")}) AS g1, CAST(0 AS DOUBLE) AS g2 FROM c WHERE k = 0
  UNION ALL SELECT c.k, {_each_process("greatest(r.e{p}, r.g2) + c.c{p}")}, {_each_process("greatest(r.e{p}, r.g2)")}, greatest({_each_process("greatest(r.e{p}, r.g2) + c.c{p}")}), r.g1 FROM r JOIN c ON c.k = r.k + 1),
t AS (SELECT k, unnest([{_each_process("s{p}")}]) AS s, unnest([{_each_process("e{p}")}]) AS e FROM r), w AS (SELECT k, MIN(s) AS s, MAX(e) AS e FROM t WHERE e > s GROUP BY k)
SELECT round(SUM(e - s) / (MAX(e) - MIN(s)), 9) AS effective_depth FROM w""")
def effective_depth(spark, sf_dir):
    """Rounds of D1 transposed with D1 that are under way at once on a 2 x 2 grid, two in flight."""
    return schedule.effective_depth(schedule.sliding_times(_costs(spark, sf_dir), 2)).select(F.round("effective_depth", 9).alias("effective_depth"))


@query(f"WITH c AS {_COSTS}, w AS (SELECT d, k // d AS w, p, SUM(cost) AS y FROM c, (SELECT unnest([1, 2, 4, 8]) AS d) x GROUP BY 1, 2, 3) SELECT CAST(d AS INTEGER) AS depth, SUM(top) / SUM(mean) AS imbalance FROM (SELECT d, w, MAX(y) AS top, AVG(y) AS mean FROM w GROUP BY 1, 2) GROUP BY d")
def sched_balance(spark, sf_dir):
    return schedule.balance(_costs(spark, sf_dir), [1, 2, 4, 8])


@query(f"WITH r AS (SELECT bi AS k, 2 * SUM(m * n) AS released, SUM(n) * MAX(m) * SUM(n) AS cost FROM {_D1N} GROUP BY 1) SELECT CAST(k AS INTEGER) AS k, CAST(released AS BIGINT) AS released, CAST(cost AS BIGINT) AS cost, CAST(row_number() OVER (ORDER BY released / CAST(cost AS DOUBLE) DESC, k) AS INTEGER) AS rank FROM r")
def sched_priority(spark, sf_dir):
    m = d1_skeleton(spark, sf_dir)
    area = (F.col("m").cast("long") * F.col("n")).alias("area")
    shape = ("bi", "bj", "m", "n", area)
    return schedule.release_order(m.T.blocks.select(*shape), m.blocks.select(*shape)).select("k", "released", "cost", "rank")


def _counted(graphs: dict) -> DataFrame:
    out = None
    for mode, (nodes, edges) in graphs.items():
        for rows, what in ((nodes, "node"), (edges, "edge")):
            part = rows.groupBy("kind").agg(F.count("*").alias("n")).select(F.lit(mode).alias("mode"), "kind", F.lit(what).alias("what"), "n")
            out = part if out is None else out.union(part)
    return out


@query(f"""
WITH g AS (SELECT CAST({ROUNDS} AS BIGINT) AS n, CAST(2 AS BIGINT) AS r, CAST(3 AS BIGINT) AS c)
SELECT * FROM (SELECT mode, kind, what, CASE kind WHEN 'bcast' THEN n * (r + c) WHEN 'update' THEN n * r * c WHEN 'data' THEN 2 * n * r * c + CASE mode WHEN 'classical' THEN (n - 1) * r * c ELSE 0 END
  ELSE 2 * (n - CASE mode WHEN 'classical' THEN 1 ELSE 3 END) * r * c END AS n
FROM g, (SELECT unnest(['classical', 'waiting', 'decoupled']) AS mode) m, (SELECT unnest(['bcast', 'update', 'data', 'sequence']) AS kind, unnest(['node', 'node', 'edge', 'edge']) AS what) k WHERE NOT (mode = 'decoupled' AND kind = 'sequence')) WHERE n > 0""")
def dag_counts(spark, sf_dir):
    """Nodes and edges of the task graphs of a product over parts on a 2 x 3 grid: in order, with three rounds in flight, without order."""
    n = d1_rounds(spark, sf_dir)
    return _counted({mode: schedule.task_graph(spark, n, 2, 3, mode, 3) for mode in ("classical", "waiting", "decoupled")})


@query(f"""
WITH t AS (SELECT DISTINCT i // {_PB} AS k, j // {_SB} AS o FROM {s.D1} WHERE v >= 100), a AS (SELECT DISTINCT k, o % 2 AS gr FROM t), b AS (SELECT DISTINCT k, o % 3 AS gc FROM t),
u AS (SELECT a.k, gr, gc FROM a JOIN b ON a.k = b.k)
SELECT * FROM (SELECT 'sparse' AS mode, 'bcast' AS kind, 'node' AS what, (SELECT count(*) FROM a) + (SELECT count(*) FROM b) AS n UNION ALL SELECT 'sparse', 'update', 'node', count(*) FROM u UNION ALL SELECT 'sparse', 'data', 'edge', 2 * count(*) FROM u
UNION ALL SELECT 'sparse', 'sequence', 'edge', (SELECT count(*) FROM u JOIN a ON a.k = u.k + 2 AND a.gr = u.gr) + (SELECT count(*) FROM u JOIN b ON b.k = u.k + 2 AND b.gc = u.gc)) WHERE n > 0""")
def dag_sparse(spark, sf_dir):
    """The same for D1's largest entries, transposed, with itself: absent tiles are not sent and not multiplied; two rounds in flight."""
    m = d1_skeleton(spark, sf_dir, 100.0)
    return _counted({"sparse": schedule.task_graph(spark, m.rows.blocks, 2, 3, "waiting", 2, m.T.blocks.select("bi", "bj"), m.blocks.select("bi", "bj"))})


@query("SELECT CAST(26000000 AS BIGINT) AS cost, '((M0 (M1 M2)) M3)' AS bracketing")
def plan_chain(spark, sf_dir):
    """The cheapest bracketing of a chain of four products."""
    cost, text = planner.chain_order([(40, 20), (20, 30), (30, 10), (10, 30)])
    return spark.createDataFrame([(cost * 1000, text)], "cost long, bracketing string")


@query(f"WITH r AS (SELECT bi AS item, SUM(m * n) AS cost FROM {_D1N} GROUP BY 1), k AS (SELECT item, cost, row_number() OVER (ORDER BY cost DESC, item) - 1 AS r FROM r) SELECT CAST(item AS INTEGER) AS item, CAST(cost AS BIGINT) AS cost, CAST(CASE WHEN r % 8 < 4 THEN r % 8 ELSE 7 - r % 8 END AS INTEGER) AS cell FROM k")
def plan_balance(spark, sf_dir):
    rows = d1_skeleton(spark, sf_dir).blocks.groupBy(F.col("bi").alias("item")).agg(F.sum(F.col("m").cast("long") * F.col("n")).alias("cost"))
    return planner.balance_cells(rows, 4)


@query(D4_GRAM)
def plan_product(spark, sf_dir):
    """The product by the variant, grid and depth that the planner chooses."""
    m = d4(spark, sf_dir)
    return planner.product(m, m.T).to_coo()


@query(f"""
WITH c AS (SELECT bi, count(*) AS c FROM {_D1N} GROUP BY 1), b AS (SELECT ceil(CAST((SELECT count(*) FROM part) AS DOUBLE) / {_PB}) AS rows, ceil(CAST((SELECT count(*) FROM supplier) AS DOUBLE) / {_SB}) AS cols)
SELECT CAST(r AS INTEGER) AS rank, CAST(SUM(c * c) * 32 * r * r AS DOUBLE) AS flops, CAST(2 * MAX(8 * cols * 8 * cols * 8 * rows) AS DOUBLE) AS dense FROM c, b, (SELECT unnest([1, 2]) AS r) x GROUP BY r""")
def flops_lowrank(spark, sf_dir):
    """Work of a product over parts with tiles of 8 x 8 and a known rank where D1 has tiles, from metadata, against that of the dense one."""
    out, d = None, d1_skeleton(spark, sf_dir)
    rows, cols = 8 * d.rows.blocks, 8 * d.cols.blocks
    for r in (1, 2):
        m = lrb.compress(integer_tiles(spark, r, at=d.blocks), 1e-9)
        m = Skeleton(m.blocks.drop("x", "w"), m.rows, m.cols)
        part = costs.flops_lrb(m.T.blocks, m.blocks).select(F.lit(r).alias("rank"), "flops", F.lit(2.0 * cols * cols * rows).alias("dense"))
        out = part if out is None else out.union(part)
    return out
