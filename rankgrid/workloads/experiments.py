"""The experiments on the given tables: what each measure does as a parameter moves."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from rankgrid import baselines
from rankgrid.operators import iterate, lrb, screening
from rankgrid.operators.iterate import Options, inv_sqrt
from rankgrid.operators.multiply import Grid, mm_panels, mm_sparse
from rankgrid.plans import costs, measures, schedule
from rankgrid.registry import query
from rankgrid.schema import BlockMatrix
from rankgrid.session import written
from rankgrid.sources import matrices as mx
from rankgrid.workloads import fragments as s
from rankgrid.workloads.lowrank import EPS_LR, EPS_SP, customer
from rankgrid.workloads.products import customer_supplier, d1


def _digits(error: float) -> int:
    """Decimal places of an error: 6 for 1e-6 to 1e-7."""
    return int(math.floor(-math.log10(max(error, 1e-16)) + 1e-9))


def inverse_roots(spark, sf_dir, kind, rounds):
    """The dense kernel of every customer, and its inverse root in dense and in low-rank form. The long-range kernel has no
    tile to screen in dense form."""
    m = customer(spark, sf_dir, kind, by="nation")
    dense = lrb.with_repr(m, "F")
    dense = BlockMatrix(written(dense.blocks, "dense"), m.rows, m.cols)
    return dense, [("F", inv_sqrt(dense, rounds, options=Options(eps_sp=EPS_SP if kind == "decay" else 0.0))), ("L", inv_sqrt(m, rounds, options=Options(eps_lr=EPS_LR, eps_sp=EPS_SP)))]


def _inverse(kind, rounds):
    """Inverse roots in dense and in low-rank form: decimal places of ‖R M R − I‖, numbers stored, and tiles by form."""

    def run(spark, sf_dir):
        dense, found = inverse_roots(spark, sf_dir, kind, rounds)
        rows = []
        for form, r in found:
            z = r.z.blocks.agg(F.sum(costs.stored_numbers()).alias("stored"), F.count_if(F.col("repr") == "L").alias("low"), F.count_if(F.col("repr") == "F").alias("full")).first()
            rows.append((form, r.rounds, _digits(iterate.residual(r.inverse(), dense)), z["stored"], dense.rows.blocks**2 - z["low"] - z["full"], z["low"], z["full"]))
        return spark.createDataFrame(rows, "form string, rounds int, residual_digits int, stored long, absent long, low long, full long")

    return run


# rounds after which the residual of the low-rank form does not fall any more
for _kind, _name, _rounds in (("longrange", "w1_longrange", 7), ("decay", "w2_overlap", 5)):
    query(None, _name)(_inverse(_kind, _rounds))


@query()
def w3_hist(spark, sf_dir):
    """Rank histograms of the input and of the matrices of round five, every customer, blocks by nation."""
    m = customer(spark, sf_dir, by="nation")
    r = inv_sqrt(m, 5, options=Options(eps_lr=EPS_LR, eps_sp=EPS_SP))
    out, n = None, m.rows.blocks
    for name, b in (("input", m), ("x", r.x), ("t", r.t), ("z", r.z), ("y", r.y)):
        part = measures.rank_histogram(b.blocks, n * n).select(F.lit(name).alias("matrix"), "bin", "blocks")
        out = part if out is None else out.unionByName(part)
    return out


_DENSE = s.nonzero(s.product(s.dense(128), s.dense(128, 5)))


@query("SELECT method, i, j, v FROM (SELECT unnest(['multi', '2d', '25d']) AS method), (" + _DENSE + ")")
def w4_dense(spark, sf_dir):
    """A dense product by the multiple-issue method and both baselines: the same integers."""
    a, b = mx.dense_integer_tiles(spark, 128, 32), mx.dense_integer_tiles(spark, 128, 32, 5)
    x, y = mx.dense_integers(spark, 128), mx.dense_integers(spark, 128, 5)
    out = None
    for name, c in (("multi", mm_panels(a, b, Grid(2, 2))), ("2d", baselines.dense2d(x, y, 128, 128, 128, 32)), ("25d", baselines.dense25d(x, y, 128, 128, 128, 32))):
        part = c.to_coo().select(F.lit(name).alias("method"), "*")
        out = part if out is None else out.union(part)
    return out


@query("SELECT CAST(d AS INTEGER) AS depth, SUM(v) AS checksum, CAST(ceil(4.0 / d) AS INTEGER) AS barriers FROM (" + _DENSE + "), (SELECT unnest([1, 2, 4]) AS d) GROUP BY d")
def w5_depth(spark, sf_dir):
    """Rounds in flight from one to all: one result, fewer barriers."""
    a, b = mx.dense_integer_tiles(spark, 128, 32), mx.dense_integer_tiles(spark, 128, 32, 5)
    out = None
    for d in (1, 2, 4):
        part = mm_panels(a, b, Grid(2, 2), depth=d).to_coo().agg(F.sum("v").alias("checksum")).select(F.lit(d).alias("depth"), "checksum", F.lit(schedule.count_barriers(4, d, "waves")).alias("barriers"))
        out = part if out is None else out.union(part)
    return out


@query("SELECT CAST(n AS INTEGER) AS n, CAST(n * n * n * 2 AS BIGINT) AS flops, SUM(v) AS checksum FROM (" + " UNION ALL ".join(f"SELECT CAST({n} AS BIGINT) AS n, v FROM ({s.product(s.dense(n), s.dense(n, 5))})" for n in (32, 64, 96, 128)) + ") GROUP BY n")
def w6_sizes(spark, sf_dir):
    """Four sizes of the dense product with apparent work: the workload of the scaling runs in the bench."""
    out = None
    for n in (32, 64, 96, 128):
        c = mm_panels(mx.dense_integer_tiles(spark, n, 32), mx.dense_integer_tiles(spark, n, 32, 5), Grid(2, 2), "all")
        part = c.to_coo().agg(F.sum("v").alias("checksum")).select(F.lit(n).alias("n"), F.lit(costs.flops_dense(n, n, n)).cast("long").alias("flops"), "checksum")
        out = part if out is None else out.union(part)
    return out


@query()
def w7_eps(spark, sf_dir):
    """kind, eps, error of the product (Frobenius), stored numbers and work relative to the dense form, as the threshold goes to zero."""
    rows = []
    for kind in ("decay", "longrange"):
        dense = lrb.with_repr(customer(spark, sf_dir, kind, eps_lr=0.0, by="nation"), "F")
        dense = BlockMatrix(written(dense.blocks, "dense"), dense.rows, dense.cols)
        exact = mm_panels(dense, dense, depth="all")
        exact = BlockMatrix(written(exact.blocks, "exact"), exact.rows, exact.cols)
        for eps in (1e-2, 1e-4, 1e-6, 1e-8, 0.0):
            low = lrb.compress(dense, eps)
            low = BlockMatrix(written(low.blocks, "low"), low.rows, low.cols)
            d = lrb.lincomb([(1.0, mm_panels(low, low, depth="all", eps_lr=eps)), (-1.0, exact)])
            n = low.rows.n
            rows.append((kind, eps, lrb.frobenius(d).first()[0] or 0.0, measures.storage(low.blocks, n * n).first()["ratio"], costs.flops_lrb(low.blocks, low.blocks).first()["flops"] / (2.0 * n**3)))
    return spark.createDataFrame(rows, "kind string, eps double, error double, storage double, work double")


def _tile_norms(kind: str) -> str:
    return f"(SELECT bi, bj, sqrt(SUM(v * v)) AS norm FROM {s.kernel(kind, 'customer')} GROUP BY 1, 2)"


_SIZES = "(SELECT c_nationkey AS b, count(*) AS n FROM customer GROUP BY 1)"


def _skipped(kind: str) -> str:
    return f"""SELECT '{kind}' AS kind, CAST(count(*) AS BIGINT) AS tiles, CAST(count(CASE WHEN est <= 1e-13 * p.n * q.n THEN 1 END) AS BIGINT) AS tiles_skipped,
  CAST(SUM(terms) AS BIGINT) AS products, CAST(SUM(CASE WHEN est <= 1e-13 * p.n * q.n THEN terms ELSE 0 END) AS BIGINT) AS products_skipped
  FROM (SELECT a.bi, b.bj, SUM(a.norm * b.norm) AS est, count(*) AS terms FROM {_tile_norms(kind)} a JOIN {_tile_norms(kind)} b ON a.bj = b.bi GROUP BY 1, 2) JOIN {_SIZES} p ON bi = p.b JOIN {_SIZES} q ON bj = q.b"""


@query(_skipped("decay") + " UNION ALL " + _skipped("longrange"))
def w8_screen(spark, sf_dir):
    """Tiles and tile products that screening leaves out of the square of each kernel over all customers, blocks by nation."""
    out = None
    for kind in ("decay", "longrange"):
        m, _ = mx.kernel_matrix(mx.positions(spark, sf_dir, "customer"), kind, by="nation")
        n = BlockMatrix(written(m.norms(), "norms"), m.rows, m.cols).blocks
        part = screening.screen_savings(n, n, m.rows, m.cols, EPS_SP).select(F.lit(kind).alias("kind"), "*")
        out = part if out is None else out.unionByName(part)
    return out


@query()
def w9_throughput(spark, sf_dir):
    """Apparent flops a second of one round of products, for two representations. Times differ from run to run: rows only."""
    rows = []
    for kind in ("F", "L"):
        m = lrb.with_repr(customer(spark, sf_dir, "longrange", by="nation"), kind, EPS_LR)
        m = BlockMatrix(written(m.blocks, "timed"), m.rows, m.cols)
        sec = measures.time_query(lambda m=m, kind=kind: mm_panels(m, m, depth="all", eps_lr=EPS_LR if kind == "L" else 0.0).blocks, repeats=1, warmup=0)
        rows.append((kind, float(costs.throughput(costs.flops_dense(m.rows.n, m.rows.n, m.rows.n), sec))))
    return spark.createDataFrame(rows, "form string, flops_per_second double")


#: Blocks of customers by nation in their order, and the cost of each process of a 2 x 2 grid in each round of a dense product.
_BLOCKS = "(SELECT row_number() OVER (ORDER BY n_regionkey, n_nationkey) - 1 AS b, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey, n_nationkey)"
_UNEVEN = f"(SELECT y.b AS k, (x.b % 2) * 2 + z.b % 2 AS p, CAST(SUM(x.n * y.n * z.n) AS DOUBLE) AS cost FROM {_BLOCKS} x, {_BLOCKS} y, {_BLOCKS} z GROUP BY 1, 2)"


@query(f"""
WITH c AS {_UNEVEN}
SELECT (SELECT SUM(x) FROM (SELECT MAX(cost) AS x FROM c GROUP BY k)) AS sync, (SELECT SUM(x) FROM (SELECT w, MAX(y) AS x FROM (SELECT k // 4 AS w, p, SUM(cost) AS y FROM c GROUP BY 1, 2) GROUP BY w)) AS waves,
  (SELECT MAX(y) FROM (SELECT SUM(cost) AS y FROM c GROUP BY p)) AS decoupled, (SELECT AVG(y) FROM (SELECT SUM(cost) AS y FROM c GROUP BY p)) AS mean""")
def w10_imbalance(spark, sf_dir):
    """Makespans of a product with uneven natural blocks (customers by nation): a barrier after each round, after four, and none, against the mean."""
    from rankgrid.operators.blocking import natural_blocking, ordering

    b = natural_blocking(ordering(mx.positions(spark, sf_dir, "customer"), "points", "key", ["region", "nation"], ["bal"])).select("b", "len")
    pairs = b.select(F.col("b").alias("bi"), F.col("len").alias("m")).crossJoin(b.select(F.col("b").alias("bj"), F.col("len").alias("n")))
    return schedule.makespan(schedule.task_costs(pairs, pairs, 2, 2, b.count()), 4)


@query("SELECT CAST(i AS INTEGER) AS depth, CAST(i * 2 * 128.0 * 32 / 2 + 3 * 128.0 * 128 / 4 AS DOUBLE) AS numbers FROM (SELECT unnest([1, 2, 4]) AS i)")
def w11_memory(spark, sf_dir):
    """The memory model for the dense workload, linear in the rounds in flight."""
    return spark.createDataFrame([(i, float(costs.mem_dense(128, 128, 128, 32, 2, 2, i))) for i in (1, 2, 4)], "depth int, numbers double")


@query("SELECT 'co_supply' AS what, * FROM (" + s.product(s.t(s.D1), s.D1) + ") UNION ALL SELECT 'customer_supplier' AS what, * FROM (" + s.product(s.D2, s.D1) + ")")
def w12_spgemm(spark, sf_dir):
    """Sparse products: suppliers that share parts, and customers by suppliers."""
    m = d1(spark, sf_dir)
    one = mm_sparse(m.T, m).to_coo()
    a, b = customer_supplier(spark, sf_dir)
    return one.select(F.lit("co_supply").alias("what"), "*").union(mm_sparse(a, b).to_coo().select(F.lit("customer_supplier").alias("what"), "*"))


