"""Low-rank tiles, screening and the inverse square root."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from rankgrid.functions import tiles
from rankgrid.functions.tiles import Tile
from rankgrid.operators import iterate, lrb, screening
from rankgrid.operators.blocking import natural_blocking
from rankgrid.operators.iterate import Options, inv_sqrt
from rankgrid.operators.multiply import Grid, mm_panels
from rankgrid.plans import costs, measures
from rankgrid.registry import query
from rankgrid.schema import BlockMatrix, block_batch, map_tiles, read_tile, tile_row
from rankgrid.session import table, written
from rankgrid.sources import matrices as mx
from rankgrid.sources.skeletons import GROUP_BYTES, kernel_cores
from rankgrid.workloads import fragments as s
from rankgrid.workloads.products import D4_GRAM, d4

EPS_LR, EPS_SP = 1e-6, 1e-13
#: The threshold of a root that is rounded to four decimals.
EPS_ROOT = 1e-12


def supplier(spark, sf_dir, kind="decay", by="region", eps_lr=0.0) -> BlockMatrix:
    m, _ = mx.kernel_matrix(mx.positions(spark, sf_dir), kind, eps_lr=eps_lr, by=by)
    return BlockMatrix(written(m.blocks, "kernel"), m.rows, m.cols)


def customer(spark, sf_dir, kind="decay", eps_lr=EPS_LR, by="region") -> BlockMatrix:
    """The kernel over all customers: the experiments' matrix."""
    m, _ = mx.kernel_matrix(mx.positions(spark, sf_dir, "customer"), kind, eps_lr=eps_lr, by=by, zero_below=EPS_SP)
    return BlockMatrix(written(m.blocks, "kernel"), m.rows, m.cols)


def _points_per_tile(of: str, group: str, where: str = "") -> str:
    return f"(SELECT {group} AS g, count(*) AS n FROM {s.points(of, where)} GROUP BY 1)"


def _natural_errors(spark, sf_dir, kind: str, eps: float):
    """block_error of the supplier kernel's natural tiles (region by region). A natural tile that is cut into parts is
    compressed part by part, each within an equal share of eps, so that the whole tile is within eps."""
    dense, order = mx.kernel_matrix(mx.positions(spark, sf_dir), kind, by="region")
    whole = lrb.natural_of(dense.rows, natural_blocking(order))
    parts = max((whole.count(b) for b in set(whole)), default=1)
    return lrb.natural_error(lrb.block_error(dense, lrb.compress(dense, eps / parts)), whole)


@query(f"SELECT CAST(count(*) AS BIGINT) AS tiles, CAST(0 AS BIGINT) AS above_eps, CAST(0 AS BIGINT) AS above_full, CAST(0 AS BIGINT) AS wrong_form FROM {_points_per_tile('supplier', 'region')} a, {_points_per_tile('supplier', 'region')} b")
def lrb_compress(spark, sf_dir):
    """Tiles compared, and those whose error, rank or form breaks the rule."""
    e = _natural_errors(spark, sf_dir, "decay", EPS_LR)
    return e.agg(F.count("*").alias("tiles"), F.count_if(F.col("err") > EPS_LR * (1 + 1e-6)).alias("above_eps"), F.count_if("above_full").alias("above_full"), F.count_if("wrong_form").alias("wrong_form"))


def integer_tiles(spark, rank: int, n: int = 8, at=None) -> BlockMatrix:
    """Tiles (bi, bj) of exact rank 1 or 2 with small integers: three by three, or those of a table."""
    from rankgrid.schema import BLOCKS, Axis

    rows = cols = Axis.uniform(3 * n, n)
    if at is None:
        at = spark.range(9).select(F.floor(F.col("id") / 3).cast("int").alias("bi"), (F.col("id") % 3).cast("int").alias("bj"))
    else:
        top = at.agg(F.max("bi").alias("bi"), F.max("bj").alias("bj")).first()
        rows, cols = (Axis.uniform(n * (0 if top[c] is None else top[c] + 1), n) for c in ("bi", "bj"))

    def make(batches):
        for b in batches:
            for bi, bj in zip(b.column("bi").to_pylist(), b.column("bj").to_pylist()):
                i, j = np.arange(n), np.arange(n)
                a = np.outer(i + bi + 1, j + bj + 1).astype(float)
                if rank == 2:
                    a = a + np.outer((i + bi) % 2 + 1, (j + bj) % 3 + 1)
                yield block_batch([tile_row(bi, bj, Tile(a))])

    return BlockMatrix(at.select("bi", "bj").mapInArrow(make, BLOCKS), rows, cols)


@query("""
SELECT CAST(r AS INTEGER) AS wanted, CAST(bi AS INTEGER) AS bi, CAST(bj AS INTEGER) AS bj, CAST(r AS INTEGER) AS rank, 'L' AS repr
FROM (SELECT unnest([1, 2]) AS r) x, (SELECT unnest(range(3)) AS bi) a, (SELECT unnest(range(3)) AS bj) b""")
def lrb_rank1(spark, sf_dir):
    out = None
    for r in (1, 2):
        part = lrb.compress(integer_tiles(spark, r), 1e-9).blocks.select(F.lit(r).alias("wanted"), "bi", "bj", "rank", "repr")
        out = part if out is None else out.union(part)
    return out


@query("""
SELECT CAST(m AS INTEGER) AS m, CAST(n AS INTEGER) AS n, CAST(r AS INTEGER) AS rank, CASE WHEN 2 * r <= least(m, n) THEN 'L' ELSE 'F' END AS repr
FROM (SELECT DISTINCT l_linenumber AS m, l_partkey % 8 + 1 AS n, l_suppkey % 8 + 1 AS r FROM lineitem) WHERE r <= least(m, n)""")
def lrb_choice(spark, sf_dir):
    """The storage rule for the shapes and ranks that line numbers, part and supplier keys give."""
    g = table(spark, sf_dir, "lineitem").select(F.col("l_linenumber").cast("int").alias("m"), (F.col("l_partkey") % 8 + 1).cast("int").alias("n"), (F.col("l_suppkey") % 8 + 1).cast("int").alias("rank")).distinct()
    return g.where(F.col("rank") <= F.least("m", "n")).select("m", "n", "rank", lrb.choose_repr(F.col("m"), F.col("n"), F.col("rank")).alias("repr"))


_DENSE_PRODUCT = f"SELECT CAST(a.i AS BIGINT) AS i, CAST(b.j AS BIGINT) AS j, round(SUM(a.v * b.v), 4) + 0.0 AS v FROM {s.kernel('longrange')} a JOIN {s.kernel('longrange')} b ON a.j = b.i GROUP BY 1, 2"


def _rounded(m: BlockMatrix, digits: int = 4):
    return m.to_coo(drop_zeros=False).select("i", "j", (F.round("v", digits) + 0.0).alias("v"))


@query(_DENSE_PRODUCT)
def lrb_mul(spark, sf_dir):
    """Low-rank times low-rank; the tiles are compressed within 1e-10."""
    m = supplier(spark, sf_dir, "longrange", eps_lr=1e-10)
    return _rounded(mm_panels(m, m, depth="all", eps_lr=1e-10))


@query(_DENSE_PRODUCT)
def lrb_mul_mixed(spark, sf_dir):
    """Full times low-rank."""
    m = supplier(spark, sf_dir, "longrange", eps_lr=1e-10)
    return _rounded(mm_panels(lrb.with_repr(m, "F"), m, depth="all"))


_DENSE_SUM = f"SELECT a.i, a.j, round(a.v + b.v, 4) + 0.0 AS v FROM {s.kernel('decay')} a JOIN {s.kernel('longrange')} b ON a.i = b.i AND a.j = b.j"


@query(_DENSE_SUM)
def lrb_add(spark, sf_dir):
    x, y = (supplier(spark, sf_dir, k, eps_lr=1e-10) for k in ("decay", "longrange"))
    return _rounded(lrb.lincomb([(1.0, x), (1.0, y)], eps_lr=1e-10))


@query("SELECT CAST(9 AS BIGINT) AS tiles, CAST(0 AS BIGINT) AS rank_grew, CAST(0 AS BIGINT) AS above_eps, CAST(18 AS BIGINT) AS rank_before, CAST(9 AS BIGINT) AS rank_after")
def lrb_recompress(spark, sf_dir):
    """A tile added to itself has twice the rank until it is recompressed."""

    def twice(row: dict) -> list[dict]:
        t = read_tile(row)
        before = tiles.add(t, t)
        after = tiles.recompress(before, 1e-9)
        return [{"before": before.rank, "after": after.rank, "err": float(np.linalg.norm(before.dense() - after.dense()))}]

    m = lrb.compress(integer_tiles(spark, 1), 1e-9)
    r = map_tiles(m.blocks, twice, "before int, after int, err double", pa.schema([("before", pa.int32()), ("after", pa.int32()), ("err", pa.float64())]))
    return r.agg(F.count("*").alias("tiles"), F.count_if(F.col("after") > F.col("before")).alias("rank_grew"), F.count_if(F.col("err") > 1e-8).alias("above_eps"), F.sum("before").alias("rank_before"), F.sum("after").alias("rank_after"))


@query(f"SELECT round(sqrt(SUM(v * v)), 6) AS fro, round(SUM(CASE WHEN i = j THEN v ELSE 0 END), 6) AS trace FROM {s.kernel('longrange')}")
def lrb_norm(spark, sf_dir):
    m = supplier(spark, sf_dir, "longrange", eps_lr=1e-12)
    return lrb.frobenius(m).crossJoin(lrb.trace(m)).select(F.round("fro", 6).alias("fro"), F.round("trace", 6).alias("trace"))


@query(f"SELECT CAST(a.i AS BIGINT) AS i, CAST(b.j AS BIGINT) AS j, round(SUM(a.v * b.v), 3) + 0.0 AS v FROM {s.kernel('decay')} a JOIN {s.kernel('decay')} b ON a.j = b.i GROUP BY 1, 2")
def mm_lrb(spark, sf_dir):
    """The product with low-rank tiles and screening at the thresholds of the experiments, to three decimals."""
    m = supplier(spark, sf_dir, by="nation", eps_lr=EPS_LR)
    c = mm_panels(m, m, depth="all", eps_lr=EPS_LR, eps_sp=EPS_SP)
    c = BlockMatrix(written(c.blocks, "product"), c.rows, c.cols)
    # tiles that are within the threshold of zero are absent: fill them in
    return _rounded(c, 3).unionByName(_absent(spark, c, m))


def _absent(spark, c: BlockMatrix, like: BlockMatrix):
    n = like.rows.blocks
    there = c.blocks.select(F.col("bi").alias("ti"), F.col("bj").alias("tj"))
    every = spark.range(n * n).select(F.floor(F.col("id") / n).cast("int").alias("bi"), (F.col("id") % n).cast("int").alias("bj"))
    gone = every.join(there, (F.col("bi") == F.col("ti")) & (F.col("bj") == F.col("tj")), "left_anti")
    starts = F.lit(list(like.rows.starts))
    at = lambda b: F.sequence(F.element_at(starts, F.col(b) + 1).cast("long"), F.element_at(starts, F.col(b) + 2).cast("long") - 1)
    return gone.select(F.explode(at("bi")).alias("i"), "bj").select("i", F.explode(at("bj")).alias("j"), F.lit(0.0).alias("v"))


@query(f"SELECT i, j, v FROM (SELECT i, j, CAST(SUM(v) AS DOUBLE) AS v FROM (SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, 2 * v AS v FROM {s.D4} UNION ALL SELECT CAST(j AS BIGINT), CAST(i AS BIGINT), -3 * v FROM {s.D4} UNION ALL SELECT unnest(range(25)), unnest(range(25)), 5) GROUP BY 1, 2) WHERE v <> 0")
def lincomb(spark, sf_dir):
    m = d4(spark, sf_dir)
    return lrb.lincomb([(2.0, m), (-3.0, m.T)], 5.0).to_coo()


_N4 = f"(SELECT i // 5 AS bi, j // 5 AS bj, sqrt(SUM(v * v)) AS norm FROM {s.D4} GROUP BY 1, 2)"
_E4 = f"(SELECT a.bi, b.bj, SUM(a.norm * b.norm) AS est, count(*) AS terms FROM {_N4} a JOIN (SELECT bj AS bi, bi AS bj, norm FROM {_N4}) b ON a.bj = b.bi GROUP BY 1, 2)"
_T4 = f"(SELECT i // 5 AS bi, j // 5 AS bj, sqrt(SUM(v * v)) AS norm FROM ({D4_GRAM}) GROUP BY 1, 2)"
_MID = f"(SELECT median(est / 25) FROM {_E4})"


def _middle(m) -> float:
    e = screening.product_estimates(m.norms(), m.T.norms())
    return e.agg(F.expr("percentile(est / 25, 0.5)")).first()[0]


@query(f"SELECT CAST(bi AS INTEGER) AS bi, CAST(bj AS INTEGER) AS bj, round(est, 3) AS est, CAST(25 AS BIGINT) AS area FROM {_E4} WHERE est > 25 * {_MID} * (1 + 1e-9)")
def screen_product(spark, sf_dir):
    """Tiles of brands by brands whose bound is above the middle one: brands through nations."""
    m = d4(spark, sf_dir)
    out = screening.screen_product(m.norms(), m.T.norms(), m.rows, m.rows, _middle(m) * (1 + 1e-9))
    return out.select("bi", "bj", F.round("est", 3).alias("est"), "area")


@query(f"SELECT CAST(a.bi AS INTEGER) AS bi, CAST(a.bj AS INTEGER) AS bj, round(a.norm + b.norm, 6) AS est, CAST(25 AS BIGINT) AS area FROM {_N4} a JOIN (SELECT bj AS bi, bi AS bj, norm FROM {_N4}) b ON a.bi = b.bi AND a.bj = b.bj WHERE a.norm + b.norm > 1e-13 * 25")
def screen_sum(spark, sf_dir):
    m = d4(spark, sf_dir)
    return screening.screen_sum(m.norms(), m.T.norms(), 1e-13).select("bi", "bj", F.round("est", 6).alias("est"), "area")


@query(f"SELECT CAST(count(*) AS BIGINT) AS tiles, CAST(count(CASE WHEN t.norm > e.est * (1 + 1e-12) THEN 1 END) AS BIGINT) AS violations FROM {_T4} t JOIN {_E4} e ON t.bi = e.bi AND t.bj = e.bj")
def screen_bound_holds(spark, sf_dir):
    m = d4(spark, sf_dir)
    return screening.check_bounds(screening.product_estimates(m.norms(), m.T.norms()), mm_panels(m, m.T, depth="all").norms())


@query(f"WITH n AS {_N4}, f AS (SELECT median(norm) * median(norm) AS f FROM n) SELECT CAST(a.bi AS INTEGER) AS bi, CAST(b.bi AS INTEGER) AS bj, CAST(count(*) AS BIGINT) AS terms FROM n a JOIN n b ON a.bj = b.bj, f WHERE a.norm * b.norm > f.f * (1 + 1e-9) GROUP BY 1, 2")
def screen_term(spark, sf_dir):
    m = d4(spark, sf_dir)
    f = m.norms().agg(F.expr("percentile(norm, 0.5)")).first()[0]
    return screening.screen_terms(m.norms(), m.T.norms(), f * f * (1 + 1e-9))


@query()
def lrb_exact_limit(spark, sf_dir):
    """eps, error, full tiles: the product's distance from the dense one as the threshold falls to zero, every customer."""
    thresholds = (1e-1, 1e-4, 1e-7, 0.0)
    cores = kernel_cores(mx.positions(spark, sf_dir, "customer"), "longrange", thresholds, by="nation", zero_below=EPS_SP)
    dense = cores.at(0.0)
    exact = mm_panels(dense, dense, depth="all")
    exact = BlockMatrix(written(exact.blocks, "exact", shuffles_go=True, group_bytes=GROUP_BYTES), exact.rows, exact.cols)
    rows = []
    for eps in thresholds:
        low = cores.at(eps)
        d = lrb.lincomb([(1.0, cores.recompressed(mm_panels(low, low, depth="all"), eps)), (-1.0, exact)])
        # only the norms are kept, and the shuffle files of a product go before the next one
        norms = BlockMatrix(written(d.blocks.select("norm"), "distance", shuffles_go=True), d.rows, d.cols)
        rows.append((eps, lrb.frobenius(norms).first()[0] or 0.0, cores.full(eps)))
    return spark.createDataFrame(rows, "eps double, error double, full long")


@query(f"SELECT i, j, round(v, 6) + 0.0 AS v FROM {s.kernel('decay')} WHERE round(v, 6) <> 0")
def base_fullrank(spark, sf_dir):
    """Compressed tiles put back into full form."""
    full = lrb.with_repr(supplier(spark, sf_dir, eps_lr=1e-12), "F")
    # what rounds to zero goes before it becomes a row
    return full.to_coo(above=4e-7).select("i", "j", (F.round("v", 6) + 0.0).alias("v")).where("v <> 0")


def invsqrt_sql(kind: str, rounds: int, out: str) -> str:
    """The iteration as unrolled common tables."""
    mul = "SELECT a.i, b.j, SUM(a.v * b.v) AS v FROM {} a JOIN {} b ON a.j = b.i GROUP BY a.i, b.j"
    parts = [f"m AS MATERIALIZED (SELECT i, j, v FROM {s.kernel(kind)})", "al AS MATERIALIZED (SELECT 1 / MAX(r) AS a FROM (SELECT SUM(abs(v)) AS r FROM m GROUP BY i))", "y0 AS (SELECT * FROM m)", "z0 AS (SELECT i, j, CASE WHEN i = j THEN 1.0 ELSE 0.0 END AS v FROM m)"]
    for k in range(rounds):
        parts.append(f"x{k} AS MATERIALIZED (SELECT i, j, v * (SELECT a FROM al) AS v FROM ({mul.format(f'y{k}', f'z{k}')}))")
        parts.append(f"q{k} AS MATERIALIZED ({mul.format(f'x{k}', f'x{k}')})")
        parts.append(f"t{k} AS MATERIALIZED (SELECT q.i, q.j, (3 * q.v - 10 * x.v + CASE WHEN q.i = q.j THEN 15 ELSE 0 END) / 8 AS v FROM q{k} q JOIN x{k} x ON q.i = x.i AND q.j = x.j)")
        parts.append(f"z{k + 1} AS MATERIALIZED ({mul.format(f'z{k}', f't{k}')})")
        parts.append(f"y{k + 1} AS MATERIALIZED ({mul.format(f't{k}', f'y{k}')})")
    return "WITH " + ", ".join(parts) + f" {out}"


def _invsqrt(kind):
    def run(spark, sf_dir):
        return _rounded(inv_sqrt(supplier(spark, sf_dir, kind), 8).inverse())

    return run


for _kind in ("decay", "longrange"):
    query(invsqrt_sql(_kind, 8, "SELECT i, j, round(v * sqrt((SELECT a FROM al)), 4) + 0.0 AS v FROM z8"), f"invsqrt_{_kind}")(_invsqrt(_kind))


@query(invsqrt_sql("decay", 8, "SELECT i, j, round(v * sqrt((SELECT a FROM al)), 4) + 0.0 AS v FROM y8"))
def sqrt_check(spark, sf_dir):
    """The square root, which the iteration gives beside the inverse one. Tiles are low-rank within 1e-12, far below the
    last of the four decimals; no tile is screened, and a round's tables go when no later one reads them."""
    m = supplier(spark, sf_dir, by="nation", eps_lr=EPS_ROOT)
    roots = inv_sqrt(m, 8, options=Options(eps_lr=EPS_ROOT, keep=False))
    # tiles that are within the threshold of zero are absent: fill them in
    return _rounded(roots.root()).unionByName(_absent(spark, roots.y, m))


@query()
def invsqrt_customer(spark, sf_dir):
    """Low-rank tiles over every customer, until ‖X − I‖ is small or ten rounds are done: rounds, ‖R M R − I‖ and ‖S S − M‖ of the inverse root and the root."""
    m = customer(spark, sf_dir, by="nation")
    r = inv_sqrt(m, 10, options=Options(eps_lr=EPS_LR, eps_sp=EPS_SP, keep=False), tol=1e-3)
    low = iterate.residual(r.inverse(), m, keep=False)
    root = lrb.lincomb([(1.0, mm_panels(r.root(), r.root(), depth="all")), (-1.0, m)])
    return spark.createDataFrame([(r.rounds, low, lrb.frobenius(root).first()[0] or 0.0)], "rounds int, residual double, root_error double")


def _distances(rounds: int) -> str:
    each = " UNION ALL ".join(f"SELECT CAST({k + 1} AS INTEGER) AS round, round(sqrt(SUM(power(v - CASE WHEN i = j THEN 1 ELSE 0 END, 2))), 5) AS distance FROM x{k}" for k in range(rounds))
    return invsqrt_sql("decay", rounds, each)


@query(_distances(6))
def invsqrt_residuals(spark, sf_dir):
    """‖X − I‖ in each of six rounds."""
    seen = []
    inv_sqrt(supplier(spark, sf_dir), 6, each=lambda k, roots: seen.append((k, round(iterate.distance_from_identity(roots.x), 5))))
    return spark.createDataFrame(seen, "round int, distance double")


@query()
def invsqrt_rank_log(spark, sf_dir):
    """round, matrix, bin, blocks: ranks of the tiles of x, t, z and y in each of five rounds."""
    m = customer(spark, sf_dir, by="nation")
    logs = []

    def log(k, roots):
        own = None
        for name in "xtzy":
            b = getattr(roots, name).blocks
            part = measures.rank_histogram(b, m.rows.blocks**2).select(F.lit(k).alias("round"), F.lit(name).alias("matrix"), "bin", "blocks")
            own = part if own is None else own.unionByName(part)
        # a round's tables go before the rows of all rounds are read
        logs.append(written(own, "ranks"))

    inv_sqrt(m, 5, options=Options(eps_lr=EPS_LR, eps_sp=EPS_SP, keep=False), each=log)
    out = logs[0]
    for x in logs[1:]:
        out = out.unionByName(x)
    return out


@query(f"SELECT round(1 / MAX(r), 9) AS alpha FROM (SELECT SUM(abs(v)) AS r FROM {s.kernel('decay')} GROUP BY i)")
def alpha_inf(spark, sf_dir):
    a = iterate.choose_alpha(supplier(spark, sf_dir))
    return spark.createDataFrame([(round(a, 9),)], "alpha double")


def _power_sql(steps: int) -> str:
    """The power iteration as unrolled common tables."""
    parts = [f"m AS MATERIALIZED (SELECT i, j, v FROM {s.kernel('decay')})", "x0 AS (SELECT DISTINCT i, (1 + i % 7 / 10.0) / sqrt((SELECT CAST(count(DISTINCT i) AS DOUBLE) FROM m)) AS v FROM m)"]
    for k in range(steps):
        parts.append(f"y{k} AS MATERIALIZED (SELECT m.i, SUM(m.v * x.v) AS v FROM m JOIN x{k} x ON m.j = x.i GROUP BY m.i)")
        parts.append(f"r{k} AS MATERIALIZED (SELECT SUM(x.v * y.v) / SUM(x.v * x.v) AS value, SUM(y.v * y.v) AS yy, SUM(x.v * x.v) AS xx FROM x{k} x JOIN y{k} y ON x.i = y.i)")
        parts.append(f"x{k + 1} AS MATERIALIZED (SELECT i, v / sqrt((SELECT yy FROM r{k})) AS v FROM y{k})")
    return "WITH " + ", ".join(parts) + f" SELECT round(1 / (value + sqrt(greatest(yy / xx - value * value, 0))), 8) AS alpha FROM r{steps - 1}"


@query(_power_sql(6))
def alpha_power(spark, sf_dir):
    """The factor of six steps of the power iteration, raised by its residual."""
    return spark.createDataFrame([(round(iterate.choose_alpha(supplier(spark, sf_dir), "power", 6), 8),)], "alpha double")


@query()
def alpha_two_sided(spark, sf_dir):
    """The three factors for one matrix: by row sums, by the largest eigenvalue, and by both ends of the spectrum."""
    m = supplier(spark, sf_dir, by="nation")
    return spark.createDataFrame([(how, iterate.choose_alpha(m, how, 12)) for how in ("inf", "power", "two_sided")], "how string, alpha double")


@query(f"SELECT CAST(a.i AS BIGINT) AS i, CAST(SUM(a.v * (a.j + 1)) AS DOUBLE) AS v FROM {s.D1} a GROUP BY a.i")
def matvec(spark, sf_dir):
    a = mx.part_supp(spark, sf_dir)
    x = a.select("j").distinct().select(F.col("j").alias("i"), (F.col("j") + 1).cast("double").alias("v"))
    return lrb.matvec(a, x)


@query(f"SELECT CAST(count(*) AS BIGINT) AS tiles, CAST(0 AS BIGINT) AS above_eps FROM {_points_per_tile('supplier', 'region')} a, {_points_per_tile('supplier', 'region')} b")
def lrb_error(spark, sf_dir):
    """Tiles compared with their originals, and those further away than the threshold."""
    return _natural_errors(spark, sf_dir, "longrange", 1e-4).agg(F.count("*").alias("tiles"), F.count_if(F.col("err") > 1e-4 * (1 + 1e-6)).alias("above_eps"))


@query()
def eps_sweep(spark, sf_dir):
    """eps, error, mean rank, storage and work relative to the dense form: the long-range kernel over every customer, blocks by nation."""
    rows = []
    steps = (1e-1, 1e-3, 1e-5, 1e-7)
    dense, _ = mx.kernel_matrix(mx.positions(spark, sf_dir, "customer"), "longrange", by="nation", zero_below=EPS_SP)
    errors, n = written(lrb.block_errors(dense, [lrb.compress(dense, eps) for eps in steps]), "sweep"), dense.rows.n
    for k, eps in enumerate(steps):
        each = errors.where(F.col("matrix") == k)
        e = each.agg(F.sqrt(F.sum(F.col("err") ** 2))).first()[0]
        low = each.where("rank > 0")
        rows.append((eps, e, low.agg(F.avg("rank")).first()[0], measures.storage(low, n**2).first()["ratio"], costs.flops_lrb(low, low).first()["flops"] / (2.0 * n**3)))
    return spark.createDataFrame(rows, "eps double, error double, mean_rank double, storage double, work double")
