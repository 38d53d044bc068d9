"""Representation, placement, and every variant of the product."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession, Window
from pyspark.sql import functions as F

from rankgrid import baselines
from rankgrid.operators import blocking, multiply
from rankgrid.operators.multiply import Grid
from rankgrid.plans import costs, schedule
from rankgrid.registry import query
from rankgrid.schema import Axis, BlockMatrix, Skeleton
from rankgrid.session import table, written
from rankgrid.sources import matrices as mx
from rankgrid.sources.skeletons import GROUP_BYTES
from rankgrid.workloads import fragments as s

#: Norm tables of D1 (parts by suppliers) in SQL, tiles as in d1, with shapes.
PB, SB = "greatest(1, (SELECT count(*) FROM part) // 16)", "greatest(1, (SELECT count(*) FROM supplier) // 5)"
D1N = f"""(SELECT bi, bj, least({PB}, (SELECT count(*) FROM part) - bi * {PB}) AS m, least({SB}, (SELECT count(*) FROM supplier) - bj * {SB}) AS n, nnz
  FROM (SELECT i // {PB} AS bi, j // {SB} AS bj, count(*) AS nnz FROM {s.D1} GROUP BY 1, 2))"""
#: Rounds of a product over parts: block rows of D1 with a tile.
ROUNDS = f"(SELECT count(DISTINCT bi) FROM {D1N})"

#: Side of the tiles of operands that grow with the tables.
SIDE = 250
#: Places of a tile of entries, or its side where it is square: a task holds a tile several times while it orders the entries.
MOST_PLACES, SPARSE_SIDE = 1 << 22, 1024

D4_GRAM = s.product(s.D4, s.t(s.D4))


def d4(spark: SparkSession, sf_dir: str, b: int = 5) -> BlockMatrix:
    return mx.tiles_of(mx.brand_nation(spark, sf_dir), 25, 25, b)


def _d1_axes(spark: SparkSession, sf_dir: str, most: int = 0) -> tuple[Axis, Axis]:
    """The sizes come from the small dimension tables: sixteenths of the parts, fifths of the suppliers, at most `most`."""
    parts, supp = table(spark, sf_dir, "part").count(), table(spark, sf_dir, "supplier").count()
    b, c = max(1, parts // 16), max(1, supp // 5)
    return Axis.uniform(parts, min(b, most or b)), Axis.uniform(supp, min(c, most or c))


def d1(spark: SparkSession, sf_dir: str, most: int = 0) -> BlockMatrix:
    """Parts by suppliers in equal tiles (of sides up to most, if that is given) that store their entries alone: an area
    grows with the square of the tables, entries do not."""
    return blocking.to_blocks(mx.part_supp(spark, sf_dir), *_d1_axes(spark, sf_dir, most), sparse=True)


def d1_strips(spark: SparkSession, sf_dir: str) -> BlockMatrix:
    """d1 with its tiles cut by columns into strips of at most MOST_PLACES places: no task holds a whole tile. A strip's
    block column is its own number divided by those of a block."""
    rows, cols = _d1_axes(spark, sf_dir)
    c = cols.length(0) if cols.blocks else 1
    cut = Axis.strips(cols.n, c, min(c, max(1, MOST_PLACES // max(1, rows.length(0) if rows.blocks else 1))))
    return blocking.to_blocks(mx.part_supp(spark, sf_dir), rows, cut, sparse=True)


def whole_column(m: BlockMatrix) -> Column:
    """The block column of d1 that a strip of d1_strips is part of."""
    return F.floor(F.col("bj") / m.cols.strips_each).cast("int")


def d1_skeleton(spark: SparkSession, sf_dir: str, least: float = 0.0) -> Skeleton:
    """Shapes and norms of the tiles of d1, entries from least on; no tile is filled. Written, as both operands are made of it."""
    entries = mx.part_supp(spark, sf_dir)
    m = blocking.skeleton(entries.where(F.col("v") >= least) if least else entries, *_d1_axes(spark, sf_dir))
    return Skeleton(written(m.blocks, "skeleton"), m.rows, m.cols)


def d1_shapes(spark: SparkSession, sf_dir: str) -> Skeleton:
    """Shapes of the tiles of d1, from the rows of lineitem as they are: what schedules read of it. Written, as d1_skeleton is."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").cast("long").alias("i"), F.col("l_suppkey").cast("long").alias("j"), F.col("l_quantity").alias("v"))
    m = blocking.shapes(lines, *_d1_axes(spark, sf_dir))
    return Skeleton(written(m.blocks, "shapes"), m.rows, m.cols)


def d1_rounds(spark: SparkSession, sf_dir: str) -> int:
    """Block rows of d1 with a tile: the rounds of a product over parts."""
    return d1_skeleton(spark, sf_dir).blocks.select("bi").distinct().count()


@query(f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(v AS DOUBLE) AS v FROM {s.D1}")
def coo_part_supp(spark, sf_dir):
    return blocking.validate_coo(mx.part_supp(spark, sf_dir))


@query("""
SELECT 'customer' AS axis, CAST(row_number() OVER (ORDER BY n_regionkey, c_nationkey, c_acctbal, c_custkey) - 1 AS BIGINT) AS pos, c_custkey AS key,
  CAST(dense_rank() OVER (ORDER BY n_regionkey, c_nationkey) - 1 AS INTEGER) AS b,
  CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) - 1 AS INTEGER) AS off
FROM customer JOIN nation ON c_nationkey = n_nationkey""")
def blocking_by_nation(spark, sf_dir):
    c = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return blocking.ordering(c, "customer", "c_custkey", ["n_regionkey", "c_nationkey"], ["c_acctbal"])


@query("WITH c AS (SELECT count(DISTINCT l_partkey) AS n FROM lineitem) SELECT 'part' AS axis, CAST(b AS INTEGER) AS b, CAST(b * 256 AS BIGINT) AS start, CAST(least(256, n - b * 256) AS INTEGER) AS len, '' AS tag FROM (SELECT unnest(range((n + 255) // 256)) AS b, n FROM c)")
def blocking_uniform(spark, sf_dir):
    """Equal blocks of the parts that were ordered."""
    return blocking.uniform_blocking(spark, "part", table(spark, sf_dir, "lineitem").select("l_partkey").distinct().count(), 256)


_LABELS = "(SELECT label, count(*) AS len FROM embeddings GROUP BY label)"


@query(f"""
SELECT 'vec' AS axis, CAST(row_number() OVER (ORDER BY label) - 1 AS INTEGER) AS b, CAST(sum(len) OVER (ORDER BY label) - len AS BIGINT) AS start,
  CAST(len AS INTEGER) AS len, CAST(row_number() OVER (ORDER BY label) - 1 AS VARCHAR) AS tag FROM {_LABELS}""")
def blocking_by_label(spark, sf_dir):
    return blocking.natural_blocking(blocking.ordering(table(spark, sf_dir, "embeddings"), "vec", "vec_id", ["label"], []))


@query(f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(v AS DOUBLE) AS v FROM {s.D1}")
def blocks_roundtrip(spark, sf_dir):
    return d1(spark, sf_dir, SPARSE_SIDE).to_coo()


@query(f"SELECT CAST(bi AS INTEGER) AS bi, CAST(bj AS INTEGER) AS bj, CAST((bi // 2) % 2 AS INTEGER) AS gr, CAST(bj % 3 AS INTEGER) AS gc FROM {D1N}")
def grid_owner(spark, sf_dir):
    """Where the tiles of D1 lie on a 2 x 3 grid, two block rows after each other on one row of it."""
    gr, gc = blocking.owner(F.col("bi"), F.col("bj"), 2, 3, rblk=2)
    return d1_skeleton(spark, sf_dir).blocks.select("bi", "bj", gr.alias("gr"), gc.alias("gc"))


@query("""
WITH cut AS (SELECT b, start, len, CAST(ceil(len / 20.0) AS BIGINT) AS parts FROM (SELECT row_number() OVER (ORDER BY label) - 1 AS b, sum(len) OVER (ORDER BY label) - len AS start, len FROM """ + _LABELS + """)),
e AS (SELECT b, start, len, parts, unnest(range(parts)) AS p FROM cut),
f AS (SELECT b, start + (p * len) // parts AS start, ((p + 1) * len) // parts - (p * len) // parts AS len FROM e)
SELECT 'vec' AS axis, CAST(row_number() OVER (ORDER BY start) - 1 AS INTEGER) AS b, CAST(start AS BIGINT) AS start, CAST(len AS INTEGER) AS len, CAST(b AS VARCHAR) AS tag FROM f""")
def grid_overdecomposition(spark, sf_dir):
    return blocking.overdecompose(blocking_by_label(spark, sf_dir), 20)


@query(f"""
WITH d AS (SELECT i // greatest(1, (SELECT count(*) FROM part) // 16) AS bi, j // greatest(1, (SELECT count(*) FROM supplier) // 5) AS bj, i, j FROM {s.D1})
SELECT CAST(bi AS INTEGER) AS bi, CAST(bj AS INTEGER) AS bj, CAST(count(DISTINCT j) AS INTEGER) AS columns, CAST(count(*) AS INTEGER) AS entries FROM d GROUP BY 1, 2""")
def dcsc_columns(spark, sf_dir):
    """Columns with entries, and entries, of each tile: the sums over its strips, which share no column."""
    m = d1_strips(spark, sf_dir)
    strips = blocking.to_dcsc(m).select("bi", whole_column(m).alias("bj"), F.size("jc").alias("columns"), F.size("num").alias("entries"))
    return strips.groupBy("bi", "bj").agg(F.sum("columns").cast("int").alias("columns"), F.sum("entries").cast("int").alias("entries"))


@query(f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(v AS DOUBLE) AS v FROM {s.D4}")
def dcsc_roundtrip(spark, sf_dir):
    m = d4(spark, sf_dir)
    return blocking.from_dcsc(blocking.to_dcsc(m), m.rows, m.cols).to_coo()


@query(f"""
WITH b AS (SELECT i // 5 AS bi, j // 5 AS bj FROM {s.D4} GROUP BY 1, 2)
SELECT CAST(count(*) AS BIGINT) AS stored_blocks, CAST(count(*) * 25 AS BIGINT) AS stored_area, CAST(count(*) * 25 AS BIGINT) AS stored_numbers, count(*) / 25.0 AS block_fill, count(*) * 25 / 625.0 AS area_fill FROM b""")
def fill_block(spark, sf_dir):
    return blocking.fill(d4(spark, sf_dir), spark)


_FLAG = "CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END"


@query(f"""
WITH x AS (SELECT {s.BRAND} AS b, CAST(s_nationkey AS BIGINT) AS n, CAST({_FLAG} AS BIGINT) AS f, SUM(l_quantity) AS v
  FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2, 3)
SELECT p.f AS f, p.n AS n, q.n AS m, CAST(SUM(p.v * q.v) AS DOUBLE) AS v FROM x p JOIN (SELECT b, n, SUM(v) AS v FROM x GROUP BY 1, 2) q ON p.b = q.b GROUP BY 1, 2, 3""")
def contract_tensor(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey")).join(table(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).cast("long")
    x = lines.groupBy(mx.brand_number().alias("b"), F.col("s_nationkey").cast("long").alias("n"), flag.alias("f")).agg(F.sum("l_quantity").alias("v"))
    y = x.groupBy("b", F.col("n").alias("m")).agg(F.sum("v").alias("v"))
    return blocking.contract(x, y, {"f": 3, "n": 25, "b": 25, "m": 25}, "fnb,bm->fnm")


def _kernel(kind):
    def run(spark, sf_dir):
        m, _ = mx.kernel_matrix(mx.positions(spark, sf_dir), kind, by="region")
        return m.to_coo(drop_zeros=False).select("i", "j", (F.round("v", 6) + 0.0).alias("v"))

    return run


for _kind in ("decay", "longrange"):
    query(f"SELECT i, j, round(v, 6) + 0.0 AS v FROM {s.kernel(_kind)}", f"kernel_{_kind}")(_kernel(_kind))


@query(D4_GRAM)
def mm_entries_brand(spark, sf_dir):
    a = mx.brand_nation(spark, sf_dir)
    return multiply.mm_entries(a, a.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))


@query(s.product(s.t(s.D1), s.D1))
def mm_entries_part_supp(spark, sf_dir):
    a = mx.part_supp(spark, sf_dir)
    return multiply.mm_entries(a.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), a)


def _gram(f):
    def run(spark, sf_dir):
        m = d4(spark, sf_dir)
        return f(m, m.T).to_coo()

    return run


#: Variants that must all give the same matrix: brands by brands through nations.
VARIANTS = {
    "mm_single_issue": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=1),
    "mm_prefetch": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=1, prefetch=1),
    "mm_reordered": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=2, mode="waves", order="by_owner"),
    "mm_release_first": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=2, order="release"),
    "mm_stationary_a": lambda a, b: multiply.mm_panels(a, b, Grid(2, 3), depth="all", stationary="A"),
    "mm_stationary_b": lambda a, b: multiply.mm_panels(a, b, Grid(2, 3), depth="all", stationary="B"),
    "mm_shift": lambda a, b: multiply.mm_shift(a, b, 3),
    "mm_25d": lambda a, b: multiply.mm_25d(a, b, Grid(2, 2), 2),
    "mm_3d": multiply.mm_3d,
    "base_single_issue": lambda a, b: baselines.single_issue(a, b),
    "mm_broadcast": multiply.mm_broadcast,
    "mm_all_rounds": lambda a, b: multiply.mm_panels(a, b, Grid(3, 2), depth="all"),
    "mm_waves": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=2, mode="waves"),
    "mm_sliding": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth=2, mode="sliding"),
    "mm_split": multiply.mm_split,
    "mm_fused": lambda a, b: multiply.mm_panels(a, b, depth="all"),
    "mm_auto_update": lambda a, b: multiply.mm_auto(a, b, Grid(2, 2), hot=4),
    "mm_tile_broadcast": lambda a, b: multiply.mm_panels(a, b, Grid(2, 3), bcast="tiles"),
    "mm_panel_broadcast": lambda a, b: multiply.mm_panels(a, b, Grid(2, 3), bcast="panel"),
    "mm_subtile": lambda a, b: multiply.mm_panels(a, b, Grid(2, 2), depth="all", row_step=2),
}
for _name, _f in VARIANTS.items():
    query(D4_GRAM, _name)(_gram(_f))


@query(s.product(s.t(s.D1), s.D1))
def mm_multi_issue(spark, sf_dir):
    """Suppliers by suppliers through parts, with the default number of rounds in flight."""
    m = d1(spark, sf_dir, mx.MOST_POINTS)
    # row groups of a few tiles: a task that reads holds those of one at once
    m = BlockMatrix(written(m.blocks, "part_supp", shuffles_go=True, group_bytes=GROUP_BYTES), m.rows, m.cols)
    shape = m.blocks.select("bi", "bj", "m", "n")
    turned = shape.select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), F.col("n").alias("m"), F.col("m").alias("n"))
    grid = multiply.places_grid(BlockMatrix(turned, m.cols, m.rows), BlockMatrix(shape, m.rows, m.cols))
    return multiply.mm_panels(m.T, m, grid).to_coo()


def _doc_tok(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return mx.tokens(docs)


_TOK = "(SELECT doc_id, lang, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]{3,}')) AS token FROM documents)"


@query(f"""
WITH t AS {_TOK}, n AS (SELECT lang, token, CAST(count(*) AS DOUBLE) AS v FROM t GROUP BY 1, 2),
k AS (SELECT token, dense_rank() OVER (ORDER BY token) - 1 AS id FROM (SELECT DISTINCT token FROM n)),
l AS (SELECT lang, dense_rank() OVER (ORDER BY lang) - 1 AS id FROM (SELECT DISTINCT lang FROM n))
SELECT CAST(a.id AS BIGINT) AS i, CAST(b.id AS BIGINT) AS j, SUM(x.v * y.v) AS v FROM n x JOIN n y ON x.token = y.token JOIN l a ON x.lang = a.lang JOIN l b ON y.lang = b.lang GROUP BY 1, 2""")
def mm_sparse_doc(spark, sf_dir):
    """Languages by languages through the counts of all words, by products over stored entries."""
    n = _doc_tok(spark, sf_dir).groupBy("lang", "token").agg(F.count("*").cast("double").alias("v"))
    words = n.select("token").distinct().withColumn("first", F.substring("token", 1, 1))
    sizes = words.groupBy("first").agg(F.count("*").alias("size")).withColumn("start", F.sum("size").over(Window.orderBy("first")) - F.col("size")).withColumnRenamed("first", "f2")
    ids = words.withColumn("off", F.row_number().over(Window.partitionBy("first").orderBy("token")) - 1).join(sizes, F.col("first") == F.col("f2")).select(F.col("token").alias("t2"), (F.col("start") + F.col("off")).alias("j"))
    langs = n.select("lang").distinct().select(F.col("lang").alias("l2"), (F.dense_rank().over(Window.orderBy("lang")) - 1).cast("long").alias("i"))
    coo = n.join(ids, F.col("token") == F.col("t2")).join(langs, F.col("lang") == F.col("l2")).select("i", "j", "v")
    count = ids.count()
    m = blocking.to_blocks(coo, Axis((0, *range(1, langs.count() + 1))), Axis.uniform(count, max(1, count // 8 + 1)))
    return multiply.mm_sparse(m, m.T).to_coo()


@query("SELECT CAST(a.i AS BIGINT) AS i, CAST(b.i AS BIGINT) AS j, round(SUM(a.v * b.v), 6) + 0.0 AS v FROM " + s.D3 + " a JOIN " + s.D3 + " b ON a.j = b.j GROUP BY 1, 2")
def mm_abt_embeddings(spark, sf_dir):
    return gram_of_embeddings(spark, sf_dir)


def gram_of_embeddings(spark, sf_dir, upper: bool = False):
    """i, j, v of the embeddings times their transpose, rounded; upper: only tiles on and above the diagonal."""
    m = mx.tiles_of(mx.embedding_entries(spark, sf_dir), table(spark, sf_dir, "embeddings").count(), 64, SIDE, 16)
    n = m.rows.blocks
    only = None
    if upper:
        every = spark.range(n * n).select(F.floor(F.col("id") / max(n, 1)).cast("int").alias("bi"), (F.col("id") % max(n, 1)).cast("int").alias("bj"))
        only = every.where("bi <= bj")
    c = multiply.multiply_blocks(m, m, tb=True, depth="all", only=only).to_coo(drop_zeros=False)
    return c.select("i", "j", (F.round("v", 6) + 0.0).alias("v"))


@query(s.product(s.t(s.D4), s.D4))
def mm_atb(spark, sf_dir):
    m = d4(spark, sf_dir)
    return multiply.multiply_blocks(m, m, ta=True, depth="all").to_coo()


def customer_supplier(spark, sf_dir) -> tuple[BlockMatrix, BlockMatrix]:
    """All customers by parts, and parts by suppliers."""
    cust, parts, supp = (table(spark, sf_dir, t).count() for t in ("customer", "part", "supplier"))
    return mx.tiles_of(mx.cust_part(spark, sf_dir), cust, parts, SIDE, sparse=True), mx.tiles_of(mx.part_supp(spark, sf_dir), parts, supp, SIDE, sparse=True)


@query(s.product(s.D2, s.D1))
def mm_rect(spark, sf_dir):
    """Customers by suppliers through parts on a grid of 3 x 1."""
    a, b = customer_supplier(spark, sf_dir)
    return multiply.mm_panels(a, b, Grid(3, 1), depth="all").to_coo()


@query(f"SELECT i, j, CAST(SUM(v) AS DOUBLE) AS v FROM (SELECT i, j, 2 * v AS v FROM ({D4_GRAM}) UNION ALL SELECT CAST(i AS BIGINT), CAST(j AS BIGINT), 3 * CAST(v AS DOUBLE) FROM {s.D4}) GROUP BY 1, 2")
def mm_axpy(spark, sf_dir):
    m = d4(spark, sf_dir)
    return multiply.multiply_blocks(m, m, tb=True, alpha=2.0, beta=3.0, c=m, depth="all").to_coo()


@query(f"SELECT 'zt' AS product, * FROM ({D4_GRAM}) UNION ALL SELECT 'ty' AS product, * FROM ({s.product(s.t(s.D4), s.D4)})")
def mm_two_products(spark, sf_dir):
    m = d4(spark, sf_dir)
    x, y = multiply.run_concurrently(lambda: multiply.mm_panels(m, m.T, depth="all"), lambda: multiply.mm_panels(m.T, m, depth="all"))
    return x.to_coo().select(F.lit("zt").alias("product"), "*").union(y.to_coo().select(F.lit("ty").alias("product"), "*"))


@query(D4_GRAM)
def base_dense2d(spark, sf_dir):
    a = mx.brand_nation(spark, sf_dir)
    return baselines.dense2d(a, a.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), 25, 25, 25, 8).to_coo()


@query(D4_GRAM)
def base_dense25d(spark, sf_dir):
    a = mx.brand_nation(spark, sf_dir)
    return baselines.dense25d(a, a.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), 25, 25, 25, 8).to_coo()


@query(f"SELECT CAST(pr AS INTEGER) AS pr, CAST(pc AS INTEGER) AS pc, CAST(least(n, greatest(2, least(pr, pc))) AS INTEGER) AS depth FROM (SELECT unnest(range(1, 9)) AS pr) a, (SELECT unnest(range(1, 9)) AS pc) b, (SELECT {ROUNDS} AS n) c")
def depth_default(spark, sf_dir):
    """Rounds in flight by default, of those that a product over parts has."""
    n = d1_rounds(spark, sf_dir)
    return spark.createDataFrame([(r, c, min(n, costs.optimal_depth(r, c))) for r in range(1, 9) for c in range(1, 9)], "pr int, pc int, depth int")


@query("""
WITH d AS (SELECT CAST(count(DISTINCT l_suppkey) AS DOUBLE) AS n, CAST(count(DISTINCT l_partkey) AS DOUBLE) AS k FROM lineitem),
g AS (SELECT CAST(p AS DOUBLE) AS p, CAST(m AS DOUBLE) * 1000000 AS budget FROM (SELECT unnest([1, 2, 4, 8]) AS p) a, (SELECT unnest([1, 4, 16, 64, 256]) AS m) b)
SELECT CAST(p AS INTEGER) AS p, CAST(budget AS BIGINT) AS budget, CAST(greatest(1, floor((budget - (n * n + 2 * n * k) / (p * p)) / (2 * n * 128 / p))) AS INTEGER) AS depth FROM g, d""")
def depth_for_budget(spark, sf_dir):
    """Rounds in flight that a budget of numbers allows for suppliers by suppliers through parts."""
    d = table(spark, sf_dir, "lineitem").agg(F.count_distinct("l_suppkey").alias("n"), F.count_distinct("l_partkey").alias("k")).first()
    rows = [(p, m * 1_000_000, costs.depth_for_memory(d["n"], d["n"], d["k"], 128, p, p, m * 1e6)) for p in (1, 2, 4, 8) for m in (1, 4, 16, 64, 256)]
    return spark.createDataFrame(rows, "p int, budget long, depth int")


@query("""
SELECT CAST(p AS INTEGER) AS p, kind, CAST(CASE kind WHEN 'flat' THEN p - 1 WHEN 'ring' THEN p - 1 WHEN 'binomial' THEN ceil(log2(p)) ELSE (p + 6) / 8.0 END AS DOUBLE) AS steps
FROM (SELECT unnest([2, 4, 8, 16]) AS p) a, (SELECT unnest(['flat', 'ring', 'binomial', 'pipeline']) AS kind) b""")
def sched_broadcast(spark, sf_dir):
    return spark.createDataFrame([(p, k, float(schedule.broadcast_time(p, k, 8))) for p in (2, 4, 8, 16) for k in ("flat", "ring", "binomial", "pipeline")], "p int, kind string, steps double")


@query("SELECT CAST(k AS INTEGER) AS k, CAST(row_number() OVER (ORDER BY k % 3, k) - 1 AS INTEGER) AS place FROM (SELECT unnest(range(12)) AS k)")
def sched_order(spark, sf_dir):
    return spark.createDataFrame([(k, n) for n, k in enumerate(multiply.round_order(12, 3, "by_owner"))], "k int, place int")
