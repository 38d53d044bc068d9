"""Operators around the matrices: scans, sinks, joins, aggregates, windows, sets, text, time, SQL and user functions."""

from __future__ import annotations

import json
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from rankgrid.operators.multiply import Grid, mm_panels
from rankgrid.registry import query
from rankgrid.schema import read_tile
from rankgrid.session import shared_dir, table
from rankgrid.sources import files
from rankgrid.sources import matrices as mx
from rankgrid.workloads import fragments as s
from rankgrid.workloads.lowrank import supplier
from rankgrid.workloads.products import d1_strips, d4, gram_of_embeddings, whole_column

_LONG = "CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(v AS DOUBLE) AS v"


def _flag(spark, sf_dir, flag):
    from rankgrid.operators.blocking import coo

    return coo(table(spark, sf_dir, "lineitem").where(F.col("l_returnflag") == flag), "l_partkey", "l_suppkey", F.col("l_quantity"))


def _flag_sql(flag):
    return f"(SELECT l_partkey AS i, l_suppkey AS j, SUM(l_quantity) AS v FROM lineitem WHERE l_returnflag = '{flag}' GROUP BY 1, 2)"


def _fresh(spark, name):
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@query(f"SELECT {_LONG} FROM {s.D1}")
def scan_coo(spark, sf_dir):
    return spark.read.schema("l_partkey long, l_suppkey long, l_quantity double").parquet(f"{sf_dir}/lineitem.parquet").groupBy(F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j")).agg(F.sum("l_quantity").alias("v"))


def _file_round_trip(kind):
    def run(spark, sf_dir):
        path = _fresh(spark, f"entries_{kind}")
        files.write_entries(mx.brand_nation(spark, sf_dir), path, kind)
        return files.read_entries(spark, path, kind)

    return run


for _k in ("csv", "json"):
    query(f"SELECT {_LONG} FROM {s.D4}", f"read_{_k}_coo")(_file_round_trip(_k))


@query(f"SELECT {_LONG} FROM {s.D4}")
def read_text_matrix(spark, sf_dir):
    path = _fresh(spark, "entries_text")
    files.write_text_matrix(mx.brand_nation(spark, sf_dir), path)
    return files.read_text_matrix(spark, path)


@query(f"SELECT i, j, round(v, 6) + 0.0 AS v FROM {s.kernel('decay')}")
def source_kernel(spark, sf_dir):
    from rankgrid.sources.kernel_source import KernelSource

    spark.dataSource.register(KernelSource)
    p = mx.positions(spark, sf_dir).orderBy("region", "nation", "bal", "key").select("px", "py", "pz").collect()
    rows = spark.read.format("kernel_matrix").option("points", json.dumps([list(r) for r in p])).option("kind", "decay").load()
    return rows.select("i", "j", (F.round("v", 6) + 0.0).alias("v"))


@query(f"""
WITH p AS (SELECT greatest(1, (SELECT count(*) FROM part) // 16) AS b, greatest(1, (SELECT count(*) FROM supplier) // 5) AS c)
SELECT CAST(i // b AS INTEGER) AS bi, CAST(j // c AS INTEGER) AS bj, round(sqrt(SUM(v * v)), 4) AS norm FROM {s.D1}, p WHERE i // b <= 3 GROUP BY 1, 2""")
def sink_blocks_roundtrip(spark, sf_dir):
    """Norms of the tiles of four block rows, from strips of the tiles in files."""
    path = _fresh(spark, "tiles")
    m = d1_strips(spark, sf_dir)
    files.write_blocks(m.blocks, path, 4)
    strips = files.read_blocks(spark, path).where("bi_group = 0 AND bi <= 3").select("bi", whole_column(m).alias("bj"), "norm")
    return strips.groupBy("bi", "bj").agg(F.round(F.sqrt(F.sum(F.col("norm") * F.col("norm"))), 4).alias("norm"))


@query(s.product(s.t(s.D4), s.D4))
def sink_bucketed(spark, sf_dir):
    """A product over a table bucketed by the summed index: the join needs no exchange."""
    name = f"bucketed_{uuid.uuid4().hex}"
    t = files.write_bucketed(mx.brand_nation(spark, sf_dir), name, "i", 4)
    right = t.select(F.col("i").alias("k"), F.col("j").alias("j2"), F.col("v").alias("v2"))
    return t.join(right.hint("merge"), F.col("i") == F.col("k")).groupBy(F.col("j").alias("i"), F.col("j2").alias("j")).agg(F.sum(F.col("v") * F.col("v2")).alias("v"))


@query(f"SELECT {_LONG} FROM {s.D1} WHERE i IN (SELECT p_partkey FROM part WHERE p_brand = 'Brand#2')")
def slice_rows(spark, sf_dir):
    p = table(spark, sf_dir, "part").where("p_brand = 'Brand#2'").select("p_partkey")
    return mx.part_supp(spark, sf_dir).join(p, F.col("i") == F.col("p_partkey"), "left_semi")


@query(f"SELECT i, j, round(v, 6) + 0.0 AS v FROM {s.kernel('decay')} WHERE abs(i - j) <= 5")
def band_extract(spark, sf_dir):
    return supplier(spark, sf_dir).to_coo(drop_zeros=False).where("abs(i - j) <= 5").select("i", "j", (F.round("v", 6) + 0.0).alias("v"))


@query(f"SELECT {_LONG} FROM {s.D1} WHERE v > 60")
def threshold_drop(spark, sf_dir):
    return mx.part_supp(spark, sf_dir).where("v > 60")


@query("SELECT CAST(a.i AS BIGINT) AS i, CAST(b.i AS BIGINT) AS j, round(SUM(a.v * b.v), 6) + 0.0 AS v FROM " + s.D3 + " a JOIN " + s.D3 + " b ON a.j = b.j WHERE a.i <= b.i GROUP BY 1, 2")
def triangle_upper(spark, sf_dir):
    """Tiles below the diagonal are not worked out, and no pair of entries is a row."""
    return gram_of_embeddings(spark, sf_dir, upper=True).where("i <= j")


def _hinted(hint):
    def run(spark, sf_dir):
        a = mx.cust_part(spark, sf_dir)
        b = mx.part_supp(spark, sf_dir).select(F.col("i").alias("k"), F.col("j").alias("j2"), F.col("v").alias("v2"))
        return a.hint(hint).join(b.hint(hint), F.col("j") == F.col("k")).groupBy("i", F.col("j2").alias("j")).agg(F.sum(F.col("v") * F.col("v2")).alias("v"))

    return run


for _h, _q in (("merge", "join_merge"), ("shuffle_hash", "join_hash")):
    query(s.product(s.D2, s.D1), _q)(_hinted(_h))


@query("SELECT l_partkey AS part, CAST(s_nationkey AS INTEGER) AS nation, SUM(l_quantity) AS v FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2")
def join_broadcast(spark, sf_dir):
    """Suppliers are broadcast only where the optimizer knows them to be small: no hint."""
    return table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_quantity").join(table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy(F.col("l_partkey").alias("part"), F.col("s_nationkey").alias("nation")).agg(F.sum("l_quantity").alias("v"))


def _located(how):
    def run(spark, sf_dir):
        from rankgrid.operators.blocking import locate, natural_blocking, ordering

        o = ordering(table(spark, sf_dir, "embeddings"), "vec", "vec_id", ["label"], [])
        return locate(o.select("pos"), "pos", natural_blocking(o), how).select("pos", "b")

    return run


for _h, _q in (("range", "join_range_blocking"), ("bucket", "join_range_bucketed")):
    query("SELECT CAST(row_number() OVER (ORDER BY label, vec_id) - 1 AS BIGINT) AS pos, CAST(dense_rank() OVER (ORDER BY label) - 1 AS INTEGER) AS b FROM embeddings", _q)(_located(_h))


@query("SELECT a.s_suppkey AS i, b.s_suppkey AS j, round(abs(a.s_acctbal - b.s_acctbal), 2) AS d FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 200")
def join_theta_pairs(spark, sf_dir):
    """A band join: balances meet only within their bin and the next."""
    t = table(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal").withColumn("bin", F.floor(F.col("s_acctbal") / 200))
    near = t.select(F.col("s_suppkey").alias("k2"), F.col("s_acctbal").alias("b2"), F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)).alias("bin2"))
    d = F.abs(F.col("s_acctbal") - F.col("b2"))
    return t.join(near, (F.col("bin") == F.col("bin2")) & (F.col("s_suppkey") < F.col("k2")) & (d < 200)).select(F.col("s_suppkey").alias("i"), F.col("k2").alias("j"), F.round(d, 2).alias("d"))


_N4 = f"(SELECT i // 5 AS bi, sqrt(SUM(v * v)) AS norm FROM {s.D4} GROUP BY 1)"


@query(f"SELECT {_LONG} FROM {s.D4} WHERE i // 5 IN (SELECT bi FROM {_N4} WHERE norm > (SELECT avg(norm) FROM {_N4}))")
def join_semi_screen(spark, sf_dir):
    m = mx.brand_nation(spark, sf_dir)
    n = m.groupBy(F.floor(F.col("i") / 5).alias("bi")).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    heavy = n.crossJoin(n.agg(F.avg("norm").alias("mean"))).where("norm > mean").select("bi")
    return m.join(heavy, F.floor(F.col("i") / 5) == F.col("bi"), "left_semi")


@query("SELECT CAST(p_partkey AS BIGINT) AS part, CAST(s_nationkey AS INTEGER) AS nation FROM part, (SELECT DISTINCT s_nationkey FROM supplier) n WHERE NOT EXISTS (SELECT 1 FROM lineitem JOIN supplier s2 ON l_suppkey = s2.s_suppkey WHERE l_partkey = p_partkey AND s2.s_nationkey = n.s_nationkey)")
def join_anti_absent(spark, sf_dir):
    """Pairs of two small dimensions without an entry."""
    lines = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select(F.col("l_partkey").alias("lp"), F.col("s_nationkey").alias("ln"))
    every = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("part")).crossJoin(table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("nation")).distinct())
    return every.join(lines, (F.col("part") == F.col("lp")) & (F.col("nation") == F.col("ln")), "left_anti")


@query("""
SELECT p.event_id, coalesce(max_by(c.event_id, struct_pack(t := c.ts, e := c.event_id)), -1) AS click_id FROM events p LEFT JOIN events c ON p.user_id = c.user_id AND c.event_type = 'click' AND (c.ts < p.ts OR (c.ts = p.ts AND c.event_id < p.event_id))
WHERE p.event_type = 'purchase' GROUP BY 1""")
def join_asof_events(spark, sf_dir):
    """Each purchase with the user's latest earlier click, -1 for none: one sort per user instead of a join."""
    e = table(spark, sf_dir, "events").where("event_type IN ('purchase', 'click')").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", F.coalesce(last, F.lit(-1))).where("event_type = 'purchase'").select("event_id", "click_id")


@query("SELECT l_orderkey, CAST(l_linenumber AS INTEGER) AS l_linenumber, CAST(datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INTEGER) AS lag FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate <= o_orderdate + INTERVAL 30 DAY")
def join_interval_orders(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    rows = table(spark, sf_dir, "lineitem").join(o, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") <= F.col("o_orderdate") + F.expr("INTERVAL 30 DAY")))
    return rows.select("l_orderkey", "l_linenumber", F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).alias("lag"))


_FULL_SUM = f"SELECT CAST(coalesce(a.i, b.i) AS BIGINT) AS i, CAST(coalesce(a.j, b.j) AS BIGINT) AS j, coalesce(a.v, 0) + coalesce(b.v, 0) AS v FROM {_flag_sql('R')} a FULL JOIN {_flag_sql('N')} b ON a.i = b.i AND a.j = b.j"


def _full_sum(null_safe):
    def run(spark, sf_dir):
        a, b = _flag(spark, sf_dir, "R"), _flag(spark, sf_dir, "N").withColumnsRenamed({"i": "i2", "j": "j2", "v": "v2"})
        on = (F.col("i").eqNullSafe(F.col("i2")) & F.col("j").eqNullSafe(F.col("j2"))) if null_safe else ((F.col("i") == F.col("i2")) & (F.col("j") == F.col("j2")))
        return a.join(b, on, "full_outer").select(F.coalesce("i", "i2").alias("i"), F.coalesce("j", "j2").alias("j"), (F.coalesce("v", F.lit(0.0)) + F.coalesce("v2", F.lit(0.0))).alias("v"))

    return run


query(_FULL_SUM, "join_full_sum")(_full_sum(False))
query(_FULL_SUM, "null_coalesce_sum")(_full_sum(True))


@query(f"SELECT 'row' AS side, CAST(i AS BIGINT) AS k, SUM(v) AS total FROM {s.D1} GROUP BY i UNION ALL SELECT 'col', CAST(j AS BIGINT), SUM(v) FROM {s.D1} GROUP BY j")
def agg_row_sums(spark, sf_dir):
    m = mx.part_supp(spark, sf_dir)
    return m.groupBy(F.lit("row").alias("side"), F.col("i").alias("k")).agg(F.sum("v").alias("total")).union(m.groupBy(F.lit("col"), "j").agg(F.sum("v")))


@query(f"SELECT SUM(v * v) AS fro2, (SELECT MAX(x) FROM (SELECT SUM(abs(v)) AS x FROM {s.D1} GROUP BY j)) AS one, (SELECT MAX(x) FROM (SELECT SUM(abs(v)) AS x FROM {s.D1} GROUP BY i)) AS inf, MAX(abs(v)) AS top FROM {s.D1}")
def agg_norms(spark, sf_dir):
    m = mx.part_supp(spark, sf_dir)
    one, inf = (m.groupBy(c).agg(F.sum(F.abs("v")).alias("x")).agg(F.max("x").alias(n)) for c, n in (("j", "one"), ("i", "inf")))
    return m.agg(F.sum(F.col("v") * F.col("v")).alias("fro2"), F.max(F.abs("v")).alias("top")).crossJoin(one).crossJoin(inf)


@query(f"SELECT SUM(v * v) AS trace FROM {s.D1}")
def agg_trace(spark, sf_dir):
    """The trace of D1 transposed with D1, from its diagonal alone."""
    m = mx.part_supp(spark, sf_dir)
    return m.groupBy("j").agg(F.sum(F.col("v") * F.col("v")).alias("d")).agg(F.sum("d").alias("trace"))


@query("SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, (SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)) AS pairs FROM lineitem")
def agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey", "l_suppkey").alias("pairs"))


@query()
def agg_approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.approx_count_distinct(F.concat_ws("-", "l_partkey", "l_suppkey"), 0.02).alias("pairs"))


def _supply(spark, sf_dir):
    n = table(spark, sf_dir, "supplier").join(table(spark, sf_dir, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    return mx.part_supp(spark, sf_dir).join(n, F.col("j") == F.col("s_suppkey"))


@query(f"SELECT CAST(coalesce(n_regionkey, -1) AS INTEGER) AS region, CAST(coalesce(s_nationkey, -1) AS INTEGER) AS nation, coalesce(s_suppkey, -1) AS supplier, SUM(v * v) AS norm2, count(*) AS nnz, CAST(grouping_id(n_regionkey, s_nationkey, s_suppkey) AS BIGINT) AS level FROM {s.D1} JOIN supplier ON j = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, s_nationkey, s_suppkey)")
def agg_rollup_blocks(spark, sf_dir):
    """Squared norms and entries at every level of tiling: supplier, nation, region, all."""
    r = _supply(spark, sf_dir).rollup("n_regionkey", "s_nationkey", "s_suppkey").agg(F.sum(F.col("v") * F.col("v")).alias("norm2"), F.count("*").alias("nnz"), F.grouping_id().alias("level"))
    return r.select(*[F.coalesce(c, F.lit(-1)).alias(a) for c, a in (("n_regionkey", "region"), ("s_nationkey", "nation"), ("s_suppkey", "supplier"))], "norm2", "nnz", "level")


@query("SELECT l_returnflag AS flag, l_linestatus AS status, SUM(l_quantity) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")).agg(F.sum("l_quantity").alias("qty"))


@query("SELECT coalesce(l_returnflag, 'all') AS flag, CAST(coalesce(l_linenumber, -1) AS INTEGER) AS line, SUM(l_quantity) AS qty FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())")
def agg_grouping_sets(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem")
    return t.groupingSets([[t.l_returnflag], [t.l_linenumber], []], t.l_returnflag, t.l_linenumber).agg(F.sum("l_quantity").alias("qty")).select(F.coalesce("l_returnflag", F.lit("all")).alias("flag"), F.coalesce("l_linenumber", F.lit(-1)).alias("line"), "qty")


_TYPES = ["click", "purchase", "view"]


@query("SELECT user_id, " + ", ".join(f"count(CASE WHEN event_type = '{x}' THEN 1 END) AS n_{x}" for x in _TYPES) + " FROM events GROUP BY user_id")
def agg_pivot(spark, sf_dir):
    p = table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", _TYPES).count()
    return p.select("user_id", *[F.coalesce(x, F.lit(0)).alias(f"n_{x}") for x in _TYPES])


@query("SELECT user_id, event_type AS kind, count(*) AS n FROM events WHERE event_type IN ('click', 'purchase', 'view') GROUP BY 1, 2")
def agg_unpivot(spark, sf_dir):
    u = agg_pivot(spark, sf_dir).unpivot("user_id", [f"n_{x}" for x in _TYPES], "kind", "n")
    return u.where("n > 0").select("user_id", F.expr("substring(kind, 3)").alias("kind"), "n")


_NNZ = f"(SELECT i // 10 AS bi, j // 5 AS bj, count(*) AS nnz FROM {s.D1} GROUP BY 1, 2)"


def _nnz(spark, sf_dir):
    return mx.part_supp(spark, sf_dir).groupBy(F.floor(F.col("i") / 10).alias("bi"), F.floor(F.col("j") / 5).alias("bj")).agg(F.count("*").alias("nnz"))


@query(f"SELECT quantile_cont(nnz, 0.5) AS p50, round(quantile_cont(nnz, 0.95), 6) AS p95 FROM {_NNZ}")
def agg_percentile(spark, sf_dir):
    return _nnz(spark, sf_dir).agg(F.percentile("nnz", 0.5).alias("p50"), F.round(F.percentile("nnz", 0.95), 6).alias("p95"))


@query("SELECT s_suppkey AS key, CAST(row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) - 1 AS INTEGER) AS off, CAST(row_number() OVER (ORDER BY n_regionkey, n_nationkey, s_acctbal, s_suppkey) - 1 AS BIGINT) AS pos FROM supplier JOIN nation ON s_nationkey = n_nationkey")
def win_order(spark, sf_dir):
    from rankgrid.operators.blocking import ordering

    return ordering(mx.positions(spark, sf_dir), "s", "key", ["region", "nation"], ["bal"]).select("key", "off", "pos")


_RANKED = f"(SELECT i AS brand, j AS nation, v FROM {s.D4})"


@query(f"SELECT CAST(brand AS BIGINT) AS brand, CAST(nation AS BIGINT) AS nation, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, percent_rank() OVER w AS p FROM {_RANKED} WINDOW w AS (PARTITION BY brand ORDER BY v DESC)")
def win_rank_blocks(spark, sf_dir):
    w = Window.partitionBy("i").orderBy(F.desc("v"))
    return mx.brand_nation(spark, sf_dir).select(F.col("i").alias("brand"), F.col("j").alias("nation"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.percent_rank().over(w).alias("p"))


@query(f"SELECT CAST(i AS BIGINT) AS brand, CAST(j AS BIGINT) AS nation, CAST(ntile(5) OVER (PARTITION BY i ORDER BY v, j) AS INTEGER) AS part FROM {s.D4}")
def win_ntile_cost(spark, sf_dir):
    return mx.brand_nation(spark, sf_dir).select(F.col("i").alias("brand"), F.col("j").alias("nation"), F.ntile(5).over(Window.partitionBy("i").orderBy("v", "j")).alias("part"))


_UD = "(SELECT user_id AS i, CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS BIGINT) AS j, CAST(count(*) AS DOUBLE) AS v FROM events GROUP BY 1, 2)"


@query(f"SELECT i, j, v - lag(v, 1, 0) OVER w AS before, lead(v) OVER w AS next FROM {_UD} WINDOW w AS (PARTITION BY i ORDER BY j)")
def win_lag_days(spark, sf_dir):
    w = Window.partitionBy("i").orderBy("j")
    return mx.user_day(spark, sf_dir).select("i", "j", (F.col("v") - F.lag("v", 1, 0.0).over(w)).alias("before"), F.lead("v").over(w).alias("next"))


@query("SELECT label, CAST(coalesce(SUM(n) OVER (ORDER BY label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM (SELECT CAST(label AS INTEGER) AS label, count(*) AS n FROM embeddings GROUP BY 1)")
def win_running_start(spark, sf_dir):
    """One row a block."""
    w = Window.orderBy("label").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf_dir, "embeddings").groupBy("label").agg(F.count("*").alias("n")).select("label", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("start"))


@query("SELECT event_id, CAST(SUM(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM events")
def win_range_time(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", F.round(F.col("value") * 100).cast("long").alias("c"), F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"))
    return e.select("event_id", F.sum("c").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)).alias("cents"))


@query(f"SELECT CAST(i AS BIGINT) AS brand, CAST(j AS BIGINT) AS nation, SUM(v) OVER w / SUM(v) OVER (PARTITION BY i) AS share, first_value(v) OVER w AS top, cume_dist() OVER w AS dist FROM {s.D4} WINDOW w AS (PARTITION BY i ORDER BY v DESC, j)")
def win_cume_share(spark, sf_dir):
    w = Window.partitionBy("i").orderBy(F.desc("v"), "j")
    return mx.brand_nation(spark, sf_dir).select(F.col("i").alias("brand"), F.col("j").alias("nation"), (F.sum("v").over(w) / F.sum("v").over(Window.partitionBy("i"))).alias("share"), F.first("v").over(w).alias("top"), F.cume_dist().over(w).alias("dist"))


@query(f"SELECT {_LONG} FROM {s.D4} ORDER BY i, j")
def sort_coo(spark, sf_dir):
    return mx.brand_nation(spark, sf_dir).orderBy("i", "j")


@query(f"SELECT {_LONG} FROM {s.D1} ORDER BY v DESC, i, j LIMIT 10")
def topk_entries(spark, sf_dir):
    return mx.part_supp(spark, sf_dir).orderBy(F.desc("v"), "i", "j").limit(10)


@query(f"SELECT {_LONG} FROM {s.D1} QUALIFY row_number() OVER (PARTITION BY i ORDER BY v DESC, j) <= 3")
def topk_per_row(spark, sf_dir):
    m = mx.part_supp(spark, sf_dir)
    return m.withColumn("r", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("v"), "j"))).where("r <= 3").drop("r")


#: Embeddings of a block of the nearest-neighbour search.
KNN_BLOCK = 500


@query("SELECT i, j FROM (SELECT CAST(a.i AS BIGINT) AS i, CAST(b.i AS BIGINT) AS j, row_number() OVER (PARTITION BY a.i ORDER BY round(SUM(a.v * b.v), 9) DESC, b.i) AS r FROM " + s.D3 + " a JOIN " + s.D3 + " b ON a.j = b.j WHERE a.i % 50 = 0 AND b.i <> a.i GROUP BY a.i, b.i) WHERE r <= 5")
def knn_gram(spark, sf_dir):
    """Five nearest embeddings by dot product of each embedding whose id is divisible by 50, among all: blocks of queries meet
    blocks of embeddings, and a pair's candidates are chosen inside tasks."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    blocks = lambda rows, width: rows.groupBy(F.floor(F.col("id") / width).alias("b")).agg(F.sort_array(F.collect_list(F.struct("id", "e"))).alias("v")).select("v")
    pairs = blocks(e.where("id % 50 = 0"), 50 * KNN_BLOCK).withColumnRenamed("v", "q").crossJoin(blocks(e, KNN_BLOCK))

    def nearest(batches):
        for batch in batches:
            for r in batch.to_pylist():
                (qi, q), (vi, v) = ((np.array([x["id"] for x in r[c]]), np.array([x["e"] for x in r[c]])) for c in ("q", "v"))
                d = np.round(q @ v.T, 9)
                d[qi[:, None] == vi[None, :]] = -np.inf
                top = np.argsort(-d, axis=1, kind="stable")[:, :5]  # v is in the order of ids, which settles ties
                best = np.take_along_axis(d, top, axis=1)
                there = best > -np.inf
                yield pa.RecordBatch.from_arrays([pa.array(np.broadcast_to(qi[:, None], top.shape)[there]), pa.array(vi[top][there]), pa.array(best[there])], ["i", "j", "d"])

    rows = pairs.mapInArrow(nearest, "i long, j long, d double")
    return rows.withColumn("r", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("d"), "j"))).where("r <= 5").select("i", "j")


@query(f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, SUM(v) AS v FROM (SELECT * FROM {_flag_sql('R')} UNION ALL SELECT * FROM {_flag_sql('N')}) GROUP BY 1, 2")
def set_union_sum(spark, sf_dir):
    return _flag(spark, sf_dir, "R").unionByName(_flag(spark, sf_dir, "N")).groupBy("i", "j").agg(F.sum("v").alias("v"))


@query(f"SELECT i, j FROM {_flag_sql('R')} INTERSECT SELECT i, j FROM {_flag_sql('N')}")
def set_intersect_pattern(spark, sf_dir):
    return _flag(spark, sf_dir, "R").select("i", "j").intersect(_flag(spark, sf_dir, "N").select("i", "j"))


@query(f"SELECT i, j FROM {_flag_sql('R')} EXCEPT ALL SELECT i, j FROM {_flag_sql('N')}")
def set_except_pattern(spark, sf_dir):
    return _flag(spark, sf_dir, "R").select("i", "j").exceptAll(_flag(spark, sf_dir, "N").select("i", "j"))


_TOK = "(SELECT doc_id, lang, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]{3,}')) AS token FROM documents)"


@query(f"SELECT token, count(*) AS n FROM {_TOK} GROUP BY token ORDER BY n DESC, token LIMIT 50")
def str_tokens(spark, sf_dir):
    return mx.tokens(table(spark, sf_dir, "documents")).groupBy("token").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "token").limit(50)


@query(f"SELECT {s.BRAND} AS b, count(*) AS n FROM part GROUP BY 1")
def str_brand_number(spark, sf_dir):
    return table(spark, sf_dir, "part").groupBy(mx.brand_number().alias("b")).agg(F.count("*").alias("n"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def str_page_host(spark, sf_dir):
    return table(spark, sf_dir, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("n"))


@query(f"""
WITH t AS (SELECT DISTINCT doc_id, token FROM {_TOK} WHERE length(token) >= 9), b AS (SELECT DISTINCT item_id, unnest(regexp_extract_all(lower(text), '[a-z]{{3,}}')) AS token FROM benchmark)
SELECT t.doc_id, b.item_id, count(*) AS shared FROM t JOIN b ON t.token = b.token GROUP BY 1, 2 HAVING count(*) >= 3""")
def doc_benchmark_overlap(spark, sf_dir):
    """Documents and items that share three long words or more, however many documents have them."""
    t = mx.tokens(table(spark, sf_dir, "documents")).where("length(token) >= 9").select("doc_id", "token").distinct()
    b = table(spark, sf_dir, "benchmark").select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]{3,}"), F.lit(0))).alias("bt")).distinct()
    return t.join(b, F.col("token") == F.col("bt")).groupBy("doc_id", "item_id").agg(F.count("*").alias("shared")).where("shared >= 3")


@query("SELECT conv_id, role, count(*) AS n FROM conversations GROUP BY 1, 2")
def conv_role_matrix(spark, sf_dir):
    return table(spark, sf_dir, "conversations").groupBy("conv_id", "role").agg(F.count("*").alias("n"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1")
def date_block_month(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy(F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(SUM(datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))) AS BIGINT) AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def date_ship_lag(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    rows = table(spark, sf_dir, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.sum(F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate"))).cast("long").alias("days"))


@query(f"WITH p AS {s.points()} SELECT CAST(a.pos AS BIGINT) AS i, CAST(b.pos AS BIGINT) AS j, round(sqrt(pow(a.px - b.px, 2) + pow(a.py - b.py, 2) + pow(a.pz - b.pz, 2)), 6) + 0.0 AS d, round(exp(-abs(a.pz - b.pz)), 6) AS e, CAST(sign(a.pz - b.pz) AS DOUBLE) AS g FROM p a JOIN p b ON b.pos BETWEEN a.pos + 1 AND a.pos + 3")
def math_kernel_terms(spark, sf_dir):
    from rankgrid.operators.blocking import ordering

    p = mx.positions(spark, sf_dir)
    o = ordering(p, "s", "key", ["region", "nation"], ["bal"]).select("pos", F.col("key").alias("k"))
    a = p.join(o, F.col("key") == F.col("k")).select("pos", "px", "py", "pz")
    b = a.select(F.explode(F.array(*[F.col("pos") - d for d in (1, 2, 3)])).alias("near"), F.col("pos").alias("j"), F.col("px").alias("qx"), F.col("py").alias("qy"), F.col("pz").alias("qz"))
    d = F.sqrt(F.pow(F.col("px") - F.col("qx"), 2) + F.pow(F.col("py") - F.col("qy"), 2) + F.pow(F.col("pz") - F.col("qz"), 2))
    return a.join(b, F.col("pos") == F.col("near")).select(F.col("pos").alias("i"), "j", (F.round(d, 6) + 0.0).alias("d"), F.round(F.exp(-F.abs(F.col("pz") - F.col("qz"))), 6).alias("e"), F.signum(F.col("pz") - F.col("qz")).alias("g"))


@query("SELECT a.i AS vec_id, round(SUM(a.v * b.v), 5) + 0.0 AS dot FROM " + s.D3 + " a JOIN " + s.D3 + " b ON a.j = b.j WHERE b.i = 0 GROUP BY 1")
def arr_dot(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    q = F.broadcast(e.where("vec_id = 0").select(F.col("e").alias("q")))
    return e.crossJoin(q).select("vec_id", (F.round(F.aggregate(F.zip_with("e", "q", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), 5) + 0.0).alias("dot"))


@query("SELECT i AS vec_id, round(SUM(v * v), 5) AS norm2 FROM " + s.D3 + " GROUP BY 1")
def arr_norm(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 5).alias("norm2"))


@query(f"SELECT i, j, v FROM {s.D3}")
def arr_explode(spark, sf_dir):
    return mx.embedding_entries(spark, sf_dir)


@query(f"SELECT CAST(nnz AS BIGINT) AS k, count(*) AS n FROM {_NNZ} GROUP BY 1")
def map_rank_hist(spark, sf_dir):
    """A histogram as one map, and flattened again."""
    h = _nnz(spark, sf_dir).groupBy("nnz").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("nnz", "n"))).alias("h"))
    return h.select(F.explode("h").alias("k", "n"))


@query("SELECT user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1, 2")
def json_props_matrix(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query(f"SELECT {s.BRAND} AS b, CAST(s_nationkey AS INTEGER) AS n, CAST(SUM(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2")
def dec_revenue_matrix(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey")).join(table(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.groupBy(mx.brand_number().alias("b"), F.col("s_nationkey").alias("n")).agg((F.sum(F.col("l_extendedprice").cast("decimal(18,2)")) * 100).cast("long").alias("cents"))


@query(s.product(s.t(s.D1), s.D1))
def sql_mm(spark, sf_dir):
    from rankgrid.sqlapi import register

    register(spark)
    mx.part_supp(spark, sf_dir).createOrReplaceTempView("rankgrid_a")
    return spark.sql("SELECT a.j AS i, b.j AS j, SUM(a.v * b.v) AS v FROM rankgrid_a a JOIN rankgrid_a b ON a.i = b.i GROUP BY a.j, b.j")


@query(f"WITH m AS {s.D4} SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(v * (SELECT 1 / CAST(MAX(r) AS DOUBLE) FROM (SELECT SUM(v) AS r FROM m GROUP BY i)), 9) AS v FROM m")
def sql_scalar_alpha(spark, sf_dir):
    mx.brand_nation(spark, sf_dir).createOrReplaceTempView("rankgrid_m")
    return spark.sql("WITH r AS (SELECT sum(v) AS r FROM rankgrid_m GROUP BY i) SELECT i, j, round(v * (SELECT 1 / max(r) FROM r), 9) AS v FROM rankgrid_m")


@query(f"WITH m AS {s.D1} SELECT DISTINCT i // 10 AS bi, j // 5 AS bj FROM m a WHERE EXISTS (SELECT 1 FROM m b WHERE b.i // 10 = a.i // 10 AND b.j // 5 = a.j // 5 AND b.v > 100)")
def sql_exists_block(spark, sf_dir):
    mx.part_supp(spark, sf_dir).createOrReplaceTempView("rankgrid_e")
    return spark.sql("SELECT DISTINCT i DIV 10 AS bi, j DIV 5 AS bj FROM rankgrid_e a WHERE EXISTS (SELECT 1 FROM rankgrid_e b WHERE b.i DIV 10 = a.i DIV 10 AND b.j DIV 5 = a.j DIV 5 AND b.v > 100)")


@query(f"SELECT {_LONG} FROM {s.D4} QUALIFY row_number() OVER (PARTITION BY i ORDER BY v DESC, j) <= 2")
def sql_lateral_topk(spark, sf_dir):
    mx.brand_nation(spark, sf_dir).createOrReplaceTempView("rankgrid_l")
    return spark.sql("SELECT t.i, x.j, x.v FROM (SELECT DISTINCT i FROM rankgrid_l) t, LATERAL (SELECT j, v FROM rankgrid_l l WHERE l.i = t.i ORDER BY v DESC, j LIMIT 2) x")


@query("SELECT CAST(c_nationkey AS INTEGER) AS nation, count(*) AS n FROM customer WHERE c_custkey % 10 = 0 GROUP BY 1")
def sample_rows(spark, sf_dir):
    return table(spark, sf_dir, "customer").where("pmod(c_custkey, 10) = 0").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("n"))


@query(f"SELECT lang, CAST(quality AS INTEGER) AS quality, count(*) AS n FROM {_TOK} t JOIN labels l ON t.doc_id = l.doc_id GROUP BY 1, 2")
def doc_quality_blocks(spark, sf_dir):
    lab = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("d"), F.col("quality").cast("int").alias("quality"))
    return mx.tokens(table(spark, sf_dir, "documents")).join(lab, F.col("doc_id") == F.col("d")).groupBy("lang", "quality").agg(F.count("*").alias("n"))


@query("SELECT i AS vec_id, round(sqrt(SUM(v * v)), 5) AS norm FROM " + s.D3 + " GROUP BY 1")
def udf_norm(spark, sf_dir):
    @F.pandas_udf("double")
    def norm(e: pd.Series) -> pd.Series:
        return e.map(lambda x: float(np.linalg.norm(np.asarray(x, dtype=np.float64))))

    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(norm("embedding"), 5).alias("norm"))


@query(f"SELECT CAST(i AS BIGINT) AS i, round(sqrt(SUM(v * v)), 4) AS fro FROM {s.D4} GROUP BY i")
def udaf_fro(spark, sf_dir):
    @F.pandas_udf("double")
    def fro(v: pd.Series) -> float:
        return float(np.sqrt((v * v).sum()))

    return mx.brand_nation(spark, sf_dir).groupBy("i").agg(fro("v").alias("fro")).select("i", F.round("fro", 4).alias("fro"))


@query(f"SELECT {_LONG} FROM {s.D4}")
def udtf_explode_block(spark, sf_dir):
    from rankgrid.sqlapi import register

    register(spark)
    m = d4(spark, sf_dir)
    m.blocks.createOrReplaceTempView("rankgrid_tiles")
    return spark.sql("SELECT b.bi * 5L + e.i AS i, b.bj * 5L + e.j AS j, e.v FROM rankgrid_tiles b, LATERAL explode_tile(b.m, b.n, b.repr, b.rank, b.x, b.w) e")


@query(f"SELECT a.pos AS a, b.pos AS b, round(exp(-((a.px - b.px) ** 2 + (a.py - b.py) ** 2 + (a.pz - b.pz) ** 2)), 6) + 0.0 AS v FROM {s.points()} a, {s.points()} b WHERE a.region = b.region")
def udtf_kernel_block(spark, sf_dir):
    """The kernel between the suppliers of each region, block by block."""
    from rankgrid.operators.blocking import ordering
    from rankgrid.sqlapi import register

    register(spark)
    p = mx.positions(spark, sf_dir)
    o = ordering(p, "points", "key", ["region", "nation"], ["bal"]).select(F.col("key").alias("okey"), "pos")
    placed = p.join(o, F.col("key") == F.col("okey"))
    blocks = placed.groupBy("region").agg(F.sort_array(F.collect_list(F.struct("pos", F.array("px", "py", "pz").alias("at")))).alias("p"))
    blocks.select(F.col("p.pos").alias("pos"), F.col("p.at").alias("points")).createOrReplaceTempView("rankgrid_blocks")
    return spark.sql("SELECT b.pos[k.i] AS a, b.pos[k.j] AS b, round(k.v, 6) + 0.0D AS v FROM rankgrid_blocks b, LATERAL kernel_block('decay', b.points, b.points) k")


@query("SELECT CAST(r AS INTEGER) AS wanted, CAST(r AS INTEGER) AS rank FROM (SELECT unnest([1, 2, 3]) AS r)")
def udf_lr_rank(spark, sf_dir):
    """The rank of blocks with one, two and three rows that differ, by the SQL function."""
    from rankgrid.sqlapi import register

    register(spark)
    rows = [(r, [float(i % r == j) for i in range(6) for j in range(4)]) for r in (1, 2, 3)]
    spark.createDataFrame(rows, "wanted int, block array<double>").createOrReplaceTempView("rankgrid_block_rows")
    return spark.sql("SELECT wanted, lr_rank(6, 4, block, 1e-9D) AS rank FROM rankgrid_block_rows")


@query(s.product(s.D4, s.t(s.D4)))
def cogroup_mm(spark, sf_dir):
    """Rows of tiles met in one task by a cogroup on the summed index, then reduced."""
    from rankgrid.operators.multiply import _PARTIAL, PARTIAL, reduce_partials
    from rankgrid.functions.tiles import multiply
    from rankgrid.schema import BlockMatrix, tile_row

    m = d4(spark, sf_dir)
    t = m.T

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        for a in left.to_pylist():
            for b in right.to_pylist():
                out.append({"k": a["bj"], **tile_row(a["bi"], b["bj"], multiply(read_tile(a), read_tile(b)))})
        return pa.Table.from_pylist(out, schema=_PARTIAL)

    parts = m.blocks.groupBy("bj").cogroup(t.blocks.groupBy("bi")).applyInArrow(meet, PARTIAL)
    return BlockMatrix(reduce_partials(parts), m.rows, m.rows).to_coo()


@query(f"WITH p AS ({s.product(s.t(s.D4), s.D4)}) SELECT CAST(i // 5 AS INTEGER) AS bi, CAST(j // 5 AS INTEGER) AS bj, round(sqrt(SUM(v * v)), 2) AS norm FROM p GROUP BY 1, 2")
def norm_table(spark, sf_dir):
    """Norms of a product's tiles, without its payload."""
    m = d4(spark, sf_dir)
    return mm_panels(m.T, m, Grid(2, 2), "all").norms().select("bi", "bj", F.round("norm", 2).alias("norm"))


