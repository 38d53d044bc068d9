"""Few entries in very large tables: an array of a tile's area would not fit into memory."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from rankgrid.operators import blocking
from rankgrid.schema import Axis

PARTS, SUPPLIERS = 1_600_000, 200_000

#: Queries over parts by suppliers, whose tiles are sixteenths by fifths: 32 GB each as arrays.
NAMES = [
    "active_grid",
    "blocks_roundtrip",
    "dag_sparse",
    "dcsc_columns",
    "mem_sparse",
    "plan_balance",
    "sched_balance",
    "sched_makespan",
    "sched_priority",
    "sink_blocks_roundtrip",
    "storage_ratio",
    "temp_c",
]


@pytest.fixture(scope="module")
def wide(spark, tmp_path_factory):
    d = tmp_path_factory.mktemp("wide")
    spark.range(PARTS).select(F.col("id").alias("p_partkey")).write.parquet(f"{d}/part.parquet")
    spark.range(SUPPLIERS).select(F.col("id").alias("s_suppkey")).write.parquet(f"{d}/supplier.parquet")
    i = F.col("id")
    lines = spark.range(900).select((i * 7919 * 211 % PARTS).alias("l_partkey"), (i * i * 1301 % SUPPLIERS).alias("l_suppkey"), (i % 50 * 4 + 1).cast("double").alias("l_quantity"))
    lines.union(lines.where("l_partkey % 3 = 0")).write.parquet(f"{d}/lineitem.parquet")
    return str(d)


@pytest.mark.parametrize("name", NAMES)
def test_tiles_of_a_large_area(spark, wide, name):
    from rankgrid import registry

    con = duckdb.connect()
    for t in ("part", "supplier", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{wide}/{t}.parquet/*.parquet')")
    df = registry.queries()[name](spark, wide)
    cols = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert sorted(map(tuple, df.select(*cols).collect())) == sorted(want) and want


def test_sparse_tiles_are_the_full_ones(spark):
    rows = [(i * 5 % 7, i * 3 % 11, float(i % 4)) for i in range(40)] + [(None, 1, 1.0), (1, None, 1.0), (1, 1, None)]
    e = spark.createDataFrame(rows, "i long, j long, v double")
    a, b = Axis.uniform(7, 3), Axis.uniform(11, 4)
    full, sparse = blocking.to_blocks(e, a, b), blocking.to_blocks(e, a, b, sparse=True)
    key = lambda df: sorted(map(tuple, df.collect()))
    for turn in (lambda m: m, lambda m: m.T):
        f, s = turn(full), turn(sparse)
        assert key(s.to_coo()) == key(f.to_coo())
        assert key(s.to_coo(drop_zeros=False)) == key(f.to_coo(drop_zeros=False))
        assert key(blocking.to_dcsc(s)) == key(blocking.to_dcsc(f))
        assert np.allclose(key(s.norms().drop("repr")), key(f.norms().drop("repr")))
        assert set(r["repr"] for r in s.norms().collect()) == {"S"}
    once = blocking.coo(e, "i", "j", F.col("v"))
    for got, want in ((blocking.skeleton(once, a, b), full), (blocking.skeleton(once, a, b).T, full.T)):
        assert np.allclose(key(got.norms().drop("repr")), key(want.norms().drop("repr")))
    nothing = blocking.to_blocks(e.where("false"), a, b, sparse=True)
    assert nothing.to_coo().count() == 0 and blocking.skeleton(e.where("false"), a, b).norms().count() == 0


def test_product_of_parts_in_many_tiles(spark, tmp_path):
    """Tiles of a product's operands have a bounded side, and are stored as entries."""
    from rankgrid.workloads.products import d1

    spark.range(32_000).select(F.col("id").alias("p_partkey")).write.parquet(f"{tmp_path}/part.parquet")
    spark.range(4_000).select(F.col("id").alias("s_suppkey")).write.parquet(f"{tmp_path}/supplier.parquet")
    spark.range(500).select((F.col("id") * 61).alias("l_partkey"), (F.col("id") % 97 * 41).alias("l_suppkey"), F.lit(2.0).alias("l_quantity")).write.parquet(f"{tmp_path}/lineitem.parquet")
    m = d1(spark, str(tmp_path), 512)
    assert max(m.rows.length(0), m.cols.length(0)) <= 512
    assert m.blocks.agg(F.sum(F.octet_length("x"))).first()[0] == 500 * 16

    from rankgrid import registry

    got = {(r["i"], r["j"]): r["v"] for r in registry.queries()["mm_multi_issue"](spark, str(tmp_path)).collect()}
    assert len(got) == 97 and all(i == j for i, j in got) and sum(got.values()) == 500 * 4


@pytest.mark.parametrize("name", ["blocks_roundtrip", "dcsc_columns", "sink_blocks_roundtrip"])
def test_no_task_holds_a_whole_tile(spark, wide, name, monkeypatch):
    from rankgrid import registry

    areas, make = [], blocking.to_blocks

    def seen(entries, rows, cols, sparse=False):
        areas.append(max(np.diff(rows.starts)) * max(np.diff(cols.starts)))
        return make(entries, rows, cols, sparse)

    monkeypatch.setattr(blocking, "to_blocks", seen)
    registry.queries()[name](spark, wide)
    assert areas and max(areas) <= 1 << 22


def test_strips_of_equal_blocks(spark):
    cut, rows = Axis.strips(23, 7, 3), Axis.uniform(5, 5)
    assert cut.starts == (0, 3, 6, 7, 10, 13, 14, 17, 20, 21, 23) and cut.strips_each == 3
    e = spark.createDataFrame([(k % 5, k, float(k + 1)) for k in range(23)], "i long, j long, v double")
    m = blocking.to_blocks(e, rows, cut, sparse=True)
    assert sorted(map(tuple, m.to_coo().collect())) == sorted(map(tuple, e.collect()))
    assert sorted({r["bj"] // cut.strips_each for r in m.norms().collect()}) == [0, 1, 2, 3]
