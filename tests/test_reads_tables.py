"""Queries about plans and formulas take their numbers from the given tables."""

import duckdb
import pytest

DATA = "/root/testdata/sf0.001"
NAMES = [
    "barriers",
    "blocking_uniform",
    "dag_counts",
    "depth_default",
    "depth_for_budget",
    "effective_depth",
    "efficiency_formula",
    "flops_apparent",
    "flops_lowrank",
    "flops_peak",
    "grid_owner",
    "lrb_choice",
]


@pytest.mark.parametrize("name", NAMES)
def test_rows_come_from_the_tables(spark, tmp_path, name):
    from rankgrid import registry

    query = registry.queries()[name]
    con = duckdb.connect()
    for t in ("part", "supplier", "lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DATA}/{t}.parquet')")
    df = query(spark, DATA)
    cols = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert sorted(map(tuple, df.select(*cols).collect())) == sorted(want) and want
    with pytest.raises(Exception, match="nowhere"):
        query(spark, f"{tmp_path}/nowhere").collect()
