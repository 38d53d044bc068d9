"""The registries: names match, and a few queries against DuckDB on the smallest tables."""

import math
import os
import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(df):
    return sorted(tuple("nan" if isinstance(v, float) and math.isnan(v) else (float(v) if isinstance(v, float) else str(v)) for v in r) for r in df)


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DATA}/{t}.parquet')")
    return con


def test_every_sql_has_a_query():
    from rankgrid import registry

    assert set(registry.oracle_sql()) <= set(registry.queries())
    assert len(registry.queries()) > 150


@pytest.mark.parametrize("name", ["mm_multi_issue", "mm_split", "lincomb", "screen_product", "comm_volume", "dag_counts", "join_theta_pairs", "win_range_time", "stream_watermark", "w5_depth"])
def test_against_sql(spark, db, name):
    from rankgrid import registry

    df = registry.queries()[name](spark, DATA)
    cols = sorted(df.columns)
    got = rows(df.select(*cols).collect())
    want = db.execute(f"SELECT {', '.join(cols)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert got == rows(want)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0


@pytest.mark.parametrize("pipeline", [True, False])
def test_the_rest_works_without_the_training_data_package(tmp_path, pipeline):
    """Both folders of it are gone, with or without the pipeline's file left in place."""
    root, copy = Path(__file__).resolve().parent.parent, tmp_path / "r"
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse", ".pytest_cache"))
    for gone in ("rankgrid/llm", "tests/llm"):
        shutil.rmtree(copy / gone, ignore_errors=True)
    if not pipeline:
        (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'mm_split' in q and 'pipeline' not in q and not any(k.startswith('op1') for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env={**os.environ, "PYTHONPATH": str(copy)})
