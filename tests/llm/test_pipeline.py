"""The pipeline stage by stage on a small table with planted cases, and the guard of the entry file."""

import subprocess
import sys
from pathlib import Path

import pytest

from tests.llm.test_operators import prose

ROOT = Path(__file__).resolve().parent.parent.parent


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    d = tmp_path_factory.mktemp("sf")
    item = prose(77, 40)
    near = prose(1001, 80).split()
    near[40] = "other"
    rows, labels = [], []
    for k in range(120):
        junk = k % 5 == 0
        rows.append((k, "\n".join("| $$ ## ** " * 15 for _ in range(4)) + str(k) if junk else prose(k + 1000, 80) + ".", "en", "s", 1))
        labels.append((k, int(not junk), 0))
    rows += [(200, prose(1001, 80) + " .", "en", "s", 1), (201, " ".join(near) + ".", "en", "s", 1), (202, prose(5, 30) + " " + item + " " + prose(6, 30), "en", "s", 1), (203, None, None, None, None), (204, "", "en", "s", 0)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(d / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(str(d / "labels.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(d / "benchmark.parquet"))
    return str(d)


def test_stages(spark, folder):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns, ids = docs.columns, {r["doc_id"] for r in docs.collect()}
    for name, stage in p.STAGES[:-1]:
        docs = stage(spark, docs, folder).cache()
        assert docs.columns == columns, name
        left = {r["doc_id"] for r in docs.collect()}
        gone, ids = ids - left, left
        if name == "quality":
            assert {k for k in range(0, 120, 5)} <= gone
            assert len([k for k in gone if k < 120 and k % 5]) <= 2
        elif name == "exact_dedup":
            assert len(gone & {1, 200}) == 1
        elif name == "near_dedup":
            assert 201 in gone
        else:
            assert gone == {202}
    pieces = p.STAGES[-1][1](spark, docs, folder).collect()
    assert {r["doc_id"] for r in pieces} == ids


def test_run_and_empty_table(spark, folder, tmp_path):
    import corpus_pipeline as p

    assert p.run(spark, folder).count() > 0
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{folder}/{t}.parquet").write.parquet(str(tmp_path / f"{t}.parquet"))
    spark.read.parquet(f"{folder}/documents.parquet").limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert p.run(spark, str(tmp_path)).count() == 0


def test_the_rest_works_without_this_package(tmp_path):
    import shutil

    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    shutil.rmtree(tmp_path / "r/rankgrid/llm")
    (tmp_path / "r/corpus_pipeline.py").unlink()
    code = "import __spark_entry__ as e; q = e.queries(); assert 'mm_split' in q and 'pipeline' not in q and not any(k.startswith('op1') for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path / "r"), "JAVA_HOME": ""})
