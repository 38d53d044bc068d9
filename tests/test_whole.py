"""Queries over whole tables against brute force and against their SQL, which takes whole tables too."""

import collections
import re

import duckdb
import numpy as np
import pyarrow.parquet as pq
import pytest

from rankgrid import registry
from rankgrid.workloads import fragments as s

DATA, LARGER = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def read(name, data=DATA):
    return pq.read_table(f"{data}/{name}.parquet")


def run(spark, name, data=DATA):
    df = registry.queries()[name](spark, data)
    return [tuple(r) for r in df.select(*sorted(df.columns)).collect()]


def sql(text, cols, data=DATA):
    con = duckdb.connect()
    for t in ("lineitem", "orders", "part", "supplier", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{data}/{t}.parquet')")
    return con.execute(f"SELECT {', '.join(cols)} FROM ({text})").fetchall()


@pytest.mark.parametrize("name", ["mm_rect", "join_merge", "join_hash"])
def test_every_customer(spark, name):
    got = run(spark, name)
    assert max(r[0] for r in got) >= 50
    assert sorted(got) == sorted(sql(registry.oracle_sql()[name], "ijv"))


def test_spgemm_has_every_customer(spark):
    got = [r[:2] + r[2:3] for r in ((i, j, v) for i, j, v, what in run(spark, "w12_spgemm") if what == "customer_supplier")]
    assert sorted(got) == sorted(sql(s.product(s.D2, s.D1), "ijv"))


@pytest.mark.parametrize("name", ["mm_abt_embeddings", "triangle_upper"])
def test_every_vector(spark, name):
    e = read("embeddings").sort_by("vec_id")
    x = np.array(e["embedding"].to_pylist(), np.float64)
    gram = x @ x.T
    got = run(spark, name)
    n = len(x)
    assert len(got) == (n * n if name == "mm_abt_embeddings" else n * (n + 1) // 2)
    assert all(abs(v - gram[i, j]) < 2e-6 for i, j, v in got)


def test_every_part(spark):
    lines, supp = read("lineitem", LARGER), read("supplier", LARGER)
    nation = dict(zip(supp["s_suppkey"].to_pylist(), supp["s_nationkey"].to_pylist(), strict=True))
    there = {(p, nation[k]) for p, k in zip(lines["l_partkey"].to_pylist(), lines["l_suppkey"].to_pylist(), strict=True)}
    want = {(p, n) for p in read("part", LARGER)["p_partkey"].to_pylist() for n in set(nation.values())} - there
    got = run(spark, "join_anti_absent", LARGER)
    assert len(got) == len(want)
    assert {(p, n) for n, p in got} == want


def test_words_of_many_documents_count(spark, tmp_path):
    docs = [(k, "en", "remarkable telescopes everywhere" if k < 230 else "remarkable telescopes") for k in range(240)]
    spark.createDataFrame(docs, "doc_id long, lang string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, "Remarkable telescopes, everywhere"), (2, "something else")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    words = lambda t: {w for w in re.findall("[a-z]{3,}", t.lower()) if len(w) >= 9}
    got = run(spark, "doc_benchmark_overlap", str(tmp_path))
    assert collections.Counter(got) == collections.Counter((d, 1, 3) for d, _, t in docs if len(words(t)) == 3)


def test_every_fiftieth_vector_is_a_query(spark):
    e = read("embeddings").sort_by("vec_id")
    x = np.array(e["embedding"].to_pylist(), np.float64)
    d = np.round(x @ x.T, 9)
    np.fill_diagonal(d, -np.inf)
    want = {(i, int(j)) for i in range(0, len(x), 50) for j in np.argsort(-d[i], kind="stable")[:5]}
    got = run(spark, "knn_gram")
    assert len(got) == len(want)
    assert set(got) == want
    assert sorted(got) == sorted(sql(registry.oracle_sql()["knn_gram"], "ij"))


def test_no_pair_of_entries_is_a_row(spark):
    """The triangle comes from products of tiles: entries are not joined with entries."""
    plan = registry.queries()["triangle_upper"](spark, DATA)._jdf.queryExecution().analyzed().toString()
    assert "v2" not in plan and "MapInArrow" in plan
