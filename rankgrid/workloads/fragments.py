"""SQL that several oracles share."""

D1 = "(SELECT l_partkey AS i, l_suppkey AS j, SUM(l_quantity) AS v FROM lineitem GROUP BY 1, 2)"
D2 = "(SELECT o_custkey AS i, l_partkey AS j, SUM(l_quantity) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)"
BRAND = r"CAST(regexp_extract(p_brand, '(\d+)', 1) AS BIGINT) - 1"
D4 = f"(SELECT {BRAND} AS i, CAST(s_nationkey AS BIGINT) AS j, SUM(l_quantity) AS v FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2)"
D3 = "(SELECT vec_id AS i, CAST(k AS BIGINT) - 1 AS j, CAST(embedding[k] AS DOUBLE) AS v FROM embeddings, (SELECT unnest(range(1, 65)) AS k))"


def t(m: str) -> str:
    return f"(SELECT j AS i, i AS j, v FROM {m})"


def product(a: str, b: str, scale: str = "") -> str:
    return f"SELECT CAST(a.i AS BIGINT) AS i, CAST(b.j AS BIGINT) AS j, CAST({scale}SUM(a.v * b.v) AS DOUBLE) AS v FROM {a} a JOIN {b} b ON a.j = b.i GROUP BY a.i, b.j"


def dense(n: int, seed: int = 0) -> str:
    return f"(SELECT i, j, CAST((i * 31 + j * 17 + i * j * 7 + {seed}) % 17 - 8 AS DOUBLE) AS v FROM (SELECT unnest(range({n})) AS i) x, (SELECT unnest(range({n})) AS j) y)"


def nonzero(sql: str) -> str:
    return f"SELECT * FROM ({sql}) WHERE v <> 0"


#: Points of suppliers (or customers) with their place in the natural order: region, nation, balance, key.
def points(of: str = "supplier", where: str = "") -> str:
    p, key = of[0], {"supplier": "s_suppkey", "customer": "c_custkey"}[of]
    return f"""(SELECT row_number() OVER (ORDER BY n_regionkey, n_nationkey, {p}_acctbal, {key}) - 1 AS pos, n_nationkey AS nation, n_regionkey AS region,
  3.0 * n_regionkey AS px, 3.0 * floor(n_nationkey / 5) AS py, {p}_acctbal / 1000 AS pz FROM {of} JOIN nation ON {p}_nationkey = n_nationkey {where})"""


def kernel(kind: str, of: str = "supplier") -> str:
    d2 = "(a.px - b.px) * (a.px - b.px) + (a.py - b.py) * (a.py - b.py) + (a.pz - b.pz) * (a.pz - b.pz)"
    f = f"exp(-({d2}))" if kind == "decay" else f"1 / sqrt(1 + {d2})"
    return f"(SELECT CAST(a.pos AS BIGINT) AS i, CAST(b.pos AS BIGINT) AS j, CAST({f} + CASE WHEN a.pos = b.pos THEN 1 ELSE 0 END AS DOUBLE) AS v, a.nation AS bi, b.nation AS bj FROM {points(of)} a, {points(of)} b)"
