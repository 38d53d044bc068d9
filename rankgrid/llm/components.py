"""Connected components of a table of links, by alternating stars; nothing is gathered on the driver but two counts a round."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.skew import left_join
from rankgrid.llm.textblocks import map_arrow
from rankgrid.session import written

#: Links up to which one task settles all of them (4 MB); the rounds' plans would take the driver more memory than that.
FEW = 1 << 18


def _tally(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40))).alias("h")).first()
    return r["n"], r["h"] or 0


def settled(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes that are not the smallest of their component, and the smallest one of each: roots are hung under smaller roots
    that they have a link to, and all paths are cut short, until no link joins two roots."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            break
        a, b = a[apart], b[apart]
        np.minimum.at(root, np.maximum(x, y)[apart], np.minimum(x, y)[apart])
        while not np.array_equal(root, nearer := root[root]):
            root = nearer
    hung = root != np.arange(len(nodes))
    return nodes[hung], nodes[root[hung]]


def _in_one_task(edges: DataFrame) -> DataFrame:
    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(b.column("u").to_numpy(), b.column("v").to_numpy()) for b in batches if b.num_rows]
        if parts:
            node, component = settled(*(np.concatenate(x) for x in zip(*parts, strict=True)))
            yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(component, pa.int64())], ["node", "component"])

    return written(map_arrow(edges.coalesce(1), each, "node long, component long"), "components")


def components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """node, component (the smallest node that can be reached) for every node of a link that is not itself the smallest.

    Each round hangs the larger neighbours of a node, then the smaller ones, under the smallest node it sees, until
    every component is a star. Rounds grow with the logarithm of the longest path. Up to FEW links are settled in one task.
    """
    edges = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    edges = written(edges, "star_edges")
    tally = _tally(edges)
    if tally[0] <= FEW:
        return _in_one_task(edges)
    for _ in range(max_rounds):
        if not tally[0]:
            break
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # a node with a large share of all links must not bring them into one task: its minimum is broadcast
        total = 2 * tally[0]
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select(F.col("u").alias("w"), F.least("u", "m").alias("m"), "n")
        large = left_join(both.where("v > u"), least, {"u": "w"}, ["m"], "n", total, F.xxhash64("v")).select(F.col("v").alias("u"), F.col("m").alias("v")).union(edges.groupBy("u").agg(F.min("v").alias("v"))).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select(F.col("u").alias("w"), "m", "n")
        hung = left_join(large, low, {"u": "w"}, ["m"], "n", total, F.xxhash64("v")).where("v <> m")
        small = hung.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select(F.col("w").alias("u"), F.col("m").alias("v"))).distinct()
        edges = written(small, "star_edges")
        now = _tally(edges)
        if now == tally:
            break
        tally = now
    else:
        raise RuntimeError(f"components: not settled after {max_rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
