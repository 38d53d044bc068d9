"""Schedules of rounds on a grid, worked out from the cost of each process in each round: no product is computed here."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F




def task_costs(a: DataFrame, b: DataFrame, pr: int, pc: int, rounds: int) -> DataFrame:
    """k, p, cost: multiplications of process p in round k, zero where it has none; from norm tables with tile shapes."""
    left = a.groupBy(F.col("bj").alias("k"), F.pmod("bi", F.lit(pr)).alias("gr")).agg(F.sum("m").alias("rows"), F.max("n").alias("width"))
    right = b.groupBy(F.col("bi").alias("k2"), F.pmod("bj", F.lit(pc)).alias("gc")).agg(F.sum("n").alias("cols"))
    spark = a.sparkSession
    cells = spark.range(rounds).select(F.col("id").cast("int").alias("ck")).crossJoin(spark.range(pr * pc).select(F.col("id").cast("int").alias("p")))
    work = left.join(right, F.col("k") == F.col("k2")).select("k", (F.col("gr") * pc + F.col("gc")).alias("wp"), (F.col("rows") * F.col("width") * F.col("cols")).alias("work"))
    return cells.join(work, (F.col("ck") == F.col("k")) & (F.col("p") == F.col("wp")), "left").select(F.col("ck").alias("k"), "p", F.coalesce("work", F.lit(0)).cast("double").alias("cost"))


def makespan(costs: DataFrame, depth: int) -> DataFrame:
    """sync: a barrier after each round. waves: one after each `depth` rounds. decoupled: none. mean: total over processes."""
    rounds = costs.groupBy("k").agg(F.max("cost").alias("c")).agg(F.sum("c").alias("sync"))
    waves = costs.groupBy(F.floor(F.col("k") / depth).alias("w"), "p").agg(F.sum("cost").alias("c")).groupBy("w").agg(F.max("c").alias("c")).agg(F.sum("c").alias("waves"))
    free = costs.groupBy("p").agg(F.sum("cost").alias("c")).agg(F.max("c").alias("decoupled"), F.avg("c").alias("mean"))
    return rounds.crossJoin(waves).crossJoin(free)


def sliding_times(costs: DataFrame, depth: int) -> DataFrame:
    """k, p, start, finish with a window of `depth` rounds: round k starts when round k - depth has ended everywhere.

    One recursion over the rounds of one schedule; a schedule's table has rounds x processes rows.
    """

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        grid = rows.pivot(index="k", columns="p", values="cost").sort_index()
        ends, out = [], []
        free = dict.fromkeys(grid.columns, 0.0)
        for n, (k, row) in enumerate(grid.iterrows()):
            gate = max(ends[n - depth].values()) if n >= depth else 0.0
            now = {}
            for p, c in row.items():
                start = max(free[p], gate)
                now[p] = free[p] = start + c
                out.append((k, p, start, now[p]))
            ends.append(now)
        return pd.DataFrame(out, columns=["k", "p", "start", "finish"])

    return costs.withColumn("g", F.lit(0)).groupBy("g").applyInPandas(lambda rows: run(rows.drop(columns="g")), "k int, p int, start double, finish double")


def effective_depth(times: DataFrame) -> DataFrame:
    """Mean number of rounds that are under way at once, by the time between their first start and last end."""
    spans = times.where("finish > start").groupBy("k").agg(F.min("start").alias("s"), F.max("finish").alias("e"))
    return spans.agg((F.sum(F.col("e") - F.col("s")) / (F.max("e") - F.min("s"))).alias("effective_depth"))


def balance(costs: DataFrame, depths: list[int]) -> DataFrame:
    """depth, imbalance: largest over mean work in a wave of that many rounds, weighted by the wave's work."""
    d = F.explode(F.lit(depths)).alias("depth")
    per = costs.select("k", "p", "cost", d).groupBy("depth", F.floor(F.col("k") / F.col("depth")).alias("w"), "p").agg(F.sum("cost").alias("c"))
    waves = per.groupBy("depth", "w").agg(F.max("c").alias("top"), F.avg("c").alias("mean"))
    return waves.groupBy("depth").agg((F.sum("top") / F.sum("mean")).alias("imbalance"))


def count_barriers(rounds: int, depth: int, mode: str) -> int:
    return {"sync": rounds, "waves": math.ceil(rounds / depth), "sliding": 1, "decoupled": 1}[mode]


def broadcast_time(p: int, kind: str, chunks: int = 1) -> float:
    """Steps until all p processes have a panel of size one."""
    if kind in ("flat", "ring"):
        return p - 1
    if kind == "binomial":
        return math.ceil(math.log2(p)) if p > 1 else 0
    return (p + chunks - 2) / chunks if p > 1 else 0


def task_graph(spark: SparkSession, rounds: int, pr: int, pc: int, mode: str = "decoupled", depth: int = 1, a: DataFrame | None = None, b: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Nodes (id, kind, k, gr, gc) and edges (src, dst, kind) of the panel product: for each round a broadcast of a down
    each grid row and of b along each grid column, and an update on each process. Data edges lead from broadcasts to
    updates; in mode 'classical' each update also follows the last one of its process, and broadcasts wait for the
    updates of the round before (sequence edges). In mode 'waiting' broadcasts wait for the updates of the round that is
    depth before, so that no more than depth rounds are in flight.

    With the tiles (bi, bj) of both operands only those pieces of panels are sent that have a tile, and only those
    updates are there that have both.
    """
    k = spark.range(rounds).select(F.col("id").cast("int").alias("k"))
    r = spark.range(pr).select(F.col("id").cast("int").alias("gr"))
    c = spark.range(pc).select(F.col("id").cast("int").alias("gc"))
    name = lambda kind, *cols: F.concat_ws("-", F.lit(kind), *cols)
    none = F.lit(-1)
    sent_a = k.crossJoin(r) if a is None else a.select(F.col("bj").alias("k"), F.pmod("bi", F.lit(pr)).alias("gr")).distinct()
    sent_b = k.crossJoin(c) if b is None else b.select(F.col("bi").alias("k"), F.pmod("bj", F.lit(pc)).alias("gc")).distinct()
    ba = sent_a.select(name("a", "k", "gr").alias("id"), F.lit("bcast").alias("kind"), "k", "gr", none.alias("gc"))
    bb = sent_b.select(name("b", "k", "gc").alias("id"), F.lit("bcast").alias("kind"), "k", none.alias("gr"), "gc")
    both = sent_a.join(sent_b.withColumnRenamed("k", "k2"), F.col("k") == F.col("k2"))
    up = both.select(name("u", "k", "gr", "gc").alias("id"), F.lit("update").alias("kind"), "k", "gr", "gc")
    data = up.select(name("a", "k", "gr").alias("src"), F.col("id").alias("dst"), F.lit("data").alias("kind")).union(up.select(name("b", "k", "gc").alias("src"), F.col("id").alias("dst"), F.lit("data").alias("kind")))
    if mode == "classical":
        earlier = up.select((F.col("k") + 1).alias("k3"), F.col("gr").alias("gr3"), F.col("gc").alias("gc3"), F.col("id").alias("src"))
        data = data.union(up.join(earlier, (F.col("k") == F.col("k3")) & (F.col("gr") == F.col("gr3")) & (F.col("gc") == F.col("gc3"))).select("src", F.col("id").alias("dst"), F.lit("data").alias("kind")))
    if mode in ("classical", "waiting"):
        ahead = 1 if mode == "classical" else depth
        done = up.select((F.col("k") + ahead).alias("k3"), F.col("gr").alias("gr3"), F.col("gc").alias("gc3"), F.col("id").alias("src"))
        for sent, own in ((ba, "gr"), (bb, "gc")):
            data = data.union(sent.join(done, (F.col("k") == F.col("k3")) & (F.col(own) == F.col(f"{own}3"))).select("src", F.col("id").alias("dst"), F.lit("sequence").alias("kind")))
    return ba.union(bb).union(up), data


def release_order(a: DataFrame, b: DataFrame) -> DataFrame:
    """k, released, cost, rank: rounds by the numbers they free for each multiplication, most first, ties by k."""
    left = a.groupBy(F.col("bj").alias("k")).agg(F.sum("area").alias("x"), F.sum("m").alias("rows"), F.max("n").alias("width"))
    right = b.groupBy(F.col("bi").alias("k2")).agg(F.sum("area").alias("y"), F.sum("n").alias("cols"))
    both = left.join(right, F.col("k") == F.col("k2")).select("k", (F.col("x") + F.col("y")).alias("released"), (F.col("rows") * F.col("width") * F.col("cols")).alias("cost"))
    from pyspark.sql import Window

    return both.withColumn("rank", F.row_number().over(Window.orderBy(F.desc(F.col("released") / F.col("cost")), "k")))


