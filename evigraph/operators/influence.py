"""Influence of nodes for a batch of queries: personalised PageRank as joins and sums over the edge table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.operators import fixpoint
from evigraph.operators.kg import both_ways


def seed_vector(mapped: DataFrame, edges: DataFrame, norm: str = "sum") -> DataFrame:
    """qid, node_key, p from the end points of the kept facts."""
    ends = mapped.join(edges.select("edge_id", "src", "dst"), "edge_id").select("qid", F.explode(F.array("src", "dst")).alias("node_key")).distinct()
    return seeds_of(ends, norm)


def seeds_of(ends: DataFrame, norm: str = "sum") -> DataFrame:
    if norm == "none":
        return ends.select("qid", "node_key", F.lit(1.0).alias("p"))
    n = ends.groupBy("qid").agg(F.count("*").alias("n"))
    return ends.join(n, "qid").select("qid", "node_key", (1 / F.col("n")).alias("p"))


def weighted_edges(edges: DataFrame, flow: str = "push") -> DataFrame:
    """a, b, w: what b gets of a's score. ``push``: a's mass is split by its degree; ``pull``: b takes the mean of its neighbours."""
    d = both_ways(edges.select("src", "dst"))
    deg = d.groupBy("src").agg(F.count("*").alias("deg"))
    if flow == "push":
        return d.join(deg, "src").select(F.col("src").alias("a"), F.col("dst").alias("b"), (1 / F.col("deg")).alias("w"))
    return d.join(deg.withColumnRenamed("src", "dst"), "dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), (1 / F.col("deg")).alias("w"))


def power(edges: DataFrame, seeds: DataFrame, damping: float = 0.5, sweeps: int | None = None, tol: float = 1e-7, flow: str = "push") -> DataFrame:
    """qid, node_key, score. Only nodes with mass are kept, so a query's rows grow with what it reaches.

    The number of sweeps is fixed, or bounded by log(tol) / log(damping) with a test of the largest change every fourth round. The edge
    table is written with its weights once, and each round shuffles scores and partial sums only.
    """
    from math import ceil, log

    from evigraph.runtime import written

    w = written(weighted_edges(edges, flow).repartition("a"), "weights")
    base = seeds.select("qid", F.col("node_key").alias("b"), ((1 - damping) * F.col("p")).alias("x"))
    most = sweeps if sweeps is not None else ceil(log(tol) / log(damping)) + 1

    def step(s: DataFrame, _: int) -> DataFrame:
        moved = s.join(w, s["node_key"] == w["a"]).select("qid", "b", (damping * F.col("score") * F.col("w")).alias("x"))
        return moved.unionByName(base).groupBy("qid", "b").agg(F.sum("x").alias("score")).withColumnRenamed("b", "node_key")

    def settled(old: DataFrame, new: DataFrame) -> bool:
        o = old.withColumnRenamed("score", "o")
        far = new.join(o, ["qid", "node_key"], "full").where(F.abs(F.coalesce("score", F.lit(0.0)) - F.coalesce("o", F.lit(0.0))) >= tol * 4)
        return far.isEmpty()

    start = seeds.select("qid", "node_key", F.col("p").alias("score"))
    return fixpoint.run(start, step, most, None if sweeps is not None else settled)[0]


def uniform(edges: DataFrame, nodes: DataFrame, seeds: DataFrame, damping: float = 0.5, sweeps: int = 32) -> DataFrame:
    """The printed transition, with 1 / V on every pair that isn't an edge, at the cost of two right-hand sides and two sums.

    With B = 1/degree - 1/V on edges, x solves (I - dB) x = (1 - d) p and y solves (I - dB) y = 1; the scores are x + y * k, where
    k = (d / V) * sum(x) / (1 - (d / V) * sum(y)).
    """
    from evigraph.runtime import written

    v = nodes.agg(F.count("*").alias("v"))  # one row
    w = weighted_edges(edges, "pull").join(F.broadcast(v)).select("a", "b", (F.col("w") - 1 / F.col("v")).alias("w"))
    w = written(w.repartition("a"), "weights")

    def solve(rhs: DataFrame) -> DataFrame:
        base = rhs.select("qid", F.col("node_key").alias("b"), "x")

        def step(s: DataFrame, _: int) -> DataFrame:
            moved = s.join(w, s["node_key"] == w["a"]).select("qid", "b", (damping * F.col("score") * F.col("w")).alias("x"))
            return moved.unionByName(base).groupBy("qid", "b").agg(F.sum("x").alias("score")).withColumnRenamed("b", "node_key")

        return fixpoint.run(rhs.select("qid", "node_key", F.col("x").alias("score")), step, sweeps)[0]

    x = solve(seeds.select("qid", "node_key", ((1 - damping) * F.col("p")).alias("x")))
    y = solve(nodes.select(F.lit(-1).cast("long").alias("qid"), "node_key", F.lit(1.0).alias("x"))).select("node_key", F.col("score").alias("y"))
    sy = y.agg(F.sum("y").alias("sy"))
    k = x.groupBy("qid").agg(F.sum("score").alias("sx")).join(F.broadcast(sy)).join(F.broadcast(v)).select("qid", (damping / F.col("v") * F.col("sx") / (1 - damping / F.col("v") * F.col("sy"))).alias("k"))
    every = y.join(F.broadcast(k))  # each query scores every node: that is what the printed form asks for
    return every.join(x, ["qid", "node_key"], "left").select("qid", "node_key", (F.coalesce("score", F.lit(0.0)) + F.col("y") * F.col("k")).alias("score"))


def push_frontier(edges: DataFrame, seeds: DataFrame, damping: float = 0.5, eps: float = 1e-4) -> DataFrame:
    """Forward push by rounds: all nodes whose residual exceeds eps * degree push at once; joins touch the frontier only."""
    from evigraph.runtime import written

    d = both_ways(edges.select("src", "dst"))
    adj = written(d.join(d.groupBy("src").agg(F.count("*").alias("deg")), "src").repartition("src"), "adjacency")
    deg = adj.select("src", "deg").distinct()
    state = written(seeds.join(deg, F.col("node_key") == F.col("src"), "left").select("qid", "node_key", F.coalesce("deg", F.lit(1)).alias("deg"), F.lit(0.0).alias("score"), F.col("p").alias("res")), "push")
    while True:  # ends: a push leaves at most the damped share of what it moves
        hot = F.col("res") > eps * F.col("deg")
        if state.where(hot).isEmpty():
            break
        spread = state.where(hot).drop("deg").join(adj, F.col("node_key") == F.col("src")).select("qid", F.col("dst").alias("node_key"), F.lit(0.0).alias("score"), (damping * F.col("res") / F.col("deg")).alias("res"))
        stay = state.select("qid", "node_key", F.when(hot, F.col("score") + (1 - damping) * F.col("res")).otherwise(F.col("score")).alias("score"), F.when(hot, 0.0).otherwise(F.col("res")).alias("res"))
        total = stay.unionByName(spread).groupBy("qid", "node_key").agg(F.sum("score").alias("score"), F.sum("res").alias("res"))
        state = written(total.join(deg, F.col("node_key") == F.col("src"), "left").select("qid", "node_key", F.coalesce("deg", F.lit(1)).alias("deg"), "score", "res"), "push")
    return state.select("qid", "node_key", "score")


def balance(scores: DataFrame, factor: float = 0.05) -> DataFrame:
    return scores.withColumn("score", F.when(F.col("node_key").startswith("p:"), F.col("score") * factor).otherwise(F.col("score")))
