"""Trees over terminals and frozen growth as joins, for graphs beyond one machine."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.functions.graphs import LocalGraph
from evigraph.runtime import written


def _directed(costs: DataFrame) -> DataFrame:
    """qid, a, b, edge_id, cost in both directions; the cheapest of parallel edges carries a path."""
    back = costs.select("qid", F.col("dst").alias("a"), F.col("src").alias("b"), "edge_id", "cost")
    both = costs.select("qid", F.col("src").alias("a"), F.col("dst").alias("b"), "edge_id", "cost").unionByName(back).where("a <> b")
    return both.groupBy("qid", "a", "b").agg(F.min(F.struct("cost", "edge_id")).alias("m")).select("qid", "a", "b", "m.edge_id", "m.cost")


def regions(costs: DataFrame, terminals: DataFrame) -> DataFrame:
    """qid, node, dist, owner, via, up: nearest terminal of every node that one reaches, the edge and node towards it.

    Relaxation from all terminals at once: the rows that improved in the last round meet their edges; each node keeps its
    least (distance, owner, edge). Ends when nothing improves.
    """
    d = written(_directed(costs).repartition("qid", "a"), "directed")
    best = written(terminals.select("qid", F.col("node_key").alias("node"), F.lit(0.0).alias("dist"), F.col("node_key").alias("owner"), F.lit(None).cast("string").alias("via"), F.lit(None).cast("string").alias("up")), "regions")
    front = best
    while True:
        met = front.join(d, (front["qid"] == d["qid"]) & (front["node"] == d["a"])).select(front["qid"], F.col("b").alias("node"), F.round(F.col("dist") + F.col("cost"), 12).alias("dist"), "owner", F.col("edge_id").alias("via"), F.col("a").alias("up"))
        offer = met.groupBy("qid", "node").agg(F.min(F.struct("dist", "owner", "via", "up")).alias("m")).select("qid", "node", "m.*")
        old = best.select("qid", "node", F.col("dist").alias("od"), F.col("owner").alias("oo"))
        front = written(offer.join(old, ["qid", "node"], "left").where("od is null or dist < od or (dist = od and owner < oo)").drop("od", "oo"), "front")
        if front.isEmpty():
            return best
        best = written(best.join(front.select("qid", "node"), ["qid", "node"], "left_anti").unionByName(front), "regions")


def boundary(costs: DataFrame, region: DataFrame) -> DataFrame:
    """qid, t1, t2, edge_id, src, dst, weight: the cheapest crossing between each two regions."""
    r = region.select("qid", "node", "dist", "owner")
    a = r.select("qid", F.col("node").alias("src"), F.col("dist").alias("d1"), F.col("owner").alias("o1"))
    b = r.select("qid", F.col("node").alias("dst"), F.col("dist").alias("d2"), F.col("owner").alias("o2"))
    met = costs.join(a, ["qid", "src"]).join(b, ["qid", "dst"]).where("o1 <> o2")
    w = F.round(F.col("d1") + F.col("cost") + F.col("d2"), 12)
    pick = met.select("qid", F.least("o1", "o2").alias("t1"), F.greatest("o1", "o2").alias("t2"), F.struct(w.alias("weight"), "edge_id", "src", "dst").alias("m"))
    return pick.groupBy("qid", "t1", "t2").agg(F.min("m").alias("m")).select("qid", "t1", "t2", "m.edge_id", "m.src", "m.dst", "m.weight")


def spanning_crossings(crossings: DataFrame) -> DataFrame:
    """The crossings of a least spanning forest over terminals, by query; at most T * T rows a query."""

    def kruskal(pdf: pd.DataFrame) -> pd.DataFrame:
        root: dict[str, str] = {}

        def find(x: str) -> str:
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        keep = []
        for r in pdf.sort_values(["weight", "t1", "t2"]).itertuples():
            a, b = find(r.t1), find(r.t2)
            if a != b:
                root[a] = b
                keep.append(r.Index)
        return pdf.loc[keep]

    return crossings.groupBy("qid").applyInPandas(kruskal, crossings.schema)


def tree_edges(crossings: DataFrame, region: DataFrame, terminals: DataFrame, costs: DataFrame) -> DataFrame:
    """qid, edge_id of the tree: crossings, and the paths from their ends back to their terminals, walked by all at once."""
    edges = crossings.select("qid", "edge_id")
    walk = crossings.select("qid", F.explode(F.array("src", "dst")).alias("node")).distinct()
    seen = written(walk, "walk")
    out = written(edges, "tree")
    while True:
        nxt = seen.join(region.where("up is not null"), ["qid", "node"]).select("qid", F.col("via").alias("edge_id"), F.col("up").alias("node"))
        nxt = written(nxt, "walk")
        if nxt.isEmpty():
            break
        out = written(out.unionByName(nxt.select("qid", "edge_id")).distinct(), "tree")
        seen = nxt.select("qid", "node").distinct()
    return prune(out, terminals, costs)


def prune(tree: DataFrame, terminals: DataFrame, costs: DataFrame) -> DataFrame:
    """Leaves that aren't terminals go, by query; a tree is as small as its terminals' paths."""
    rows = tree.join(costs.select("qid", "edge_id", "src", "dst", "cost"), ["qid", "edge_id"]).withColumn("kind", F.lit("edge"))
    t = terminals.select("qid", F.lit("").alias("edge_id"), F.col("node_key").alias("src"), F.lit("").alias("dst"), F.lit(0.0).alias("cost"), F.lit("terminal").alias("kind"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        e = pdf[pdf["kind"] == "edge"].reset_index(drop=True)
        names = sorted({*e["src"], *e["dst"], *pdf.loc[pdf["kind"] == "terminal", "src"]})
        no = {x: i for i, x in enumerate(names)}
        g = LocalGraph(len(names), np.array([[no[a], no[b]] for a, b in zip(e["src"], e["dst"])]).reshape(-1, 2))
        keep = g.pruned(g.spanning(range(len(e)), e["cost"].to_numpy()), [no[x] for x in pdf.loc[pdf["kind"] == "terminal", "src"]])
        return e.loc[keep, ["qid", "edge_id"]]

    return rows.unionByName(t).groupBy("qid").applyInPandas(run, "qid long, edge_id string")


def steiner_tree(costs: DataFrame, terminals: DataFrame) -> DataFrame:
    region = regions(costs, terminals)
    return tree_edges(spanning_crossings(boundary(costs, region)), region, terminals, costs)


def subgraph_ratio(edges: DataFrame, costs: DataFrame, scores: DataFrame, kind: str = "sum") -> DataFrame:
    """qid, ratio of a subgraph: sum or mean of cost / (s_u + s_v), or all cost over all score (pooled)."""
    e = edges.join(costs.select("qid", "edge_id", "src", "dst", "cost"), ["qid", "edge_id"])
    s = scores.select("qid", "node_key", "score")
    if kind == "pooled":
        n = e.select("qid", F.explode(F.array("src", "dst")).alias("node_key")).distinct().join(s, ["qid", "node_key"]).groupBy("qid").agg(F.sum("score").alias("s"))
        return e.groupBy("qid").agg(F.sum("cost").alias("c")).join(n, "qid").select("qid", (F.col("c") / F.nullif("s", F.lit(0.0))).alias("ratio"))
    a, b = (s.select("qid", F.col("node_key").alias(k), F.col("score").alias(f"s{k}")) for k in ("src", "dst"))
    both = e.join(a, ["qid", "src"], "left").join(b, ["qid", "dst"], "left")
    term = F.col("cost") / F.nullif(F.coalesce("ssrc", F.lit(0.0)) + F.coalesce("sdst", F.lit(0.0)), F.lit(0.0))
    return both.groupBy("qid").agg((F.sum if kind == "sum" else F.avg)(term).alias("ratio"))


def grow_frozen(tree: DataFrame, terminals: DataFrame, costs: DataFrame, scores: DataFrame, counted: DataFrame | None = None, base: str = "sum") -> DataFrame:
    """qid, edge_id, step of growth under the tree's own ratio, which is independent of order.

    A step goes from a node inside over an edge to v where cost / s_v is under the ratio; at the end every edge between reached nodes whose
    cost over the larger score is under it belongs too. So it is a breadth-first search over filtered edges. ``counted``: the part of the tree
    that sets the ratio; ``base``: sum, mean or pooled.
    """
    limit = subgraph_ratio(tree if counted is None else counted, costs, scores, base).withColumnRenamed("ratio", "r")
    s = scores.select("qid", F.col("node_key").alias("b"), F.col("score").alias("sb"))
    d = costs.select("qid", F.col("src").alias("a"), F.col("dst").alias("b"), "edge_id", "cost").unionByName(costs.select("qid", F.col("dst").alias("a"), F.col("src").alias("b"), "edge_id", "cost")).where("a <> b")
    omega = written(d.join(s, ["qid", "b"]).join(limit, "qid").where("sb > 0 and cost / sb < r").select("qid", "a", "b", "edge_id"), "omega")
    ends = tree.join(costs.select("qid", "edge_id", "src", "dst"), ["qid", "edge_id"]).select("qid", F.explode(F.array("src", "dst")).alias("node"))
    reached = written(ends.unionByName(terminals.select("qid", F.col("node_key").alias("node"))).distinct().withColumn("step", F.lit(0)), "reached")
    front = reached
    i = 0
    while True:
        i += 1
        new = front.join(omega, (front["qid"] == omega["qid"]) & (front["node"] == omega["a"])).select(front["qid"], F.col("b").alias("node")).distinct()
        front = written(new.join(reached.select("qid", "node"), ["qid", "node"], "left_anti").withColumn("step", F.lit(i)), "front")
        if front.isEmpty():
            break
        reached = written(reached.unionByName(front), "reached")
    a = reached.select("qid", F.col("node").alias("a"), F.col("step").alias("sa"))
    b = reached.select("qid", F.col("node").alias("b"), F.col("step").alias("sb"))
    inner = omega.join(a, ["qid", "a"]).join(b, ["qid", "b"]).groupBy("qid", "edge_id").agg(F.min(F.greatest("sa", "sb")).alias("step"))
    return inner.join(tree.select("qid", "edge_id"), ["qid", "edge_id"], "left_anti")


def check_reach(edges: DataFrame, terminals: DataFrame, costs: DataFrame) -> DataFrame:
    """qid, terminals, reached: how many terminals the least one reaches over the subgraph's edges."""
    d = edges.join(costs.select("qid", "edge_id", "src", "dst"), ["qid", "edge_id"])
    d = written(d.select("qid", F.col("src").alias("a"), F.col("dst").alias("b")).unionByName(d.select("qid", F.col("dst").alias("a"), F.col("src").alias("b"))).distinct(), "adjacency")
    seen = written(terminals.groupBy("qid").agg(F.min("node_key").alias("node")), "reach")
    front = seen
    while True:
        new = front.join(d, (front["qid"] == d["qid"]) & (front["node"] == d["a"])).select(front["qid"], F.col("b").alias("node")).distinct()
        front = written(new.join(seen, ["qid", "node"], "left_anti"), "reach")
        if front.isEmpty():
            break
        seen = written(seen.unionByName(front), "reach")
    hit = terminals.join(seen.withColumnRenamed("node", "node_key"), ["qid", "node_key"], "left_semi").groupBy("qid").agg(F.count("*").alias("reached"))
    return terminals.groupBy("qid").agg(F.count("*").alias("terminals")).join(hit, "qid", "left")
