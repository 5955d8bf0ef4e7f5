"""Distributed union-find: alternating star contraction over an edge table.

Each round points every node's larger neighbours at its least neighbour (large star), then every node
and its smaller neighbours at the least of them (small star). Tables are written to the shared folder after each round, so
plans stay short and a lost executor costs no more than a re-read. Ends when all is stars.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm.common import forget, saved


def _large(e: DataFrame) -> DataFrame:
    both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small(e: DataFrame) -> DataFrame:
    least = e.groupBy("u").agg(F.min("v").alias("m"))
    return e.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x")).select("x.*").where("u > v").distinct()


def _settled(e: DataFrame) -> bool:
    """Whether each node points at one other and none is both pointing and pointed at: a forest of stars."""
    ends = e.select(F.col("u").alias("n"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(e.select(F.col("v").alias("n"), F.lit(0).alias("out"), F.lit(1).alias("into")))
    bad = ends.groupBy("n").agg(F.sum("out").alias("o"), F.max("into").alias("i")).where("o > 1 or (o > 0 and i > 0)")
    return bad.isEmpty()


def components(edges: DataFrame, a: str, b: str, rounds: int = 60) -> DataFrame:
    """Node and root (the least node of its component) of every node that has an edge."""
    e = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u > v").distinct()
    e = saved(e, "edges", light=True)  # the first round reads it more than once
    for _ in range(rounds):
        old, e = e, saved(_small(_large(e)), "stars", light=True)
        forget(old)
        if _settled(e):
            roots = e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
    raise RuntimeError("components: no fixed point in the allowed rounds")


def joined_on(roots: DataFrame, links: DataFrame) -> DataFrame:
    """node and root after more links (a, b) between nodes; nodes without a root are their own."""
    if links.isEmpty():
        return roots
    of = roots.select(F.col("node").alias("a"), F.col("root").alias("ra"))
    up = links.select("a", "b").join(of, "a", "left").join(of.toDF("b", "rb"), "b", "left")
    up = saved(components(up.select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b")), "a", "b").toDF("root", "top"), "tops", light=True)
    old = roots.join(up, "root", "left").select("node", F.coalesce("top", "root").alias("root"))
    new = up.select(F.col("root").alias("node"), F.col("top").alias("root")).join(roots.select("node"), "node", "left_anti")
    return old.unionByName(new)
