"""Retrieval baselines over the same index. Each gives qid, chunk_key, score, rk unless its name says otherwise."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.functions.encoder import encode
from evigraph.operators.kg import both_ways
from evigraph.operators.retrieval import best, cosine, keyword_top, mixture_among, top_vectors
from evigraph.operators.textprep import tokens
from evigraph.plans.index import Index
from evigraph.plans.search import first, retrieved_by, searched, with_graph
from evigraph.runtime import once, token, written


def none(queries: DataFrame, labels: DataFrame) -> DataFrame:
    """No context: the most frequent label, whatever is asked."""
    top = labels.groupBy("label").agg(F.count("*").alias("n")).agg(F.max(F.struct("n", "label")).alias("m"))
    return queries.select("qid").join(F.broadcast(top.select("m.label"))).select("qid", F.col("label").alias("pred"))


def dense(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    return top_vectors(q, index.chunks, k, "chunk_key").withColumnRenamed("ms", "score")


def keyword_nodes(nodes: DataFrame, q: DataFrame) -> DataFrame:
    """qid, node_key of entities that a question names."""
    words = q.select("qid", F.explode(F.array_distinct(tokens(F.col("text")))).alias("text"))
    return nodes.where("kind = 'entity'").join(words, "text").select("qid", "node_key")


def mapped_nodes(index: Index, q: DataFrame, floor: float = 0.6) -> DataFrame:
    """qid, node_key: each word of a question goes to the one entity whose vector is closest, if it is close enough."""
    words = q.select("qid", F.explode(F.array_distinct(tokens(F.col("text")))).alias("w"))
    each = words.select("w").distinct().select(F.xxhash64("w").alias("qid"), "w")
    named = encode(index.nodes.where("kind = 'entity'"), "text", index.cfg.dim)
    top = top_vectors(written(encode(each, "w", index.cfg.dim, "qvec"), "words"), named, 1, "node_key").where(F.col("ms") >= floor)
    return words.select("qid", F.xxhash64("w").alias("w")).join(top.select(F.col("qid").alias("w"), "node_key"), "w").select("qid", "node_key").distinct()


def sparse(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    return keyword_top(q, index.chunks, index.words, index.cfg.fuse, k).withColumnRenamed("bm25", "score")


def compressed(index: Index, q: DataFrame, k: int = 5, budget: float = 0.5) -> DataFrame:
    """qid, prompt_tokens, kept: dense passages, then the most surprising half of their words under corpus bigrams, words of the question first.

    Surprisal -ln((count(a b) + 1) / (count(a) + V)); the words kept stay in order.
    """
    flat = index.chunks.select("chunk_key", F.posexplode("tokens").alias("i", "w"))
    pairs = index.chunks.select(F.explode(F.arrays_zip(F.slice("tokens", 1, F.size("tokens") - 1).alias("a"), F.slice("tokens", 2, F.size("tokens")).alias("w"))).alias("x")).select("x.a", "x.w")
    big = pairs.groupBy("a", "w").agg(F.count("*").alias("ab"))
    uni = pairs.groupBy("a").agg(F.count("*").alias("n"))
    size = index.words.agg(F.countDistinct("term").alias("v"))
    hit = dense(index, q, k).select("qid", "chunk_key", "rk")
    w = Window.partitionBy("qid", "rk").orderBy("i")
    rows = hit.join(flat, "chunk_key").withColumn("a", F.lag("w").over(w)).join(big, ["a", "w"], "left").join(uni, "a", "left").join(F.broadcast(size))
    asked = q.select("qid", tokens(F.col("text")).alias("qw"))
    s = -F.ln((F.coalesce("ab", F.lit(0)) + 1) / (F.coalesce("n", F.lit(0)) + F.col("v"))) + F.when(F.array_contains("qw", F.col("w")), 100.0).otherwise(0.0)
    scored = rows.join(asked, "qid").withColumn("s", F.round(s, 6))
    order = Window.partitionBy("qid").orderBy(F.desc("s"), "rk", "i")
    total = F.count("*").over(Window.partitionBy("qid"))
    keep = scored.withColumn("r", F.row_number().over(order)).withColumn("n_all", total).where(F.col("r") <= F.ceil(F.col("n_all") * budget))
    return keep.groupBy("qid").agg(F.max("n_all").alias("prompt_tokens"), F.count("*").alias("kept_tokens"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rk", "i", "w"))), lambda x: x["w"]), " ").alias("kept"))


def _codes(vecs: DataFrame, bits: int, seed: int) -> DataFrame:
    """node, code: the side of each of some random planes through the vectors."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        planes = None
        for pdf in batches:
            if len(pdf):
                m = np.array(pdf["vec"].tolist(), np.float32)
                planes = np.random.default_rng(seed).standard_normal((m.shape[1], bits)).astype(np.float32) if planes is None else planes
                yield pd.DataFrame({"node": pdf["node"], "code": (m @ planes > 0) @ (1 << np.arange(bits))})

    return vecs.select("node", "vec").mapInPandas(run, "node string, code long")


def summary_levels(index: Index, fanout: int = 10, levels: int = 3, seed: int = 1, by: str = "vector") -> DataFrame:
    """node, level, vec, chunk_key: leaves are chunks; each level puts the nodes below that lie on the same sides of random planes under one, which stands for
    its chunks by their mean vector and by the chunk closest to it (its summary). ``by='shared'`` groups chunks by their strongest shared entity first.

    No list of members is made: a table of (chunk, node) is carried from level to level, and the number of planes follows from the number of nodes."""
    chunks = index.chunks.select("chunk_key", "vec")
    out = chunks.select(F.col("chunk_key").alias("node"), F.lit(0).alias("level"), "vec", "chunk_key")
    member, n = chunks.select("chunk_key", F.col("chunk_key").alias("node")), out.count()
    nodes = out
    for level in range(1, levels + 1):
        if n <= fanout:
            break
        if by == "shared" and level == 1:
            strongest = F.row_number().over(Window.partitionBy("chunk_key").orderBy(F.desc("df"), "term"))
            member = index.entities.withColumn("r", strongest).where("r = 1").select("chunk_key", F.concat(F.lit("g:"), "term").alias("node"))
        else:
            code = _codes(nodes, max(1, round(np.log2(n / fanout))), seed + level).select("node", F.format_string(f"{by[0]}{level}:%x", "code").alias("up"))
            member = member.join(code, "node").select("chunk_key", F.col("up").alias("node"))
        member = written(member, "members")
        nodes = written(_summaries(member.join(chunks, "chunk_key"), index.cfg.dim).withColumn("level", F.lit(level)), "level")
        out, n = out.unionByName(nodes.select(out.columns)), nodes.count()
    return written(out, "tree")


def _summaries(rows: DataFrame, dim: int) -> DataFrame:
    """node, vec, chunk_key: the mean of a node's chunks and the chunk closest to it."""
    mean = F.array(*[F.avg(F.element_at("vec", i + 1)) for i in range(dim)])
    means = rows.groupBy("node").agg(mean.cast("array<float>").alias("mean"))
    near = rows.join(means, "node").groupBy("node").agg(F.max(F.struct(F.round(cosine(F.col("vec"), F.col("mean")), 6).alias("c"), "chunk_key")).alias("m"))
    return means.join(near, "node").select("node", F.col("mean").alias("vec"), F.col("m.chunk_key").alias("chunk_key"))


def summary_tree(index: Index, q: DataFrame, k: int = 5, by: str = "vector") -> DataFrame:
    """Flat search over all levels; a node found stands for its summary, the chunk closest to its mean."""
    nodes = once(q.sparkSession, ("summaries", token(index), by), lambda: summary_levels(index, by=by))
    found = top_vectors(q, nodes, k, "node").join(nodes.select("node", "chunk_key"), "node")
    return best(found.groupBy("qid", "chunk_key").agg(F.max("ms").alias("score")), k, "score", "chunk_key")


def twin_tree(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    """A tree by similarity and one by shared entities; both are searched and merged by the better score."""
    both = summary_tree(index, q, k).unionByName(summary_tree(index, q, k, by="shared"))
    return best(both.groupBy("qid", "chunk_key").agg(F.max("score").alias("score")), k, "score", "chunk_key")


def prize_subgraph(index: Index, q: DataFrame, prize_k: int = 10, edge_cost: float = 0.5) -> DataFrame:
    """qid, nodes, n_edges, value: ranked prizes on the nearest nodes and edges; regions grow while prize exceeds cost and weak branches go."""

    def solve(loc, near):
        top = first(near, np.arange(len(near)), prize_k, 6)
        prize: Counter = Counter()
        ep = {int(e): float(prize_k - i) / prize_k for i, e in enumerate(top)}
        for e in ep:
            for x in loc.ends[e]:
                prize[int(x)] = max(prize[int(x)], ep[e])
        cost = np.full(len(loc.ends), edge_cost)
        for e, p in ep.items():
            cost[e] = max(0.0, edge_cost - p)
        tree = loc.graph.steiner_voronoi(cost, list(prize))
        kept = set(tree)
        while kept:  # strong pruning: a leaf whose prize doesn't pay its edge goes
            deg: dict[int, list[int]] = {}
            for e in kept:
                for x in loc.ends[e]:
                    deg.setdefault(int(x), []).append(e)
            bad = {es[0] for x, es in deg.items() if len(es) == 1 and prize.get(x, 0.0) < cost[es[0]]}
            if not bad:
                break
            kept -= bad
        nodes = {int(x) for e in kept for x in loc.ends[e]} or {int(x) for x in loc.ends[top[0]]} if len(top) else set()
        return sorted(loc.keys[x] for x in nodes), len(kept), sum(prize.get(x, 0.0) for x in nodes) - float(sum(cost[e] for e in kept))

    def each(loc, r, near):
        return dict(zip(("qid", "nodes", "n_edges", "value"), (r.qid, *solve(loc, near))))

    return with_graph(index, q, each, "qid long, nodes array<string>, n_edges int, value double")


def prize_passages(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    """The passages of the prize subgraph, closest first."""
    held = prize_subgraph(index, q).select("qid", F.explode("nodes").alias("n")).where("n like 'p:%'").select("qid", F.expr("substring(n, 3)").alias("chunk_key"))
    near = held.join(index.chunks.select("chunk_key", "vec"), "chunk_key").join(q.select("qid", "qvec"), "qid")
    return best(near.select("qid", "chunk_key", cosine(F.col("vec"), F.col("qvec")).alias("score")), k, "score", "chunk_key")


def expert_mix(index: Index, q: DataFrame, k: int = 5, temperature: float = 1.0) -> DataFrame:
    """Four experts (single passage, path, summary, neighbours weighted by the question) with weights softmax(features / temperature) of the question's length."""
    n = F.size(tokens(F.col("text")))
    feats = F.array(F.lit(1.0), F.least(n / 20.0, F.lit(2.0)), F.least(n / 60.0, F.lit(2.0)), F.lit(0.5))
    gate = q.select("qid", F.transform(feats, lambda x: F.exp(x / temperature)).alias("e")).select("qid", F.transform("e", lambda x: x / F.aggregate("e", F.lit(0.0), lambda a, b: a + b)).alias("g"))
    experts = [dense(index, q, 2 * k), retrieved_by(searched(index, q, k=2 * k), "passages"), summary_tree(index, q, 2 * k), aggregated(index, q, 2 * k)]
    total = None
    for i, e in enumerate(experts):
        top = F.max("score").over(Window.partitionBy("qid"))
        part = e.withColumn("score", F.col("score") / F.nullif(top, F.lit(0.0))).join(gate, "qid").select("qid", "chunk_key", (F.element_at("g", i + 1) * F.col("score")).alias("score"))
        total = part if total is None else total.unionByName(part)
    return best(total.groupBy("qid", "chunk_key").agg(F.sum("score").alias("score")), k, "score", "chunk_key")


def aggregated(index: Index, q: DataFrame, k: int) -> DataFrame:
    """Passages by the facts around their entities: each entity takes the mean of its facts' closeness to the question, by their closeness, so facts far
    from the question add nothing; a passage takes the sum over its entities. Only the 200 closest facts of a question weigh."""
    rel = index.edges.where("kind = 'relation'")
    near = top_vectors(q, rel, 200, "edge_id").where("ms > 0").join(rel.select("edge_id", "src", "dst"), "edge_id")
    gate = near.select("qid", F.explode(F.array("src", "dst")).alias("src"), "ms").groupBy("qid", "src").agg((F.sum(F.col("ms") * F.col("ms")) / F.sum("ms")).alias("x"))
    held = index.edges.where("kind = 'contains'").select("src", F.expr("substring(dst, 3)").alias("chunk_key"))
    return best(held.join(gate, "src").groupBy("qid", "chunk_key").agg(F.sum("x").alias("score")), k, "score", "chunk_key")


def communities(edges: DataFrame, rounds: int = 5) -> DataFrame:
    """node_key, label by majority vote of neighbours, ties to the least label; each round is one join and two sums."""
    d = written(both_ways(edges.select("src", "dst")), "directed")
    label = d.select(F.col("src").alias("node_key")).distinct().withColumn("label", F.col("node_key"))
    for _ in range(rounds):
        votes = d.join(label, d["dst"] == label["node_key"]).groupBy("src", "label").agg(F.count("*").alias("n"))
        win = votes.groupBy("src").agg(F.min(F.struct((-F.col("n")).alias("n"), "label")).alias("m"))
        label = written(win.select(F.col("src").alias("node_key"), "m.label"), "labels")
    return label


def reports(index: Index, label: DataFrame, k: int = 10) -> DataFrame:
    """label, report, vec: a community's report names its k best-connected entities, as text and as a vector."""
    deg = both_ways(index.edges.select("src", "dst")).groupBy("src").agg(F.count("*").alias("g")).withColumnRenamed("src", "node_key")
    named = index.nodes.where("kind = 'entity'").join(label, "node_key").join(deg, "node_key")
    top = named.withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("g"), "text"))).where(F.col("r") <= k)
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "text"))), lambda x: x["text"]), " ")
    return written(encode(top.groupBy("label").agg(text.alias("report")), "report", index.cfg.dim), "reports")


def community_reports(index: Index, q: DataFrame, k: int = 5, mode: str = "local", rounds: int = 3) -> DataFrame:
    """Passages of the communities of the mapped entities (local) or of the two whose report is closest (global), by the mixture over all members."""
    label = once(q.sparkSession, ("communities", token(index), rounds), lambda: communities(index.edges, rounds))
    if mode == "local":
        rel = index.edges.where("kind = 'relation'")
        ends = top_vectors(q, rel, index.cfg.map.k_facts, "edge_id").join(rel.select("edge_id", "src", "dst"), "edge_id").select("qid", F.explode(F.array("src", "dst")).alias("node_key"))
        mine = ends.join(label, "node_key").select("qid", "label").distinct()
    else:
        mine = top_vectors(q, reports(index, label), 2, "label").select("qid", "label")
    groups = label.where("node_key like 'p:%'").select(F.expr("substring(node_key, 3)").alias("chunk_key"), "label")
    return mixture_among(q, index.chunks, index.words, groups, written(mine, "asked"), index.cfg.fuse.weight, k).withColumnRenamed("hs", "score")


def touching(seeds: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """Passages by how many of the seeds (qid, node_key) they touch; edges: src, dst in both directions."""
    met = seeds.join(edges, seeds["node_key"] == edges["src"]).where("dst like 'p:%'").groupBy("qid", F.expr("substring(dst, 3)").alias("chunk_key")).agg(F.countDistinct("src").cast("double").alias("score"))
    return best(met, k, "score", "chunk_key")


def neighbourhood(index: Index, q: DataFrame, k: int = 5, hops: int = 1, mode: str = "hybrid") -> DataFrame:
    """``low``: passages around the entities that the words of a question go to, one each, by vectors; ``high``: around the ends of the closest
    relation; ``hybrid``: both. Passages rank by how many of the nodes they touch."""
    low = mapped_nodes(index, q)
    rel = index.edges.where("kind = 'relation'")
    high = top_vectors(q, rel, 1, "edge_id").join(rel.select("edge_id", "src", "dst"), "edge_id").select("qid", F.explode(F.array("src", "dst")).alias("node_key"))
    seeds = {"low": low, "high": high, "hybrid": low.unionByName(high)}[mode].distinct()
    d = both_ways(index.edges.select("src", "dst"))
    for _ in range(hops - 1):
        seeds = written(seeds.unionByName(seeds.join(d, seeds["node_key"] == d["src"]).select("qid", F.col("dst").alias("node_key"))).distinct(), "hop")
    return touching(seeds, d, k)


def entity_sums(edges: DataFrame, scores: DataFrame, passage: str = "p:") -> DataFrame:
    """node_key, score of each passage: the sum over the nodes that it is tied to."""
    return both_ways(edges.select("src", "dst")).where(F.col("dst").startswith(passage)).join(scores, F.col("src") == F.col("node_key")).groupBy(F.col("dst").alias("node_key")).agg(F.sum("score").alias("score"))


def _scores_only(index: Index):
    return replace(index.cfg, tree=replace(index.cfg.tree, method="none"))


def ppr_passage(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    return retrieved_by(searched(index, q, _scores_only(index), grow=False, k=k), "passages")


def ppr_sum(index: Index, q: DataFrame, k: int = 5) -> DataFrame:
    return retrieved_by(searched(index, q, _scores_only(index), grow=False, k=k), "summed")
