"""Evidence subgraphs of a batch of questions, and answers: the method end to end with its ablations."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from evigraph.functions.encoder import encode
from evigraph.operators.influence import balance, power, seed_vector, uniform
from evigraph.operators.kg import pseudo_edges
from evigraph.operators.retrieval import MOST_QUERIES, best, build_prompt, cosine, fused_top, kept_facts, sliced, top_vectors, word_count
from evigraph.operators.steiner import grow_frozen, steiner_tree, subgraph_ratio
from evigraph.plans.index import LOCAL_EDGES, Index, LocalIndex
from evigraph.runtime import known, once, token, written
from evigraph.specs import Config

INSTRUCTION = "Answer the question from the evidence and the passages."
FOUND = (
    "qid long, facts array<string>, kept array<string>, terminals array<string>, tree array<string>, grown array<string>, tree_nodes int, nodes int, ratio_tree double, "
    "ratio double, candidates int, evidence string, tree_evidence string, passages array<struct<chunk_key:string,score:double>>, summed array<struct<chunk_key:string,score:double>>, top_entities array<string>"
)


def with_vectors(queries: DataFrame, dim: int) -> DataFrame:
    return encode(queries, "text", dim, out="qvec")


def first(values: np.ndarray, among: np.ndarray, k: int, digits: int) -> np.ndarray:
    """Of the numbers ``among`` (rising), those of the k largest rounded values, largest first, ties by number; without sorting all."""
    v = np.round(values[among].astype(float), digits)
    if len(v) > k > 0:
        at = np.flatnonzero(v >= np.partition(v, len(v) - k)[len(v) - k])
        among, v = among[at], v[at]
    return among[np.argsort(-v, kind="stable")[:k]]


def map_and_filter(loc: LocalIndex, text: str, near: np.ndarray, cfg: Config, judge: bool, kinds=("relation",)) -> tuple[list[int], list[int]]:
    """Edge numbers of the k closest facts, and of those that the offline judge keeps: close enough, or naming a word of the question."""
    own = loc.of_kinds(*kinds)
    if not len(own):
        return [], []
    top = first(near, own, cfg.map.k_facts, 6).tolist()
    if not judge:
        return top, top
    words = set(text.lower().split())
    kept = [e for e in top if round(float(near[e]), 6) >= cfg.map.floor or words & {w for x in loc.ends[e] for w in loc.text[x].split()}]
    return top, kept or top[:1]


def influence_of(loc: LocalIndex, seeds: list[int], cfg: Config) -> np.ndarray:
    i = cfg.influence
    s = loc.graph.influence(seeds, i.damping, i.tol, i.flow, i.off_edge, i.seed_norm)
    return np.where(loc.passage, s * i.balance, s)


def serialise(loc: LocalIndex, edges: list[int]) -> str:
    """Tree edges first, then growth in order; one line a fact."""
    return "; ".join(f"{loc.text[a]} -[{loc.relations[e]}]- {loc.text[b]}" for e in edges for a, b in [loc.ends[e]])


def one(loc: LocalIndex, qid: int, text: str, near: np.ndarray, cfg: Config, judge: bool, grow: bool, k: int) -> dict:
    """``near``: the question's cosine to each edge."""
    facts, kept = map_and_filter(loc, text or "", near, cfg, judge)
    terminals = sorted({int(x) for e in kept for x in loc.ends[e]})
    s = influence_of(loc, terminals, cfg) if terminals else np.zeros(len(loc.keys))
    cost = np.round((1 - near.astype(float)) / 2, 6)  # facts of the same words tie, whatever their order
    n_real = len(loc.ends)
    full = np.concatenate([cost, np.full(len(loc.linked.ends) - n_real, cfg.tree.pseudo)])
    method = {"voronoi": loc.linked.steiner_voronoi, "closure": loc.linked.steiner_closure, "chain": loc.linked.path_chain, "none": lambda *_: []}[cfg.tree.method]
    tree = [e for e in method(full, terminals)] if len(terminals) > 1 else []
    real = [e for e in tree if e < n_real]
    g = cfg.grow
    # Of a frozen threshold, edges with a passage may be left out: the balance factor would let a single one set it. A moving one counts all.
    counted = real if g.threshold != "frozen" or g.counted == "all" else [e for e in real if not loc.passage[loc.ends[e]].any()] or real
    limit = loc.graph.ratio(counted, cost, s, g.base if g.threshold == "frozen" else g.threshold)
    grown = loc.graph.grow(real, terminals, cost, s, g.threshold, g.pick, g.recompute, g.max_steps, limit) if grow and terminals else []
    tree_nodes = {int(x) for e in real for x in loc.ends[e]} | set(terminals)
    nodes = tree_nodes | {int(x) for e in grown for x in loc.ends[e]}
    tops, lead = (first(s, np.flatnonzero(own & (s > 0)), m, 9) for own, m in ((loc.passage, k), (~loc.passage, 10)))
    into, of = loc.held  # a passage's sum over the entities it holds
    sums = np.bincount(into, weights=s[of], minlength=len(loc.keys))
    tot = first(sums, np.flatnonzero(sums > 0), k, 9)
    named = lambda ids, v: [{"chunk_key": loc.keys[i][2:], "score": float(v[i])} for i in ids]
    return {
        "qid": qid, "facts": [loc.edge_id(e) for e in facts], "kept": [loc.edge_id(e) for e in kept], "terminals": [loc.keys[t] for t in terminals],
        "tree": [loc.edge_id(e) for e in real], "grown": [loc.edge_id(e) for e in grown], "tree_nodes": len(tree_nodes), "nodes": len(nodes),
        "ratio_tree": loc.graph.ratio(real, cost, s), "ratio": loc.graph.ratio(real + grown, cost, s), "candidates": under(loc, real, cost, s, limit), "evidence": serialise(loc, real + grown), "tree_evidence": serialise(loc, real),
        "passages": named(tops, s), "summed": named(tot, sums), "top_entities": [loc.text[i] for i in lead],
    }


def under(loc: LocalIndex, tree: list[int], cost: np.ndarray, s: np.ndarray, limit: float) -> int:
    """Edges outside the tree whose cost over the larger score is under the first threshold: no frozen growth takes more."""
    a, b = loc.graph.columns
    top = np.maximum(s[a], s[b])
    with np.errstate(divide="ignore", invalid="ignore"):
        fits = (top > 0) & (cost / top < limit)
    fits[tree] = False
    return int(fits.sum())


#: Questions whose closeness to all edges a task works out at once.
AT_ONCE = 16


def with_graph(index: Index, queries: DataFrame, each: Callable[[LocalIndex, Row, np.ndarray], dict], kind: str) -> DataFrame:
    """``each(graph, question, its cosines to all edges)`` of all questions (qid, text, qvec) as rows of ``kind``. Every task reads the whole graph from the tables of the index and
    takes a share of the questions, so neither the driver nor a broadcast holds the graph."""
    return sliced(queries, lambda q: _with_graph(index, q, each, kind))


def _with_graph(index: Index, queries: DataFrame, each: Callable[[LocalIndex, Row, np.ndarray], dict], kind: str) -> DataFrame:
    spark, dim = index.edges.sparkSession, index.cfg.dim
    asked = queries.select("qid", "text", "qvec").orderBy("qid").limit(MOST_QUERIES + 1).collect()
    if len(asked) > MOST_QUERIES:
        raise ValueError(f"more than {MOST_QUERIES} questions in one batch; run them in slices")
    parts = max(1, min(len(asked), spark.sparkContext.defaultParallelism))
    shared = spark.sparkContext.broadcast(asked)

    n_edges, graph = index.n_edges, index.numbered

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = next(batches, None)
        if first is not None:
            mine = shared.value[first["part"][0].as_py() :: parts]
            loc = LocalIndex.of(chain([first], batches), n_edges, dim)
            for at in range(0, len(mine), AT_ONCE):
                some = mine[at : at + AT_ONCE]
                near = np.array([r.qvec for r in some], np.float32) @ loc.vecs.T
                yield pa.RecordBatch.from_pylist([each(loc, r, c) for r, c in zip(some, near)], schema=out)

    out = to_arrow_schema(StructType.fromDDL(kind))
    # By pairs of partitions: each of the parts meets the one partition of the graph, and no row is dealt out.
    return spark.range(0, parts, 1, parts).select(F.col("id").alias("part")).hint("shuffle_replicate_nl").join(graph.coalesce(1)).mapInArrow(run, kind)


def search(index: Index, queries: DataFrame, cfg: Config | None = None, judge: bool = True, grow: bool = True, k: int = 5, local: bool | None = None) -> DataFrame:
    """One row a question. A graph of at most LOCAL_EDGES edges is read whole by each task, a larger one searched by joins; ``local`` sets the way.

    Both give the same rows but for the order of ``grown`` (by price, or by step) and the choice among edges of equal cost.
    """
    cfg = cfg or index.cfg
    if not (index.n_edges <= LOCAL_EDGES if local is None else local):
        return joined(index, queries, cfg, judge, grow, k)
    return with_graph(index, queries, lambda loc, r, near: one(loc, r.qid, r.text, near, cfg, judge, grow, k), FOUND)


def search_frames(index: Index, queries: DataFrame, cfg: Config | None = None, judge: bool = True, grow: bool = True) -> dict[str, DataFrame]:
    """The search by joins, for graphs of any size: mapped facts, scores, costs, tree, growth. Nothing of the graph reaches the driver.

    Costs are computed only for edges with a scored end, and their passages are tied to the pseudo node. It knows Voronoi trees (or none) and
    frozen growth by edges; other settings raise ValueError.
    """
    cfg = cfg or index.cfg
    if cfg.tree.method not in ("voronoi", "none") or (grow and (cfg.grow.threshold != "frozen" or cfg.grow.pick != "edge" or cfg.grow.max_steps is not None)):
        raise ValueError("the search by joins has Voronoi trees and frozen growth by edges only")
    rel = index.edges.where("kind = 'relation'")
    mapped = written(top_vectors(queries, rel, cfg.map.k_facts, "edge_id"), "mapped")
    kept = mapped
    if judge:
        words = queries.select("qid", F.split(F.lower("text"), r"\s+").alias("qw"))
        facts = mapped.join(rel.select("edge_id", "src", "dst"), "edge_id").join(words, "qid")
        named = F.arrays_overlap("qw", F.split(F.concat_ws(" ", F.expr("substring(src, 3)"), F.expr("substring(dst, 3)")), " "))
        kept = written(kept_facts(facts, cfg.map.floor, F.coalesce(named, F.lit(False))).select("qid", "edge_id", "ms", "rk"), "kept")
    i = cfg.influence
    seeds = written(seed_vector(kept, index.edges, i.seed_norm), "seeds")
    raw = uniform(index.edges, index.nodes, seeds, i.damping) if i.off_edge == "uniform" else power(index.edges, seeds, i.damping, None, i.tol, i.flow)
    scores = written(balance(raw, i.balance), "scores")
    near = scores.select("qid", F.col("node_key").alias("src"))
    ends = index.edges.select("edge_id", "src", "dst", "vec")
    touched = near.join(ends, "src").unionByName(near.withColumnRenamed("src", "dst").join(ends, "dst"))
    cost = F.round((1 - cosine(F.col("vec"), F.col("qvec"))) / 2, 6).alias("cost")
    costs = written(touched.dropDuplicates(["qid", "edge_id"]).join(queries.select("qid", "qvec"), "qid").select("qid", "edge_id", "src", "dst", cost), "costs")
    terminals = seeds.select("qid", "node_key")
    held = costs.select("qid", F.explode(F.array("src", "dst")).alias("node_key")).where("node_key like 'p:%'").distinct()
    tied = costs.unionByName(held.join(pseudo_edges(index.nodes).select("edge_id", "src", "dst"), held["node_key"] == F.col("dst")).select("qid", "edge_id", "src", "dst", F.lit(cfg.tree.pseudo).alias("cost")))
    none = costs.select("qid", "edge_id").where("false")
    tree = written(steiner_tree(tied, terminals).join(costs.select("qid", "edge_id"), ["qid", "edge_id"], "left_semi"), "tree") if cfg.tree.method == "voronoi" else none
    plain = tree
    if cfg.grow.counted == "entities":  # edges without a passage, but all of a tree that has no such
        inner = tree.join(costs.select("qid", "edge_id", "src", "dst"), ["qid", "edge_id"]).withColumn("inner", F.expr("src not like 'p:%' and dst not like 'p:%'"))
        some = inner.groupBy("qid").agg(F.bool_or("inner").alias("some"))
        plain = inner.join(some, "qid").where("inner or not some").select("qid", "edge_id")
    grown = grow_frozen(tree, terminals, costs, scores, plain, cfg.grow.base) if grow else none.withColumn("step", F.lit(0))
    return {"mapped": mapped, "kept": kept, "seeds": seeds, "scores": scores, "costs": costs, "tree": tree, "counted": plain, "grown": grown}


def joined(index: Index, queries: DataFrame, cfg: Config, judge: bool = True, grow: bool = True, k: int = 5) -> DataFrame:
    """The rows of ``search`` from ``search_frames``. A row holds one question's facts, tree, growth and best passages, as its prompt does."""
    f = search_frames(index, queries, cfg, judge, grow)
    listed = lambda df, c, *by: df.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct(*by, c))).alias("x"))
    names = lambda df, c, out, *by: listed(df, c, *by).select("qid", F.col(f"x.{c}").alias(out))
    grown = written(f["grown"], "grown")
    edges = written(f["tree"].select("qid", "edge_id", F.lit(-1).alias("step")).unionByName(grown.select("qid", "edge_id", "step")), "subgraph")
    ends = edges.join(f["costs"].select("qid", "edge_id", "src", "dst"), ["qid", "edge_id"])
    inside = lambda e: e.select("qid", F.explode(F.array("src", "dst")).alias("node_key")).unionByName(f["seeds"].select("qid", "node_key")).distinct().groupBy("qid").agg(F.count("*").cast("int").alias("n"))
    text = index.nodes.select("node_key", "text")
    said = ends.join(index.edges.select("edge_id", "relation"), "edge_id").join(text.select(F.col("node_key").alias("src"), F.col("text").alias("ta")), "src").join(text.select(F.col("node_key").alias("dst"), F.col("text").alias("tb")), "dst")
    said = said.select("qid", "step", "edge_id", F.concat("ta", F.lit(" -["), "relation", F.lit("]- "), "tb").alias("line"))
    evidence, tree_evidence = (listed(x, "line", "step", "edge_id").select("qid", F.array_join("x.line", "; ").alias(n)) for x, n in ((said, "evidence"), (said.where("step < 0"), "tree_evidence")))
    s = f["scores"].where("score > 0")
    top = lambda df, out: listed(best(df, k, "score", "node_key", digits=9), "node_key", "rk", "score").select("qid", F.transform("x", lambda r: F.struct(F.substring(r["node_key"], 3, 2**30).alias("chunk_key"), r["score"].alias("score"))).alias(out))
    links = index.edges.where("(src like 'p:%') <> (dst like 'p:%')").select(F.expr("if(src like 'p:%', src, dst)").alias("p"), F.expr("if(src like 'p:%', dst, src)").alias("node_key"))
    sums = s.join(links, "node_key").groupBy("qid", "p").agg(F.sum("score").alias("score")).withColumnRenamed("p", "node_key")
    lead = best(s.where("node_key not like 'p:%'"), 10, "score", "node_key", digits=9).join(text, "node_key")
    limit = subgraph_ratio(f["counted"], f["costs"], f["scores"], cfg.grow.base).withColumnRenamed("ratio", "r")
    side = lambda c: s.select("qid", F.col("node_key").alias(c), F.col("score").alias(f"s{c}"))
    priced = f["costs"].join(f["tree"], ["qid", "edge_id"], "left_anti").join(side("src"), ["qid", "src"], "left").join(side("dst"), ["qid", "dst"], "left").join(limit, "qid")
    under = priced.where("cost / greatest(ssrc, sdst) < r").groupBy("qid").agg(F.count("*").cast("int").alias("candidates"))
    ratio = lambda e, out: subgraph_ratio(e.select("qid", "edge_id"), f["costs"], f["scores"]).withColumnRenamed("ratio", out)
    parts = [
        names(f["mapped"], "edge_id", "facts", "rk"), names(f["kept"], "edge_id", "kept", "rk"), names(f["seeds"], "node_key", "terminals"), names(f["tree"], "edge_id", "tree"),
        names(grown, "edge_id", "grown", "step"), inside(ends.where("step < 0")).withColumnRenamed("n", "tree_nodes"), inside(ends).withColumnRenamed("n", "nodes"), ratio(f["tree"], "ratio_tree"),
        ratio(edges, "ratio"), under, evidence, tree_evidence, top(s.where("node_key like 'p:%'"), "passages"), top(sums, "summed"), names(lead, "text", "top_entities", "rk"),
    ]
    out = queries.select("qid")
    for part in parts:
        out = out.join(part, "qid", "left")
    kinds = {x.name: x.dataType for x in index.edges.sparkSession.createDataFrame([], FOUND).schema}
    empty = {n: F.lit("") if n.endswith("evidence") else F.lit(0) if n not in ("passages", "summed") and kinds[n].typeName() != "array" else F.array() for n in kinds}
    return out.select(*[F.coalesce(F.col(n), empty[n].cast(kinds[n])).cast(kinds[n]).alias(n) for n in kinds])


VARIANTS = ("full", "fused_only", "llm_entities", "graph_only", "tree_only", "no_filter")


#: A shared search ranks so many passages at least; who asks for fewer takes the first of them.
PASSAGES = 10


def searched(index: Index, queries: DataFrame, cfg: Config | None = None, judge: bool = True, grow: bool = True, k: int = 5) -> DataFrame:
    """``search``, written once for the same index, questions and settings, as several systems and measures read it. A search that grows its trees also has
    the rows of the same search without growth, or without trees."""
    cfg, spark, wide = cfg or index.cfg, queries.sparkSession, max(k, PASSAGES)
    key = lambda c, g: ("search", token(index), token(queries), c, judge, g, wide)
    treed = replace(cfg, tree=index.cfg.tree)
    if not grow and known(spark, key(cfg, True)):
        found = ungrown(once(spark, key(cfg, True), dict))
    elif not grow and cfg.tree.method == "none" and known(spark, key(treed, True)):
        found = treeless(once(spark, key(treed, True), dict))
    else:
        found = once(spark, key(cfg, grow), lambda: written(search(index, queries, cfg, judge, grow, wide), "found"))
    return found.withColumns({c: F.slice(c, 1, k) for c in ("passages", "summed")}) if k < wide else found


def ungrown(found: DataFrame) -> DataFrame:
    """Rows of a search as they are without growth."""
    return found.withColumns({"grown": F.array().cast("array<string>"), "nodes": F.col("tree_nodes"), "ratio": F.col("ratio_tree"), "evidence": F.col("tree_evidence")})


def treeless(found: DataFrame) -> DataFrame:
    """Rows of a search as they are without trees: influence is that of the terminals, whatever joins them."""
    none, ends = F.array().cast("array<string>"), F.size("terminals")
    cells = {"tree": none, "grown": none, "tree_nodes": ends, "nodes": ends, "ratio_tree": F.lit(0.0), "ratio": F.lit(0.0), "candidates": F.lit(0), "evidence": F.lit(""), "tree_evidence": F.lit("")}
    return found.withColumns(cells)


def ask(index: Index, queries: DataFrame, cfg: Config | None = None, variant: str = "full") -> DataFrame:
    """qid, text, evidence, chunk_keys, prompt, answer, tok_in, tok_out, nodes, tree_nodes, n_edges.

    ``fused_only`` leaves out the graph, ``graph_only`` the fused passages, ``tree_only`` growth, ``no_filter`` the judge of facts;
    ``llm_entities`` is the same search over an index built with ``extract_with_model``.
    """
    cfg = cfg or index.cfg
    if variant not in VARIANTS:
        raise ValueError(f"unknown variant {variant}")
    q = queries if "qvec" in queries.columns else once(queries.sparkSession, ("vectors", token(queries), cfg.dim), lambda: written(with_vectors(queries.select("qid", "text"), cfg.dim), "questions"))
    if variant == "fused_only":
        return answered(index, q.select("qid", "text"), fused_top(q, index.chunks, index.words, cfg.fuse))
    found = searched(index, q, cfg, judge=variant != "no_filter", grow=variant != "tree_only", k=cfg.fuse.k)
    rows = q.select("qid", "text").join(found.select("qid", "evidence", "nodes", "tree_nodes", (F.size("tree") + F.size("grown")).alias("n_edges"), "top_entities"), "qid", "left")
    return answered(index, rows, retrieved_by(found, "passages") if variant == "graph_only" else fused_top(q, index.chunks, index.words, cfg.fuse))


def answered(index: Index, rows: DataFrame, top: DataFrame) -> DataFrame:
    """Prompt and answer of each question (qid, text and, of a search, evidence, sizes and entities) from its passages (qid, chunk_key, rk)."""
    empty = {"evidence": F.lit(""), "nodes": F.lit(0), "tree_nodes": F.lit(0), "n_edges": F.lit(0), "top_entities": F.array().cast("array<string>")}
    rows = rows.withColumns({c: v for c, v in empty.items() if c not in rows.columns})
    text = top.select("qid", "chunk_key", "rk").join(index.chunks.select("chunk_key", F.array_join("tokens", " ").alias("t")), "chunk_key")
    held = text.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("rk", "chunk_key", "t"))).alias("c"))
    rows = rows.join(held, "qid", "left").withColumns({"chunk_keys": F.transform("c", lambda x: x["chunk_key"]), "texts": F.transform("c", lambda x: x["t"])})
    rows = rows.withColumn("prompt", build_prompt(F.col("text"), F.col("evidence"), F.col("texts"), INSTRUCTION)).withColumn("answer", extractive(F.col("text"), F.col("top_entities"), F.col("texts")))
    return rows.select("qid", "text", "evidence", "chunk_keys", "prompt", "answer", word_count(F.col("prompt")).alias("tok_in"), word_count(F.col("answer")).alias("tok_out"), "nodes", "tree_nodes", "n_edges")


def extractive(question, entities, texts):
    """Offline generator: the most influential entities that the question doesn't name, a line each, then the head of the first passage."""
    asked = F.split(F.lower(question), " ")
    new = F.slice(F.filter(F.coalesce(entities, F.array().cast("array<string>")), lambda e: ~F.array_contains(asked, e)), 1, 3)
    head = F.array_join(F.slice(F.split(F.coalesce(F.try_element_at(texts, F.lit(1)), F.lit("")), " "), 1, 40), " ")
    return F.trim(F.concat_ws("\n", F.array_join(new, "\n"), head))


def retrieved_by(found: DataFrame, column: str) -> DataFrame:
    """qid, chunk_key, score, rk of the passages that a search ranked: ``passages`` (their own score) or ``summed`` (their entities')."""
    return found.select("qid", F.posexplode(column).alias("i", "p")).select("qid", "p.chunk_key", "p.score", (F.col("i") + 1).alias("rk"))
