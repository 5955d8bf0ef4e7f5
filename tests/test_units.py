"""Hand-checked fixtures and properties of the method."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from evigraph.functions.graphs import LocalGraph
from evigraph.operators import entities as ents
from evigraph.operators import influence as infl
from evigraph.operators import measures as me
from evigraph.operators import steiner, textprep
from evigraph.operators.retrieval import fuse
from evigraph.specs import ChunkSpec, EntitySpec

NAMES = ["pump", "motor", "seal", "valve", "paint", "p1", "p2"]
PAIRS = [("pump", "motor"), ("pump", "seal"), ("motor", "valve"), ("seal", "valve"), ("valve", "paint"), ("pump", "p1"), ("motor", "p1"), ("seal", "p2"), ("valve", "p2"), ("paint", "p2")]
GRAPH = LocalGraph(7, np.array([[NAMES.index(a), NAMES.index(b)] for a, b in PAIRS]))
PUSH = [0.267417, 0.244305, 0.232269, 0.093973, 0.021033, 0.085287, 0.055716]
PULL = [0.267417, 0.244305, 0.232269, 0.070480, 0.031549, 0.127930, 0.055716]
PRINTED = [1.371816, 1.323836, 1.303919, 0.752152, 0.802440, 1.007014, 0.797886]


def test_entity_score(spark):
    docs = spark.createDataFrame([("A", "red bolt red nut"), ("B", "blue bolt steel nut"), ("C", "green ring bolt nut")], "doc_key string, text string")
    s = ents.score_chunks(textprep.chunk(docs), EntitySpec(min_df=1))
    got = {(r.term, r.chunk_key[0]): r.er for r in s.collect()}
    assert got["red", "A"] == pytest.approx(0.25)
    assert got["red bolt", "A"] == pytest.approx(0.125)
    assert got["bolt", "A"] == 0
    assert got["steel", "B"] == pytest.approx(0.125)
    kept = ents.select_entities(s, EntitySpec(min_df=1, tau=0.2, cap=None, max_df=1)).collect()
    assert [(r.term, r.chunk_key) for r in kept] == [("red", "A:0")]
    counts = [ents.select_entities(s, EntitySpec(min_df=1, tau=t, cap=None, max_df=1)).count() for t in (0.0, 0.1, 0.2, 0.3)]
    assert counts == sorted(counts, reverse=True)


@pytest.mark.parametrize("n,chunks", [(0, 0), (1, 1), (224, 1), (225, 1), (256, 1), (257, 2), (480, 2), (481, 3)])
def test_chunk_counts(spark, n, chunks):
    docs = spark.createDataFrame([("d", " ".join(f"w{i}" for i in range(n))), ("e", None)], "doc_key string, text string")
    rows = textprep.chunk(docs).orderBy("chunk_no").collect()
    assert len(rows) == chunks
    words = [w for r in rows for w in (r.tokens if r.chunk_no == 0 else r.tokens[32:])]
    assert words == [f"w{i}" for i in range(n)]


def test_chunk_rejects_overlap(spark):
    with pytest.raises(ValueError):
        textprep.chunk(spark.createDataFrame([("d", "x")], "doc_key string, text string"), ChunkSpec(10, 10))


@pytest.mark.parametrize("kw,want", [({}, PUSH), ({"flow": "pull"}, PULL), ({"off_edge": "uniform", "seed_norm": "none"}, PRINTED)])
def test_influence(kw, want):
    assert GRAPH.influence([0, 1, 2], **kw) == pytest.approx(want, abs=2e-6)


def test_uniform_equals_dense_solve():
    rng = np.random.default_rng(0)
    g = LocalGraph(40, rng.integers(0, 40, (90, 2)))
    ends = {tuple(sorted(e)) for e in g.ends.tolist()}
    g = LocalGraph(40, np.array(sorted(e for e in ends if e[0] != e[1])))
    p = np.zeros(40)
    p[[1, 5]] = 1
    m = np.full((40, 40), 1 / 40)
    for u in range(40):
        for v, _ in g.around(u):
            m[u, v] = 1 / g.degree[u]
    assert g.influence([1, 5], off_edge="uniform", seed_norm="none") == pytest.approx(np.linalg.solve(np.eye(40) - 0.5 * m, 0.5 * p), abs=1e-6)


def test_influence_frames_match(spark):
    e = spark.createDataFrame([(f"{a}|r|{b}", a, b) for a, b in PAIRS], "edge_id string, src string, dst string")
    seeds = infl.seeds_of(spark.createDataFrame([(1, x) for x in NAMES[:3]], "qid long, node_key string"))
    for flow, want in (("push", PUSH), ("pull", PULL)):
        got = {r.node_key: r.score for r in infl.power(e, seeds, flow=flow).collect()}
        assert [got[n] for n in NAMES] == pytest.approx(want, abs=2e-6)
    near = {r.node_key: r.score for r in infl.push_frontier(e, seeds, eps=1e-5).collect()}
    assert [near[n] for n in NAMES] == pytest.approx(PUSH, abs=1e-4)
    assert GRAPH.push_local([0, 1, 2], eps=1e-7) == pytest.approx(PUSH, abs=1e-5)
    nodes = spark.createDataFrame([(n,) for n in NAMES], "node_key string")
    raw = infl.seeds_of(spark.createDataFrame([(1, x) for x in NAMES[:3]], "qid long, node_key string"), "none")
    uni = {r.node_key: r.score for r in infl.uniform(e, nodes, raw).collect()}
    assert [uni[n] for n in NAMES] == pytest.approx(PRINTED, abs=1e-5)


G4 = LocalGraph(5, np.array([[0, 1], [0, 2], [1, 3], [2, 3], [3, 4]]))
COST4, SCORE4 = np.array([0.20, 0.22, 0.10, 0.14, 0.08]), np.array([0.30, 0.25, 0.25, 0.20, 0.10])


def test_tree_and_ratios():
    tree = G4.steiner_voronoi(COST4, [0, 1, 2])
    assert tree == [0, 1] == G4.steiner_closure(COST4, [0, 1, 2])
    assert G4.ratio(tree, COST4, SCORE4) == pytest.approx(0.763636, abs=1e-6)
    assert G4.ratio(tree, COST4, SCORE4, "mean") == pytest.approx(0.381818, abs=1e-6)
    assert G4.ratio(tree, COST4, SCORE4, "pooled") == pytest.approx(0.525, abs=1e-6)


@pytest.mark.parametrize(
    "threshold,pick,recompute,nodes,edges",
    [("frozen", "edge", "after", 4, 4), ("frozen", "node", "after", 4, 3), ("frozen", "node_all", "after", 4, 4), ("sum", "edge", "after", 5, 5), ("sum", "node", "after", 5, 4), ("sum", "node_all", "after", 5, 5), ("sum", "node", "before", 4, 3), ("mean", "edge", "after", 3, 2), ("mean", "node", "after", 3, 2), ("pooled", "node", "after", 4, 3), ("pooled", "edge", "after", 4, 3), ("pooled", "node_all", "after", 4, 4)],
)
def test_growth_table(threshold, pick, recompute, nodes, edges):
    added = G4.grow([0, 1], [0, 1, 2], COST4, SCORE4, threshold, pick, recompute)
    every = [0, 1, *added]
    assert len({int(x) for e in every for x in G4.ends[e]}) == nodes
    assert len(every) == edges


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10_000))
def test_trees_within_twice_the_optimum(seed):
    rng = np.random.default_rng(seed)
    n = 12
    ends = np.array([[i, int(rng.integers(0, i))] for i in range(1, n)] + [[int(x) for x in rng.choice(n, 2, replace=False)] for _ in range(10)])
    g, cost = LocalGraph(n, ends), rng.random(len(ends)) + 0.05
    t = sorted(rng.choice(n, 4, replace=False).tolist())
    best = g.steiner_exact(cost, t)
    for tree in (g.steiner_voronoi(cost, t), g.steiner_closure(cost, t)):
        assert best - 1e-9 <= cost[tree].sum() <= 2 * (1 - 1 / 4) * best + 1e-9
        assert {int(x) for e in tree for x in g.ends[e]} >= set(t)


def frames4(spark):
    name = ["pump", "motor", "seal", "valve", "paint"]
    costs = spark.createDataFrame([(1, f"e{i}", name[a], name[b], float(COST4[i])) for i, (a, b) in enumerate(G4.ends)], "qid long, edge_id string, src string, dst string, cost double")
    scores = spark.createDataFrame([(1, n, float(s)) for n, s in zip(name, SCORE4)], "qid long, node_key string, score double")
    return costs, scores, spark.createDataFrame([(1, n) for n in name[:3]], "qid long, node_key string")


def test_frames_tree_growth_and_reach(spark):
    costs, scores, terminals = frames4(spark)
    tree = steiner.steiner_tree(costs, terminals)
    assert {r.edge_id for r in tree.collect()} == {"e0", "e1"}
    assert {k: steiner.subgraph_ratio(tree, costs, scores, k).first().ratio for k in ("sum", "mean", "pooled")} == pytest.approx({"sum": 0.763636, "mean": 0.381818, "pooled": 0.525}, abs=1e-6)
    assert {r.edge_id for r in steiner.grow_frozen(tree, terminals, costs, scores).collect()} == {"e2", "e3"}
    assert steiner.check_reach(tree, terminals, costs).first().reached == 3


def test_measures(spark):
    row = spark.createDataFrame([("the red bolt fits", "a red bolt")], "a string, g string")
    assert row.select(me.lcs_ratio("a", "g")).first()[0] == 0.5
    assert row.select(me.lcs_fold(F.col("a"), F.col("g"))).first()[0] == 0.5
    assert row.select(me.coverage(F.array(F.lit("red"), F.lit("bolt"), F.lit("steel")), F.lit("red bolt"))).first()[0] == pytest.approx(2 / 3)
    assert row.select(me.faithfulness(F.lit("a b. c d. e f. no"), F.lit("a b c d and c d e f"))).first()[0] == 0.75
    p = spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "b"), ("z", "b")], "pred string, gold string")
    assert me.accuracy_exact(p).first()[0] == 0.5
    assert me.macro_recall(p).first()[0] == pytest.approx(2 / 3)
    assert me.out_of_label_rate(p, spark.createDataFrame([("a",), ("b",)], "label string")).first()[0] == 0.25


def test_fusion(spark):
    d = spark.createDataFrame([(1, "c", 0.6)], "qid long, chunk_key string, ms double")
    s = spark.createDataFrame([(1, "c", 1.8)], "qid long, chunk_key string, bm25 double")
    assert fuse(d, s).first().hs == pytest.approx(1.2)


def test_blocks_find_the_pairs_of_buckets(spark):
    """Both ways to the pairs that share a band, with copies, a null and a zero vector; and no vector is sent to more than its block."""
    from evigraph.operators import synonyms

    x = np.random.default_rng(3).standard_normal((60, 8)).astype(np.float32)
    rows = [(f"k{i}", [float(v) for v in x[i % 45]]) for i in range(60)] + [("zero", [0.0] * 8), ("none", None)]
    vecs = spark.createDataFrame(rows, "node_key string, vec array<float>").where("vec is not null")
    pairs = lambda df: {(r.src, r.dst): round(r.cos, 9) for r in df.collect()}
    for phi, recall in ((0.35, 0.99), (0.8, 0.6)):
        want = pairs(synonyms.edges_lsh(vecs, phi, recall=recall, whole=False))
        blocks = synonyms.edges_lsh(vecs, phi, recall=recall, whole=True)
        assert pairs(blocks) == want and blocks.count() == len(want) > 15
        exact = synonyms.pairs_exact(vecs, phi, "node_key").count()
        r = synonyms.recall_of_bands(vecs, phi, recall=recall).first()
        assert r.pairs == exact and r.recall == pytest.approx(len(want) / exact)
    plan = synonyms.met_in_blocks(vecs, 0.35, "node_key", 62, 40, 4)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
