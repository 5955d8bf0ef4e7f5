"""Searches of many questions: the same results without walking the whole graph, or making a row for each question and chunk."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evigraph.functions.graphs import LocalGraph
from evigraph.operators import retrieval
from evigraph.specs import FuseSpec


def plain_tree(g, cost, terminals):
    """Regions over the whole graph, all crossings, least spanning tree, its paths, pruned."""
    dist, owner, via = g.distances(cost, terminals)
    best = {}
    for e, (a, b) in enumerate(g.ends):
        if owner[a] >= 0 and owner[b] >= 0 and owner[a] != owner[b]:
            key = tuple(sorted((int(owner[a]), int(owner[b]))))
            best[key] = min(best.get(key, (np.inf, 0)), (round(dist[a] + cost[e] + dist[b], 9), e))
    path = lambda e: [e, *g._walk(int(g.ends[e][0]), via), *g._walk(int(g.ends[e][1]), via)]
    return g.pruned(g.spanning(g._join(sorted(set(terminals)), sorted((w, k, e) for k, (w, e) in best.items()), path), cost), terminals)


@pytest.mark.parametrize("seed", range(12))
def test_trees_equal_those_over_the_whole_graph(seed):
    rng = np.random.default_rng(seed)
    n = 60
    g = LocalGraph(n, rng.integers(0, n, (rng.integers(40, 200), 2)))
    cost = np.round(rng.uniform(0, 0.5, len(g.ends)) if seed % 3 else rng.integers(0, 4, len(g.ends)) / 10, 6)  # every third: ties and edges without a cost
    ends = rng.choice(n, rng.integers(1, 8), replace=False).tolist()
    tree, want = g.steiner_voronoi(cost, ends), plain_tree(g, cost, ends)
    assert tree == want if seed % 3 else cost[tree].sum() == pytest.approx(cost[want].sum())


def test_a_tree_needs_only_the_graph_around_its_terminals(monkeypatch):
    """Terminals that meet over few edges in a long chain, all of whose nodes a far node is tied to, as passages are to the pseudo node."""
    n = 20_000
    chain = np.column_stack([np.arange(n - 1), np.arange(1, n)])
    g = LocalGraph(n + 1, np.vstack([chain, np.column_stack([np.full(n, n), np.arange(n)])]))
    cost = np.concatenate([np.full(n - 1, 0.4), np.full(n, 10.0)])

    def whole(*_):
        raise AssertionError("walked by a heap")

    monkeypatch.setattr(g, "distances", whole)
    assert g.steiner_voronoi(cost, [5_000, 5_003, 5_010]) == list(range(5_000, 5_010))
    dist, _, most = g._regions(cost, [5_000, 5_003, 5_010])
    assert most == pytest.approx(2.8) and np.isfinite(dist).sum() < 20


def test_the_mixture_makes_no_row_for_a_question_and_a_chunk(spark, monkeypatch):
    rng = np.random.default_rng(1)
    names = [f"w{i}" for i in range(40)]
    texts = [[names[int(x)] for x in rng.zipf(1.4, 30) % 40] for _ in range(150)]
    vec = rng.standard_normal((190, 8)).astype(np.float32)
    chunks = spark.createDataFrame([(f"c{i % 75}:{i // 75}", len(t), t, v.tolist()) for i, (t, v) in enumerate(zip(texts, vec))], "chunk_key string, n_tok int, tokens array<string>, vec array<float>")
    counts = chunks.select("chunk_key", "n_tok", F.explode("tokens").alias("term")).groupBy("chunk_key", "n_tok", "term").agg(F.count("*").alias("cnt"))
    asked = [(i, " ".join(rng.choice(names, 6).tolist()) if i % 9 else "nothing", v.tolist()) for i, v in enumerate(vec[150:])]
    q = spark.createDataFrame([*asked, (90, None, vec[0].tolist())], "qid long, text string, qvec array<float>")
    cos = chunks.crossJoin(q).select("qid", "chunk_key", F.aggregate(F.zip_with("vec", "qvec", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, b: a + b).alias("ms"))
    both = retrieval.fuse(cos, retrieval.bm25(q, counts, retrieval.chunk_stats(chunks)))
    want = {(r.qid, r.rk): r for r in retrieval.best(both.withColumn("hs", F.round("hs", 6)), 5, "hs", "chunk_key").collect()}

    def pairs(*_):
        raise AssertionError("a row for each question and chunk")

    monkeypatch.setattr(retrieval, "bm25", pairs)
    monkeypatch.setattr(retrieval, "COMMON", 5)
    monkeypatch.setattr(retrieval, "ITEMS", 64)
    got = retrieval.fused_top(q, chunks, counts, FuseSpec()).collect()
    assert len(got) == len(want) == 41 * 5
    for r in got:
        x = want[r.qid, r.rk]
        assert r.hs == pytest.approx(x.hs, abs=2e-6) and r.bm25 == pytest.approx(x.bm25, abs=1e-6) or r.chunk_key == x.chunk_key


def test_the_best_of_blocks_with_ties():
    rng = np.random.default_rng(2)
    scores, names = rng.integers(0, 6, (7, 90)) / 10, np.array([f"n{i:02}" for i in rng.permutation(90)], object)
    held = retrieval.Best(7, 4)
    for at in range(0, 90, 13):
        held.add(0, scores[:4, at : at + 13], names[at : at + 13])
        held.add(4, scores[4:, at : at + 13], names[at : at + 13])
        held._cut()
    (q, name, s), = held.rows()
    for i in range(7):
        assert list(zip(-s[q == i], name[q == i])) == sorted(zip(-scores[i], names))[:4]


def test_one_search_serves_smaller_ones(spark, sf, monkeypatch):
    """Without growth, without trees and with fewer passages, rows equal those of searches of their own, and no other search runs."""
    from evigraph.plans import search as se
    from evigraph.queries import method

    index, q = method.index_of(spark, sf), method.questions_of(spark, sf).where("qid % 4 = 0")
    bare = se.replace(index.cfg, tree=se.replace(index.cfg.tree, method="none"))
    asks = [(index.cfg, False), (bare, False), (index.cfg, True)]
    want = [sorted(se.search(index, q, cfg, grow=grow, k=5).drop("candidates").collect()) for cfg, grow in asks]
    ran, search = [], se.search
    monkeypatch.setattr(se, "search", lambda *a, **k: ran.append(a) or search(*a, **k))
    se.searched(index, q, k=10)
    got = [sorted(se.searched(index, q, cfg, grow=grow).drop("candidates").collect()) for cfg, grow in asks]
    assert len(ran) == 1 and got == want


def test_many_texts_have_the_vectors_of_each(spark):
    from evigraph.functions.encoder import HashEncoder

    texts, one = ["red bolt red", None, "", "a b c d e", "steel bolt"] * 3, HashEncoder()
    assert (one.many(texts) == np.array([one.one(t) for t in texts])).all()
