"""Registered queries against DuckDB on the smallest tables."""

import ast
import decimal
from pathlib import Path

import duckdb
import pytest

from evigraph.plans import baselines, search
from evigraph.queries import core, method

ORACLES = {k: s for m in core.MODULES for k, s in m.ORACLES.items()}
QUERIES = {k: f for m in core.MODULES for k, f in m.QUERIES.items()}
SOME = "p_chunks p_doc_freq p_entity_score p_select_chunk_max g_topk_vectors g_filter_overlap b_neighbourhood_low b_ppr_sum_star udf_matrix_topk p_select_rank_cap p_relations_adjacent p_edge_union g_topk_facts g_ppr_push g_voronoi h_bm25 h_fuse_raw b_keyword b_community_round e_macro_recall e_hit_rate w_fact_ppr w_grid_entities src_html_text join_asof_events join_interval agg_cube_lang_source win_rank_family sql_recursive_reach udtf_chunk stream_df_counts stream_late".split()


def plain(v):
    if isinstance(v, (float, decimal.Decimal)):
        return repr(round(float(v), 6) + 0.0)
    return str(v)


@pytest.fixture(scope="session")
def con(sf):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_query_matches_sql(spark, con, sf, name):
    df = QUERIES[name](spark, sf)
    rel = con.execute(ORACLES[name])
    cols = sorted(df.columns)
    own = [x[0] for x in rel.description]
    assert sorted(own) == cols
    want = sorted(tuple(plain(r[own.index(c)]) for c in cols) for r in rel.fetchall())
    assert sorted(tuple(plain(r[c]) for c in cols) for r in df.collect()) == want


@pytest.mark.parametrize("name", ["g_evidence_subgraph", "g_grow_sum", "b_dense", "b_twin_tree", "b_communities_global", "b_expert_mix", "w_class_narrow", "p_synonym_lsh"])
def test_query_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_synonyms_are_found(spark, sf):
    rows = QUERIES["p_synonym_recall"](spark, sf).collect()
    assert all(r.recall is None or r.recall >= 0.95 for r in rows) and any(r.pairs for r in rows)
    assert QUERIES["p_index_stats"](spark, sf).first().synonyms > 0


def test_growth_and_trees_keep_their_bounds(spark, sf):
    steps = QUERIES["e_growth_steps"](spark, sf).first()
    assert steps.beyond == 0 and 0 < steps.added <= steps.candidates
    rows = {r.method: r.ratio for r in QUERIES["e_cost_vs_optimum"](spark, sf).collect()}
    assert 1 <= rows["voronoi"] <= 2 and 1 <= rows["closure"] <= 2 and rows["chain"] >= 1


def test_ablations_move_as_reported(spark, sf):
    rows = {r.variant: r for r in QUERIES["w_ablation"](spark, sf).collect()}
    assert rows["graph_only"].tok_in != rows["full"].tok_in
    assert rows["tree_only"].nodes <= rows["full"].nodes
    assert rows["tree_only"].tree_nodes == rows["full"].tree_nodes
    assert rows["fused_only"].nodes == 0 and rows["fused_only"].tok_in < rows["full"].tok_in


def test_comparison_tables(spark, sf):
    rows = {r.system: r for r in QUERIES["w_compare_reason"](spark, sf).collect()}
    assert len(rows) == 14 and rows["none"].tok_in < rows["compressed"].tok_in < rows["dense"].tok_in
    assert rows["method"].hit_rate >= rows["none"].hit_rate == 0 and rows["method"].lcs > 0


def test_both_ways_of_searching_agree(spark, sf):
    """All questions over one index: by a broadcast graph and by joins. Trees are compared by their ends, as parallel edges may tie."""
    index, q = method.index_of(spark, sf), method.questions_of(spark, sf)
    ends = lambda ids: sorted(tuple(sorted(e.split("|")[::2])) for e in ids)
    here, there = ({r.qid: r for r in search.search(index, q, local=way).collect()} for way in (True, False))
    assert here.keys() == there.keys() and any(r.grown for r in here.values())
    for k, x in here.items():
        y = there[k]
        for c in ("facts", "kept", "terminals", "tree_nodes", "nodes", "candidates", "top_entities"):
            assert x[c] == y[c], (k, c)
        assert ends(x.tree) == ends(y.tree) and [p.chunk_key for p in x.passages] == [p.chunk_key for p in y.passages]
        assert len(x.grown) == len(y.grown) and y.ratio == pytest.approx(x.ratio, rel=1e-3)


def test_search_gathers_no_graph_on_the_driver(spark, sf, monkeypatch):
    """Each task reads the graph; the driver and its broadcasts see questions only."""
    index, q = method.index_of(spark, sf), method.questions_of(spark, sf)
    sizes, kept, frame = [], type(spark.sparkContext).broadcast, type(q)

    def refuse(df):
        raise AssertionError("gathered on the driver")

    monkeypatch.setattr(frame, "toPandas", refuse)
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, value: sizes.append(len(value)) or kept(self, value))
    found, prize = search.search(index, q, local=True), baselines.prize_subgraph(index, q)
    assert sizes == [q.count()] * 2
    monkeypatch.undo()
    assert found.count() == prize.count() == q.count() and found.where("tree_nodes > 0").count() > 0


def test_the_join_search_refuses_other_settings(spark, sf):
    index, q = method.index_of(spark, sf), method.questions_of(spark, sf)
    with pytest.raises(ValueError, match="frozen"):
        search.search(index, q, search.replace(index.cfg, grow=search.replace(index.cfg.grow, threshold="mean")), local=False)


def test_nothing_imports_the_training_data_package():
    root = Path(__file__).resolve().parent.parent / "evigraph"
    for p in root.rglob("*.py"):
        if "llm" not in p.parts:
            for node in ast.walk(ast.parse(p.read_text())):
                names = [node.module or ""] if isinstance(node, ast.ImportFrom) else [a.name for a in node.names] if isinstance(node, ast.Import) else []
                assert not any(n.startswith("evigraph.llm") for n in names), p


def test_cost_vs_optimum_gathers_no_leaves(spark, sf):
    """Only nations and the five suppliers that are terminals reach the driver, and the costs are those over all suppliers."""
    import numpy as np
    from pyspark.sql import Row

    from evigraph.functions.graphs import LocalGraph
    from evigraph.queries import baselines

    whole = method.star_costs(spark, sf).where("src not like 'c:%'").select("src", "dst", "cost").collect()
    inner = baselines._inner_star(method.star_costs(spark, sf)).collect()
    assert len(inner) == sum(r.src.startswith("n:") for r in whole) + 5
    whole += [Row(src="w:", dst=x, cost=0.7) for x in sorted({r.dst for r in whole if r.dst.startswith("r:")})]
    names = sorted({x for r in whole for x in (r.src, r.dst)})
    g, cost = LocalGraph(len(names), np.array([[names.index(r.src), names.index(r.dst)] for r in whole])), np.array([r.cost for r in whole])
    ends = [names.index(x) for x in [x for x in names if x.startswith("s:")][:5]]
    want = {"voronoi": g.steiner_voronoi, "closure": g.steiner_closure, "chain": g.path_chain}
    for r in QUERIES["e_cost_vs_optimum"](spark, sf).collect():
        assert r.cost == pytest.approx(cost[want[r.method](cost, ends)].sum()) and r.optimum == pytest.approx(g.steiner_exact(cost, ends))


def test_cross_grid_reads_a_given_table(spark, con, sf):
    df = QUERIES["join_cross_grid"](spark, sf)
    assert sorted((r.n, r.tau) for r in df.collect()) == [(n, t) for n in (1, 3, 5, 7) for t in (0.1, 0.3, 0.5, 0.7)] == sorted(con.execute(ORACLES["join_cross_grid"]).fetchall())
    assert any("lineitem" in f for f in df.inputFiles())
