"""Queries of baselines, measures and workloads."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Row, Window
from pyspark.sql import functions as F

from evigraph.operators import entities as ents
from evigraph.operators import measures as me
from evigraph.operators import textprep
from evigraph.operators.influence import power, seeds_of
from evigraph.operators.kg import both_ways, entity_key, passage_edges
from evigraph.operators.retrieval import best, candidate_labels, fused_top, kept_facts, top_vectors
from evigraph.plans import baselines as ba
from evigraph.plans import index as ix
from evigraph.plans import search as se
from evigraph.queries.method import BM_SQL, QV, _cos_rows, chunk_sql, index_of, ppr_sql, questions_of, score_sql, star_costs, star_scores, star_seeds, star_sql, star_tree, select_sql
from evigraph.runtime import once, written
from evigraph.sources import corpora
from evigraph.specs import Config, EntitySpec

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def _ranked(rows: DataFrame) -> DataFrame:
    return rows.select("qid", "chunk_key", F.round("score", 6).alias("score"), "rk")


# ---- baselines over the documents' index ----


@query("WITH top AS (SELECT lang AS label, count(*) AS n FROM documents GROUP BY lang ORDER BY n DESC, label DESC LIMIT 1) SELECT item_id AS qid, label AS pred FROM benchmark, top")
def b_none(spark, d):
    q = corpora.table(spark, d, "benchmark").select(F.col("item_id").alias("qid"))
    return ba.none(q, corpora.table(spark, d, "documents").select(F.col("lang").alias("label")))


@query(f"WITH {QV} SELECT qid, edge_id, ms, rk::INTEGER AS rk FROM r WHERE rk <= 5")
def b_dense_vectors(spark, d):
    return best(_cos_rows(spark, d), 5, "ms", "edge_id", digits=4).select("qid", "edge_id", "ms", "rk")


def _over_index(f, *cols):
    return lambda spark, d: f(index_of(spark, d), questions_of(spark, d)) if cols else _ranked(f(index_of(spark, d), questions_of(spark, d)))


for _n, _f in {"b_dense": ba.dense, "b_summary_tree": ba.summary_tree, "b_twin_tree": ba.twin_tree, "b_expert_mix": ba.expert_mix, "b_communities": ba.community_reports, "b_ppr_passage": ba.ppr_passage, "b_ppr_sum": ba.ppr_sum, "b_neighbourhood": ba.neighbourhood}.items():
    query(name=_n)(_over_index(_f))
query(name="b_communities_global")(lambda spark, d: _ranked(ba.community_reports(index_of(spark, d), questions_of(spark, d), mode="global")))
query(name="b_compressed")(_over_index(ba.compressed, "all"))
query(name="b_prize_subgraph")(_over_index(ba.prize_subgraph, "all"))


@query("WITH " + BM_SQL + ", r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(bm25, 6) DESC, chunk_key) AS rk FROM bm) SELECT qid, chunk_key, round(bm25, 4) AS score, rk::INTEGER AS rk FROM r WHERE rk <= 5")
def b_bm25(spark, d):
    from evigraph.queries.method import _bm25

    return best(_bm25(spark, d).withColumnRenamed("bm25", "score"), 5, "score", "chunk_key").select("qid", "chunk_key", F.round("score", 4).alias("score"), "rk")


LOW_SQL = "WITH " + select_sql() + ", qw AS (SELECT DISTINCT item_id AS qid, unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS term FROM benchmark)"


def _chosen(spark, d):
    return ents.select_words(textprep.chunk(corpora.documents(spark, d)), EntitySpec())


def _named(spark, d):
    q = corpora.table(spark, d, "benchmark").select(F.col("item_id").alias("qid"), F.explode(F.array_distinct(textprep.tokens(F.col("text")))).alias("term"))
    return q.distinct()


@query(LOW_SQL + " SELECT DISTINCT qid, 'e:' || term AS node_key FROM qw WHERE term IN (SELECT term FROM chosen)")
def b_keyword(spark, d):
    nodes = _chosen(spark, d).select("term").distinct().select(entity_key().alias("node_key"), F.lit("entity").alias("kind"), F.col("term").alias("text"))
    return ba.keyword_nodes(nodes, corpora.table(spark, d, "benchmark").select(F.col("item_id").alias("qid"), "text")).distinct()


@query(LOW_SQL + ", m AS (SELECT qid, chunk_key, count(DISTINCT term) AS score FROM qw JOIN chosen USING (term) GROUP BY qid, chunk_key), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, chunk_key) AS rk FROM m) SELECT qid, chunk_key, CAST(score AS DOUBLE) AS score, rk::INTEGER AS rk FROM r WHERE rk <= 5")
def b_neighbourhood_low(spark, d):
    seeds = _named(spark, d).select("qid", entity_key().alias("node_key"))
    return ba.touching(seeds, both_ways(passage_edges(_chosen(spark, d)).select("src", "dst")), 5).select("qid", "chunk_key", "score", "rk")


@query("WITH " + star_sql(False) + ", v AS (SELECT d.a AS node, l.k AS label, count(*) AS n FROM d JOIN (SELECT DISTINCT a AS k FROM d) l ON l.k = d.b GROUP BY ALL), w AS (SELECT node, label, row_number() OVER (PARTITION BY node ORDER BY n DESC, label) AS r FROM v) SELECT node AS node_key, label FROM w WHERE r = 1")
def b_community_round(spark, d):
    """One round of votes over the star schema."""
    return ba.communities(corpora.star_edges(spark, d, orders=False), rounds=1)


@query(ppr_sql(12) + ", h AS (SELECT d.b AS k, sum(s) AS s FROM s12 JOIN d ON d.a = s12.k WHERE d.b LIKE 'n:%' GROUP BY d.b) SELECT k AS node_key, round(s, 6) AS score FROM h")
def b_ppr_sum_star(spark, d):
    """A passage's score as the sum over its entities; nations stand for passages."""
    e = corpora.star_edges(spark, d)
    return ba.entity_sums(e, power(e, star_seeds(spark), sweeps=12), "n:").select("node_key", F.round("score", 6).alias("score"))


@query()
def b_tree(spark, d):
    return se.searched(index_of(spark, d), questions_of(spark, d), grow=False).select("qid", "tree_nodes", F.size("tree").alias("tree_edges"), F.round("ratio_tree", 6).alias("ratio"))


# ---- measures ----


#: Language told by the nearest labelled vector, on embeddings: predictions with gold labels for the measures.
PRED_SQL = f"WITH {QV}, preds AS (SELECT r.qid, CAST(r.label AS VARCHAR) AS pred, CAST(g.label AS VARCHAR) AS gold FROM r JOIN embeddings g ON g.vec_id = r.qid WHERE rk = 1)"


def _preds(spark, d):
    near = best(_cos_rows(spark, d), 1, "ms", "edge_id", digits=4).select("qid", F.col("label").cast("string").alias("pred"))
    gold = corpora.table(spark, d, "embeddings").select(F.col("vec_id").alias("qid"), F.col("label").cast("string").alias("gold"))
    return near.join(gold, "qid")


@query(PRED_SQL + " SELECT avg(CASE WHEN pred = gold THEN 1.0 ELSE 0 END) AS accuracy FROM preds")
def e_accuracy(spark, d):
    return me.accuracy_exact(_preds(spark, d))


@query(PRED_SQL + " SELECT round(avg(x), 6) AS macro_recall FROM (SELECT gold, avg(CASE WHEN pred = gold THEN 1.0 ELSE 0 END) AS x FROM preds GROUP BY gold)")
def e_macro_recall(spark, d):
    return me.macro_recall(_preds(spark, d)).select(F.round("macro_recall", 6).alias("macro_recall"))


@query(PRED_SQL + " SELECT avg(CASE WHEN CAST(pred AS INTEGER) >= 5 THEN 1.0 ELSE 0 END) AS out_of_label_rate FROM preds")
def e_out_of_label(spark, d):
    labels = corpora.table(spark, d, "embeddings").where("label < 5").select(F.col("label").cast("string").alias("label"))
    return me.out_of_label_rate(_preds(spark, d), labels)


PAIR_SQL = "p AS (SELECT conv_id, turn, text, role, lead(text) OVER w AS nt, lead(role) OVER w AS nr FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)), qa AS (SELECT conv_id, turn, text AS answer, nt AS gold FROM p WHERE role = 'user' AND nr = 'assistant')"


def _qa(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = corpora.table(spark, d, "conversations").withColumns({"nt": F.lead("text").over(w), "nr": F.lead("role").over(w)})
    return c.where("role = 'user' and nr = 'assistant'").select("conv_id", "turn", F.col("text").alias("answer"), F.col("nt").alias("gold"))


TOK = "regexp_extract_all(lower({0}), '[\\p{{L}}\\p{{N}}]+')"


@query(
    f"WITH {PAIR_SQL}, t AS (SELECT list_distinct({TOK.format('answer')}) AS a, list_distinct({TOK.format('gold')}) AS g FROM qa), f AS (SELECT 2.0 * len(list_intersect(a, g)) / greatest(len(a) + len(g), 1) AS f FROM t) SELECT avg(CASE WHEN f >= 0.8 THEN 1.0 WHEN f >= 0.3 THEN 0.5 ELSE 0 END) AS accuracy FROM f"
)
def e_graded(spark, d):
    return me.accuracy_graded(_qa(spark, d))


@query(f"WITH {PAIR_SQL} SELECT conv_id, turn, CASE WHEN list_has_all({TOK.format('gold')}, {TOK.format('answer')}) THEN 1.0 ELSE 0.0 END AS coverage FROM qa")
def e_coverage(spark, d):
    return _qa(spark, d).select("conv_id", "turn", me.coverage(F.array("answer"), F.col("gold")).alias("coverage"))


@query(f"WITH {PAIR_SQL}, c AS (SELECT conv_id, turn, list_filter(list_transform(regexp_split_to_array(answer, '[.!?\\n]+'), lambda x: trim(x, ' ')), lambda x: x <> '') AS c, gold FROM qa) SELECT conv_id, turn, round(len(list_filter(c, lambda x: contains(gold, x))) / len(c), 6) AS fs FROM c WHERE len(c) > 0")
def e_faithfulness(spark, d):
    return _qa(spark, d).select("conv_id", "turn", F.round(me.faithfulness(F.col("answer"), F.col("gold")), 6).alias("fs")).where("fs is not null")


@query(f"WITH {PAIR_SQL} SELECT round(avg(len({TOK.format('answer')})), 6) AS tok_in, round(avg(len({TOK.format('gold')})), 6) AS tok_out FROM qa")
def e_tokens(spark, d):
    rows = _qa(spark, d).select(F.col("answer").alias("prompt"), F.col("gold").alias("answer"))
    return me.token_cost(rows).select(F.round("tok_in", 6).alias("tok_in"), F.round("tok_out", 6).alias("tok_out"))


@query()
def e_lcs(spark, d):
    return _qa(spark, d).select("conv_id", "turn", F.round(me.lcs_ratio(F.col("answer"), F.col("gold")), 6).alias("lcs"))


HIT_SQL = "WITH " + BM_SQL + """, rk AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(bm25, 6) DESC, chunk_key) AS rk FROM bm), gold AS (SELECT item_id AS qid, CAST(doc_id AS VARCHAR) AS doc_key FROM benchmark b JOIN documents d ON contains(d.text, b.text)),
    f AS (SELECT rk.qid, min(rk) AS rk FROM rk JOIN gold ON gold.qid = rk.qid AND gold.doc_key = split_part(chunk_key, ':', 1) WHERE rk <= 5 GROUP BY rk.qid), q AS (SELECT DISTINCT qid FROM gold)
    SELECT round(avg(CASE WHEN rk IS NULL THEN 0.0 ELSE 1.0 END), 6) AS hit_rate, round(avg(coalesce(1.0 / rk, 0)), 6) AS mrr, count(*) AS questions FROM q LEFT JOIN f USING (qid)"""


def _gold(spark, d):
    return corpora.fact_questions(spark, d).select("qid", F.explode("evidence").alias("doc_key"))


@query(HIT_SQL)
def e_hit_rate(spark, d):
    return me.hit_rate(b_bm25(spark, d), _gold(spark, d), 5).select(F.round("hit_rate", 6).alias("hit_rate"), F.round("mrr", 6).alias("mrr"), "questions")


@query()
def e_graph_and_subgraph_sizes(spark, d):
    r = se.searched(index_of(spark, d), questions_of(spark, d))
    return r.agg(F.avg("tree_nodes").alias("tree_nodes"), F.avg(F.size("tree")).alias("tree_edges"), F.avg("nodes").alias("evidence_nodes"), F.avg(F.size("tree") + F.size("grown")).alias("evidence_edges"))


@query()
def e_growth_steps(spark, d):
    """Edges added against the edges that a frozen threshold could admit."""
    r = se.searched(index_of(spark, d), questions_of(spark, d))
    return r.agg(F.round(F.avg(F.size("grown")), 3).alias("added"), F.round(F.avg("candidates"), 3).alias("candidates"), F.max((F.size("grown") > F.col("candidates")).cast("int")).alias("beyond"))


def _inner_star(costs: DataFrame, terminals: int = 5) -> DataFrame:
    """Edges of nations and of the suppliers that are terminals (first by key). Customers and other suppliers have one edge each, so no path between terminals and no least tree holds them."""
    first = costs.where("src like 's:%'").select("src").distinct().orderBy("src").limit(terminals)
    return costs.where("src like 'n:%'").unionByName(costs.join(F.broadcast(first), "src", "left_semi")).select("src", "dst", "cost")


@query()
def e_cost_vs_optimum(spark, d):
    """Tree costs over the least cost, over regions (tied to one root), nations and suppliers with five suppliers as terminals; trees are never over 2."""
    from evigraph.functions.graphs import LocalGraph

    rows = _inner_star(star_costs(spark, d)).collect()
    rows += [Row(src="w:", dst=x, cost=0.7) for x in sorted({r.dst for r in rows if r.dst.startswith("r:")})]
    names = sorted({x for r in rows for x in (r.src, r.dst)})
    no = {x: i for i, x in enumerate(names)}
    g, cost = LocalGraph(len(names), np.array([[no[r.src], no[r.dst]] for r in rows])), np.array([r.cost for r in rows])
    ends = [no[x] for x in [x for x in names if x.startswith("s:")][:5]]
    best_cost = g.steiner_exact(cost, ends)
    made = {"voronoi": g.steiner_voronoi, "closure": g.steiner_closure, "chain": g.path_chain}
    return spark.createDataFrame([(k, float(cost[f(cost, ends)].sum()), best_cost) for k, f in made.items()], "method string, cost double, optimum double").withColumn("ratio", F.round(F.col("cost") / F.col("optimum"), 6))


@query()
def e_stage_seconds(spark, d):
    """Seconds of index stages and, for all questions, of filtering, search, fused retrieval and answers."""
    watch, index, q = index_of(spark, d).watch, index_of(spark, d), questions_of(spark, d)
    rel = index.edges.where("kind = 'relation'")
    parts = {
        "map and filter": lambda: kept_facts(top_vectors(q, rel, index.cfg.map.k_facts, "edge_id"), index.cfg.map.floor),
        "score, tree, growth": lambda: se.search(index, q),
        "fused retrieval": lambda: fused_top(q, index.chunks, index.words, index.cfg.fuse),
        "answer": lambda: se.ask(index, q),
    }
    for name, run in parts.items():
        with watch.stage(name):
            run().write.format("noop").mode("overwrite").save()
    return spark.createDataFrame(sorted(watch.seconds.items()), "stage string, seconds double")


# ---- workloads ----


@query(ppr_sql(12) + ", r AS (SELECT k, s, row_number() OVER (ORDER BY round(s, 9) DESC, k) AS rk FROM s12 WHERE k LIKE 'o:%') SELECT k AS node_key, round(s, 7) AS score FROM r WHERE rk <= 100", "w_star_ppr")
def w_star_ppr(spark, d):
    s = power(corpora.star_edges(spark, d), star_seeds(spark), sweeps=12).where("node_key like 'o:%'")
    return s.orderBy(F.round("score", 9).desc(), "node_key").limit(100).select("node_key", F.round("score", 7).alias("score"))


@query()
def w_star_steiner(spark, d):
    return star_tree(spark, d).join(star_costs(spark, d), ["qid", "edge_id"]).select("qid", "edge_id", "cost")


@query()
def w_star_grow(spark, d):
    from evigraph.operators.steiner import grow_frozen
    from evigraph.queries.method import star_terminals

    return grow_frozen(star_tree(spark, d), star_terminals(spark), star_costs(spark, d), star_scores(spark, d))


FACT_SQL = score_sql(1, 2) + """, ent AS (SELECT chunk_key, term FROM scores WHERE df <= greatest(2, 0.2 * n_chunks)),
    e AS (SELECT 'e:' || term AS src, 'p:' || chunk_key AS dst FROM ent), d AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e), deg AS (SELECT a, count(*) AS g FROM d GROUP BY a), w AS MATERIALIZED (SELECT d.a, d.b, 1.0 / g AS w FROM d JOIN deg ON d.a = deg.a),
    qw AS (SELECT DISTINCT item_id AS qid, 'e:' || unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS k FROM benchmark), sd AS (SELECT qid, k FROM qw WHERE k IN (SELECT src FROM e)), sn AS (SELECT qid, count(*) AS n FROM sd GROUP BY qid), s0 AS (SELECT qid, k, 1.0 / n AS s FROM sd JOIN sn USING (qid)), p AS (SELECT qid, k, 0.5 * s AS x FROM s0)"""


def _fact_sql(sweeps: int = 3) -> str:
    text = "WITH " + FACT_SQL
    for i in range(1, sweeps + 1):
        text += f", s{i} AS MATERIALIZED (SELECT qid, k, sum(x) AS s FROM (SELECT qid, w.b AS k, 0.5 * s * w AS x FROM s{i - 1} JOIN w ON w.a = s{i - 1}.k UNION ALL SELECT qid, k, x FROM p) GROUP BY qid, k)"
    return text + f", r AS (SELECT qid, k, s, row_number() OVER (PARTITION BY qid ORDER BY round(s * 0.05, 9) DESC, k) AS rk FROM s{sweeps} WHERE k LIKE 'p:%') SELECT qid, k AS node_key, round(s * 0.05, 7) AS score, rk::INTEGER AS rk FROM r WHERE rk <= 5"


@query(_fact_sql())
def w_fact_ppr(spark, d):
    """Flagship slice: entities and passages of the documents, influence seeded on the words of the benchmark items, best passages."""
    from evigraph.operators.influence import balance

    scores = ents.score_chunks(textprep.chunk(corpora.documents(spark, d)), EntitySpec(max_n=1))
    chosen = scores.where(F.col("df") <= F.greatest(F.lit(2.0), 0.2 * F.col("n_chunks")))
    edges = written(chosen.select(F.concat(F.lit("e:"), "term").alias("src"), F.concat(F.lit("p:"), "chunk_key").alias("dst")), "edges")
    words = _named(spark, d).select("qid", F.concat(F.lit("e:"), "term").alias("node_key"))
    seeds = seeds_of(words.join(edges.select(F.col("src").alias("node_key")).distinct(), "node_key", "left_semi"))
    s = balance(power(edges, seeds, sweeps=3)).where("node_key like 'p:%'")
    return best(s, 5, "score", "node_key", digits=9).select("qid", "node_key", F.round("score", 7).alias("score"), "rk")


SYSTEMS = {
    "dense": ba.dense, "bm25": ba.sparse, "ppr_passage": ba.ppr_passage, "ppr_sum": ba.ppr_sum, "neighbourhood": ba.neighbourhood, "communities": ba.community_reports,
    "summary_tree": ba.summary_tree, "twin_tree": ba.twin_tree, "prize_subgraph": ba.prize_passages, "expert_mix": ba.expert_mix,
}


def answers_of(index, q, system: str) -> DataFrame:
    """Answers of a system: ``method`` and its ablations, ``none`` (no context), ``compressed`` (half of the dense passages' words) or one of SYSTEMS."""
    if system == "method" or system in se.VARIANTS:
        return se.ask(index, q, variant="full" if system == "method" else system)
    if system == "none":
        return se.answered(index, q.select("qid", "text"), ba.dense(index, q).where("false"))
    if system == "compressed":
        got = se.answered(index, q.select("qid", "text"), ba.dense(index, q)).join(ba.compressed(index, q).select("qid", "kept"), "qid", "left")
        prompt = se.build_prompt(F.col("text"), F.lit(""), F.array(F.coalesce("kept", F.lit(""))), se.INSTRUCTION)
        return got.withColumn("prompt", prompt).withColumn("tok_in", se.word_count(F.col("prompt"))).drop("kept")
    return se.answered(index, q.select("qid", "text"), SYSTEMS[system](index, q))


def scored(index, q, gold: DataFrame, need: DataFrame, systems) -> DataFrame:
    """One row a system: hit rate of documents (gold: qid, doc_key), graded accuracy and common-subsequence share against ``want``, coverage of ``parts``
    (need: qid, want, parts), faithfulness to the prompt, words in and out, subgraph sizes."""
    out = None
    for name in systems:
        a = written(answers_of(index, q, name), "answers")
        hits = me.hit_rate(a.select("qid", F.posexplode("chunk_keys").alias("i", "chunk_key")).withColumn("rk", F.col("i") + 1), gold, 5).select("hit_rate", "mrr")
        b = a.join(need, "qid")
        cells = {
            "accuracy": F.avg(me.graded(F.col("answer"), F.col("want"))), "lcs": F.avg(me.lcs_ratio(F.col("answer"), F.col("want"))), "coverage": F.avg(me.coverage(F.col("parts"), F.concat_ws(" ", "answer", "evidence"))),
            "faithfulness": F.avg(me.faithfulness(F.col("answer"), F.col("prompt"))), "tok_in": F.avg("tok_in"), "tok_out": F.avg("tok_out"), "tree_nodes": F.avg("tree_nodes"), "nodes": F.avg("nodes"),
        }
        # Each side has one row.
        row = b.agg(F.count("*").alias("questions"), *[F.round(c, 4).alias(n) for n, c in cells.items()]).join(hits.select(F.round("hit_rate", 6).alias("hit_rate"), F.round("mrr", 6).alias("mrr")))
        row = row.withColumn("system", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


ALL = ("method", "none", "dense", "compressed", "bm25", *[n for n in SYSTEMS if n not in ("dense", "bm25")], "tree_only")


def _facts(spark, d):
    """W1: benchmark items over documents; the passages of their documents are the evidence, an item's own words the wanted answer."""
    need = corpora.table(spark, d, "benchmark").select(F.col("item_id").alias("qid"), F.col("text").alias("want"), F.array("text").alias("parts"))
    return index_of(spark, d), questions_of(spark, d), once(spark, ("gold", d), lambda: written(_gold(spark, d), "gold")), need


def _vectors(spark, d, name, rows):
    return once(spark, (name, d), lambda: written(se.with_vectors(rows.select("qid", "text"), 64), "questions"))


def _reasons(spark, d):
    """W2: first user turn of a conversation; the next assistant turn is the wanted answer and its document the evidence."""
    qs = corpora.reasoning_questions(spark, d)
    need = qs.select("qid", F.col("gold").alias("want"), me.claims(F.col("gold")).alias("parts"))
    return _reason_index(spark, d), _vectors(spark, d, "reason questions", qs), qs.select("qid", F.explode("evidence").alias("doc_key")), need


def _summaries(spark, d):
    """W3: for each source the two commonest entities are asked about; its five commonest entities are to be covered, by its documents."""
    index = index_of(spark, d)
    src = corpora.table(spark, d, "documents").where("source is not null").select(F.col("doc_id").cast("string").alias("doc_key"), "source")
    e = index.entities.join(index.chunks.select("chunk_key", "doc_key"), "chunk_key").join(src, "doc_key").groupBy("source", "term").agg(F.count("*").alias("n"))
    r = best(e, 5, "n", "term", by="source").groupBy("source").agg(F.array_sort(F.collect_list(F.struct("rk", "term"))).alias("x"))
    qid = F.crc32(F.col("source").cast("binary")).alias("qid")
    text = F.concat_ws(" and ", F.try_element_at(F.col("x.term"), F.lit(1)), F.try_element_at(F.col("x.term"), F.lit(2))).alias("text")
    q = once(spark, ("summary", d), lambda: written(r.select(qid, text, F.col("x.term").alias("parts"), F.concat_ws(" ", "x.term").alias("want")), "summary"))
    return index, _vectors(spark, d, "summary questions", q), src.select(qid, "doc_key"), q.select("qid", "want", "parts")


def _creations(spark, d):
    """W4: the last turn of each conversation is asked for; it is wanted itself, and claims are held against the prompt."""
    w = Window.partitionBy("conv_id").orderBy(F.desc("turn"))
    last = corpora.table(spark, d, "conversations").withColumn("r", F.row_number().over(w)).where("r = 1").select(F.col("conv_id").alias("qid"), "text", F.concat_ws("-", "conv_id", "turn").alias("doc_key"))
    return _reason_index(spark, d), _vectors(spark, d, "create questions", last), last.select("qid", "doc_key"), last.select("qid", F.col("text").alias("want"), me.claims(F.col("text")).alias("parts"))


def _low(spark, d):
    """W7: the language with fewest documents, as its own corpus, asked by the benchmark items."""
    few = corpora.table(spark, d, "documents").where("lang is not null").groupBy("lang").agg(F.count("*").alias("n")).agg(F.min_by("lang", F.struct("n", "lang")).alias("lang"))
    docs = corpora.table(spark, d, "documents").join(F.broadcast(few), "lang").select(F.col("doc_id").cast("string").alias("doc_key"), "text")
    index = once(spark, ("low", d), lambda: ix.build(docs))
    _, q, gold, need = _facts(spark, d)
    return index, q, gold.join(docs.select("doc_key"), "doc_key", "left_semi").select("qid", "doc_key"), need


WORK = {"facts": _facts, "reason": _reasons, "summary": _summaries, "create": _creations}


def _table(load, systems):
    return lambda spark, d: scored(*load(spark, d), systems)


query(name="w_compare")(_table(_facts, ALL))
query(name="w_compare_reason")(_table(_reasons, ALL))
query(name="w_compare_summary")(_table(_summaries, ALL))
query(name="w_compare_create")(_table(_creations, ALL))
query(name="w_compare_low_resource")(_table(_low, ("method", "dense", "ppr_passage", "ppr_sum")))
ABLATED = tuple(v for v in se.VARIANTS if v != "llm_entities")
for _n in ("reason", "summary", "create"):
    query(name=f"w_ablation_{_n}")(_table(WORK[_n], ABLATED))


@query()
def w_ablation(spark, d):
    """W10 on W1: all variants, that with a model's entities over an index of its own."""
    index, q, gold, need = _facts(spark, d)
    model = once(spark, ("model entities", d), lambda: ix.build(corpora.documents(spark, d), extract_entities=ents.extract_with_model))
    own = scored(model, q, gold, need, ("full",)).withColumn("system", F.lit("llm_entities"))
    return scored(index, q, gold, need, ABLATED).unionByName(own).withColumnRenamed("system", "variant")


@query()
def w_sensitivity(spark, d):
    """W8: hits by largest n-gram and by entity threshold (on the scale of a chunk's largest score); each cell builds its own index."""
    _, q, gold, _ = _facts(spark, d)
    out = None
    for n, tau in sorted({(b, 0.5) for b in (1, 3, 5, 7)} | {(3, t) for t in (0.1, 0.3, 0.5, 0.7)}):
        cfg = Config(entity=EntitySpec(max_n=n, tau=tau, mode="chunk_max"))
        index = once(spark, ("grid", n, tau, d), lambda c=cfg: ix.build(corpora.documents(spark, d), c, synonyms=False))
        row = me.hit_rate(ba.ppr_passage(index, q), gold, 5).select(F.lit(n).alias("max_n"), F.lit(tau).alias("tau"), F.round("hit_rate", 6).alias("hit_rate"), F.round("mrr", 6).alias("mrr"))
        row = row.join(index.entities.agg(F.countDistinct("term").alias("entities")))  # one row each
        out = row if out is None else out.unionByName(row)
    return out


@query()
def w_fact_method(spark, d):
    return se.ask(index_of(spark, d), corpora.fact_questions(spark, d)).select("qid", F.array_join("chunk_keys", ",").alias("chunks"), "answer", "tok_in", "tok_out", "nodes")


def _reason_index(spark, d):
    return once(spark, ("conversations", d), lambda: ix.build(corpora.conversations(spark, d)))


query(name="w_reason_method")(_table(_reasons, ("method",)))
query(name="w_summary_method")(_table(_summaries, ("method",)))
query(name="w_create_method")(_table(_creations, ("method",)))


def _classes(spark, d, label: str):
    corpus, tests = corpora.class_texts(spark, d, label)
    index = once(spark, ("classes", label, d), lambda: ix.build(corpus.select("doc_key", "text")))
    return index, corpus.select("doc_key", "label"), once(spark, ("tests", label, d), lambda: written(se.with_vectors(tests.select("qid", "text", "gold"), 64), "tests"))


def labelled(found: DataFrame, corpus: DataFrame, q: DataFrame) -> DataFrame:
    """qid, pred, gold, labels: candidate labels of the retrieved chunks, and of these the best chunk's."""
    named = found.select("qid", "chunk_key", "rk").withColumn("doc_key", F.substring_index("chunk_key", ":", 1)).join(corpus, "doc_key").select("qid", "chunk_key", "rk", "label")
    pred = named.groupBy("qid").agg(F.min_by("label", "rk").alias("pred"))
    labels = candidate_labels(found.select("qid", "chunk_key").join(named.select("chunk_key").distinct(), "chunk_key", "left_semi"), named.select("chunk_key", "label").distinct())
    return q.select("qid", "gold").join(pred, "qid", "left").join(labels, "qid", "left")


def _rates(p: DataFrame, corpus: DataFrame) -> DataFrame:
    """One row: accuracy, macro recall, share out of the label set, candidate labels a question."""
    p = written(p, "preds")
    out = me.accuracy_exact(p).join(me.macro_recall(p)).join(me.out_of_label_rate(p, corpus)).join(p.agg(F.avg(F.size("labels")).alias("candidates")))
    return out.select(*[F.round(c, 6).alias(c) for c in out.columns])


def classified(spark, d, label: str, k: int = 5) -> DataFrame:
    """Every text by its k nearest labelled chunks."""
    index, corpus, q = _classes(spark, d, label)
    return labelled(top_vectors(q, index.chunks, k, "chunk_key"), corpus, q)


def _class_query(label):
    return lambda spark, d: _rates(classified(spark, d, label), _classes(spark, d, label)[1])


for _n, _l in {"narrow": "lang", "wide": "wide", "quality": "quality", "toxic": "toxic"}.items():
    query(name=f"w_class_{_n}")(_class_query(_l))


def _class_table(label):
    """W5, W6 and W12 by system, through the labels of what each retrieves, for texts whose id is divisible by 50."""

    def run(spark, d):
        index, corpus, q = _classes(spark, d, label)
        q, out = once(spark, ("fifty", label, d), lambda: written(q.where("qid % 50 = 0"), "tests")), None
        systems = {"method": lambda i, x: fused_top(x, i.chunks, i.words, i.cfg.fuse).unionByName(se.retrieved_by(se.searched(i, x), "passages").select("qid", "chunk_key", (F.col("rk") + 5).alias("rk")), allowMissingColumns=True), **SYSTEMS}
        for name in systems:
            p = labelled(systems[name](index, q).select("qid", "chunk_key", "rk"), corpus, q)
            row = _rates(p, corpus).withColumn("system", F.lit(name))
            out = row if out is None else out.unionByName(row)
        free = q.select("qid", "gold", F.substring_index("text", " ", -1).alias("pred"), F.array().cast("array<string>").alias("labels"))
        return out.unionByName(_rates(free, corpus).withColumn("system", F.lit("none")))

    return run


query(name="w_compare_class_narrow")(_class_table("lang"))
query(name="w_compare_class_wide")(_class_table("wide"))


@query()
def w_outlabel(spark, d):
    """W12: out-of-label share of the candidate-label answer and of free naming (the last word of the answer's passage)."""
    p, labels = written(classified(spark, d, "lang"), "preds"), _classes(spark, d, "lang")[1]
    free = corpora.class_texts(spark, d, "lang")[1].select("qid", F.substring_index("text", " ", -1).alias("pred"))
    return me.out_of_label_rate(p, labels).withColumn("system", F.lit("candidate labels")).unionByName(me.out_of_label_rate(free, labels).withColumn("system", F.lit("no retrieval")))


GRID = [(b, t) for b in (1, 3, 5, 7) for t in (0.1, 0.3, 0.5, 0.7)]


def _grid_sql() -> str:
    from evigraph.queries.method import count_sql

    return "WITH " + count_sql(7) + """, freq AS (SELECT term, count(*) AS df FROM counts GROUP BY term), total AS (SELECT count(*) AS n_chunks FROM chunks),
    sc AS (SELECT chunk_key, n, term, cnt / n_tok * ln((n_chunks + 1) / (df + 1)) / ln(n_chunks + 1) AS er FROM counts JOIN freq USING (term), total), g AS (SELECT b, tau FROM (VALUES (1), (3), (5), (7)) x(b), (VALUES (0.1), (0.3), (0.5), (0.7)) y(tau))
    SELECT b, tau::DOUBLE AS tau, count(DISTINCT term) AS entities, count(term) AS pairs FROM g LEFT JOIN sc ON n <= b AND round(er, 9) > tau GROUP BY b, tau"""


@query(_grid_sql())
def w_grid_entities(spark, d):
    """W8: entity counts over the grid of n-gram sizes and thresholds; one scoring serves all cells."""
    s = ents.score_chunks(textprep.chunk(corpora.documents(spark, d)), EntitySpec(max_n=7, min_df=1)).where(F.round("er", 9) > 0.1).select("n", "term", F.round("er", 9).alias("er"))
    grid = spark.createDataFrame(GRID, "b int, tau double")
    return grid.join(s, (F.col("n") <= F.col("b")) & (F.col("er") > F.col("tau")), "left").groupBy("b", "tau").agg(F.countDistinct("term").alias("entities"), F.count("term").alias("pairs"))


@query()
def w_pages_index(spark, d):
    """W13: index sizes over the visible text of raw pages."""
    from evigraph.operators.kg import graph_stats

    index = ix.build(corpora.pages(spark, d), Config())
    return graph_stats(index.chunks, index.nodes, index.edges)


from evigraph.queries.relational import HTML_SQL  # noqa: E402


@query("WITH " + chunk_sql(source=f"SELECT CAST(page_id AS VARCHAR) AS doc_key, {HTML_SQL} AS text FROM pages") + " SELECT chunk_key, CAST(len(tokens) AS INTEGER) AS n_tok FROM chunks")
def w_pages_chunks(spark, d):
    return textprep.chunk(corpora.pages(spark, d)).select("chunk_key", "n_tok")


@query("WITH " + score_sql(3, 1, source=f"SELECT CAST(page_id AS VARCHAR) AS doc_key, {HTML_SQL} AS text FROM pages") + " SELECT chunk_key, count(*) AS terms, round(max(er), 6) AS top FROM scores GROUP BY chunk_key")
def p_entity_score_pages(spark, d):
    s = ents.score_chunks(textprep.chunk(corpora.pages(spark, d)), EntitySpec(min_df=1))
    return s.groupBy("chunk_key").agg(F.count("*").alias("terms"), F.round(F.max("er"), 6).alias("top"))
