"""Packed n-gram counts against plain rows, with repeated keys, short chunks and small limits."""

import pytest
import test_queries
from pyspark.sql import functions as F

from evigraph.operators import entities as ents
from evigraph.operators import kg, packed, retrieval, textprep
from evigraph.operators.retrieval import bm25, chunk_stats
from evigraph.specs import ChunkSpec, EntitySpec
from test_queries import QUERIES, con  # noqa: F401

TEXTS = [("1", "a b a b c"), ("1", "a b c c d"), ("2", "a"), ("3", "b c d e f g h a b c d e f g h"), ("4", "a b c d e f g h i j k l"), ("4", "x y"), ("5", ""), ("6", None), ("7", "École école ñ1 ñ1 a b")]


@pytest.fixture(scope="module")
def chunks(spark):
    docs = spark.createDataFrame(TEXTS, "doc_key string, text string").repartition(3)
    return textprep.chunk(docs, ChunkSpec(5, 1)).cache()


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def test_totals_and_scores_equal_plain_rows(spark, chunks, monkeypatch):
    monkeypatch.setattr(packed, "ROWS", 2)
    counts = textprep.term_counts(textprep.ngrams(chunks, 3))
    want = counts.groupBy("n").agg(F.count("*").alias("pairs"), F.sum("cnt").alias("occurrences"), F.countDistinct("term").alias("terms"))
    assert rows(packed.gram_totals(chunks, 3), "n", "pairs", "occurrences", "terms") == rows(want, "n", "pairs", "occurrences", "terms")
    every = ("chunk_key", "n", "term", "cnt", "df", "n_chunks")
    plain = ents.score_chunks(chunks, EntitySpec(min_df=1))
    assert rows(packed.candidates(chunks, 3), *every) == rows(plain, *every)
    whole = plain.groupBy("chunk_key").agg(F.count("*").alias("terms"), F.sum("df").alias("dfs"), F.round(F.max("er"), 9).alias("top"), F.round(F.min("er"), 9).alias("low"))
    own = packed.summaries(chunks, 3).groupBy("chunk_key").agg(F.sum("terms").alias("terms"), F.sum("dfs").alias("dfs"), F.round(F.max("top"), 9).alias("top"), F.round(F.min("low"), 9).alias("low"))
    assert rows(own, "chunk_key", "terms", "dfs", "top", "low") == rows(whole, "chunk_key", "terms", "dfs", "top", "low")


@pytest.mark.parametrize("spec", [EntitySpec(max_df=0.9, cap=2), EntitySpec(tau=0.1, cap=None, max_df=1.0), EntitySpec(max_n=2, mode="chunk_max", tau=0.5, cap=None, max_df=1.0), EntitySpec(min_df=1, cap=3, max_df=1.0)])
def test_selections_equal_plain_rows(chunks, spec):
    cols = ("chunk_key", "n", "term", "cnt", "df", "er")
    assert rows(ents.select_words(chunks, spec), *cols) == rows(ents.select_entities(ents.score_chunks(chunks, spec), spec), *cols)


def test_only_a_share_of_the_hashes_is_sent_at_once(chunks):
    blocked = packed.blocks(chunks)
    got = [packed.sent(blocked, 2, own, 4).agg(F.sum(F.length("hashes") / 16)).first()[0] for own in range(packed.CLASSES)]
    assert len(got) > 1 and all(got) and sum(got) == textprep.term_counts(textprep.ngrams(chunks, 2)).where("n = 2").count()


def test_relations_need_no_row_with_its_tokens_for_each_entity(chunks):
    rel = kg.adjacent_relations(chunks.where("chunk_key not like '1%' and chunk_key not like '4%'"), ents.select_words(chunks, EntitySpec(min_df=1, cap=4, max_df=1.0)))
    assert "lead(" not in rel._jdf.queryExecution().optimizedPlan().toString() and rel.count() > 0


def test_asked_words_alone_are_dealt_out(spark, chunks):
    q = spark.createDataFrame([(1, "a B zz"), (2, "école x a"), (3, None)], "qid long, text string")
    want = bm25(q, textprep.term_counts(textprep.ngrams(chunks, 1)), chunk_stats(chunks))
    got = retrieval.bm25_of_chunks(q, chunks)
    assert {(r.qid, r.chunk_key): round(r.bm25, 9) for r in got.collect()} == {(r.qid, r.chunk_key): round(r.bm25, 9) for r in want.collect()}
    plan = got._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    assert plan.count("Exchange hashpartitioning(chunk_key") == 1 and "Exchange hashpartitioning(qid" not in plan


@pytest.mark.parametrize("name", "p_select_literal p_passage_edges p_graph_stats p_ngrams_5 sql_functions b_bm25".split())
def test_changed_queries_match_sql(spark, con, sf, name):
    test_queries.test_query_matches_sql(spark, con, sf, name)


def test_terms_anywhere_equal_plain_rows(spark, chunks, monkeypatch):
    """Known terms in all chunks, those of a key with chunks of several sizes counted once; no row for each n-gram is dealt out."""
    monkeypatch.setattr(packed, "ROWS", 2)
    counts = textprep.term_counts(textprep.ngrams(chunks, 3))
    for some in (counts.where("term in ('a', 'a b', 'b c d', 'c c', 'h', 'école ñ1')"), counts, counts.where("n = 2")):
        want = kg.passage_edges_anywhere(counts, some).groupBy("dst").agg(F.count("*").alias("terms"))
        got = packed.holding(chunks, some, 3)
        assert rows(got.withColumn("dst", kg.passage_key()), "dst", "terms") == rows(want, "dst", "terms")
    monkeypatch.setattr(textprep, "term_counts", lambda *_: pytest.fail("a row for each n-gram"))
    QUERIES["p_passage_edges_anywhere"](spark, "/root/testdata/sf0.001")


def test_terms_anywhere_match_sql(spark, con, sf):  # noqa: F811
    test_queries.test_query_matches_sql(spark, con, sf, "p_passage_edges_anywhere")
