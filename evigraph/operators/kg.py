"""Evidence graph: relations, passages, synonyms, union, pseudo edges, statistics, storage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def adjacent_relations(chunks: DataFrame, entities: DataFrame) -> DataFrame:
    """Offline relation extraction: each selected entity and the next one to its right in the chunk.

    The relation is the text between (at most three words), else ``near``. One row for (chunk, head, relation, tail).
    """
    texts = chunks.groupBy("chunk_key").agg(F.collect_list(F.array_join("tokens", " ")).alias("texts"))  # one text but for chunks of one key
    named = entities.groupBy("chunk_key").agg(F.collect_list(F.struct("term", "n")).alias("named"))

    def of(text: Column, no: Column) -> Column:
        def spots(tokens: Column) -> Column:
            def at(e: Column) -> Column:
                starts = F.filter(F.sequence(F.lit(1), F.greatest(F.size(tokens) - e["n"] + 1, F.lit(1))), lambda i: F.array_join(F.slice(tokens, i, e["n"]), " ") == e["term"])
                return F.transform(starts, lambda i: F.struct(i.alias("at"), (-e["n"]).alias("m"), e["term"].alias("term"), no.alias("no")))

            return F.flatten(F.transform("named", at))

        return F.element_at(F.transform(F.array(F.split(text, " ")), spots), 1)

    held = texts.join(named, "chunk_key").select("chunk_key", F.transform("texts", lambda t: F.split(t, " ")).alias("words"), F.array_sort(F.flatten(F.transform("texts", of))).alias("s"))

    def pair(i: Column) -> Column:
        a, b = F.element_at("s", i), F.element_at("s", i + 1)
        gap = b["at"] - a["at"] + a["m"]
        between = F.array_join(F.slice(F.element_at("words", a["no"] + 1), a["at"] - a["m"], F.greatest(gap, F.lit(0))), " ")
        return F.struct(a["term"].alias("head"), F.when((gap >= 1) & (gap <= 3), between).otherwise(F.lit("near")).alias("relation"), b["term"].alias("tail"))

    pairs = F.transform(F.filter(F.sequence(F.lit(1), F.greatest(F.size("s") - 1, F.lit(1))), lambda i: i < F.size("s")), pair)
    rel = held.select("chunk_key", F.explode(F.array_distinct(F.filter(pairs, lambda p: p["head"] != p["tail"]))).alias("p"))
    return rel.select("chunk_key", "p.head", "p.relation", "p.tail")


def extract_relations(chunks: DataFrame, entities: DataFrame, extractor: Callable | None = None) -> DataFrame:
    """Relations by a model: ``extractor`` maps batches of (chunk_key, text, terms) to (chunk_key, head, relation, tail)."""
    if extractor is None:
        return adjacent_relations(chunks, entities)
    terms = entities.groupBy("chunk_key").agg(F.collect_list("term").alias("terms"))
    rows = chunks.select("chunk_key", F.array_join("tokens", " ").alias("text")).join(terms, "chunk_key")
    return rows.mapInPandas(extractor, "chunk_key string, head string, relation string, tail string")


def entity_key(term: str = "term"):
    return F.concat(F.lit("e:"), F.col(term))


def passage_key(chunk: str = "chunk_key"):
    return F.concat(F.lit("p:"), F.col(chunk))


def passage_edges(entities: DataFrame) -> DataFrame:
    return entities.select(entity_key().alias("src"), passage_key().alias("dst"), F.lit("contains").alias("relation")).distinct()


def passage_edges_anywhere(counts: DataFrame, entities: DataFrame) -> DataFrame:
    """Contains-edges for every chunk in which an entity of the dictionary occurs."""
    known = entities.select("term").distinct()
    return counts.join(known, "term", "left_semi").select(entity_key().alias("src"), passage_key().alias("dst"), F.lit("contains").alias("relation")).distinct()


def assemble(chunks: DataFrame, entities: DataFrame, relations: DataFrame, synonyms: DataFrame | None = None, head_words: int = 32) -> tuple[DataFrame, DataFrame]:
    """nodes(node_key, kind, text) and edges(edge_id, src, dst, kind, relation, fact_text); parallel relations stay."""
    nodes = entities.select(entity_key().alias("node_key"), F.lit("entity").alias("kind"), F.col("term").alias("text")).distinct()
    head = F.array_join(F.slice("tokens", 1, head_words), " ")
    nodes = nodes.unionByName(chunks.select(passage_key().alias("node_key"), F.lit("passage").alias("kind"), head.alias("text")))
    rel = relations.select(F.concat(F.lit("e:"), "head").alias("src"), F.concat(F.lit("e:"), "tail").alias("dst"), F.lit("relation").alias("kind"), "relation", F.concat_ws(" ", "head", "relation", "tail").alias("fact_text"))
    has = entities.join(chunks.select("chunk_key", head.alias("h")), "chunk_key").select(
        entity_key().alias("src"), passage_key().alias("dst"), F.lit("contains").alias("kind"), F.lit("contains").alias("relation"), F.concat_ws(" ", "term", F.lit("contains"), "h").alias("fact_text")
    )
    edges = rel.unionByName(has)
    if synonyms is not None:
        edges = edges.unionByName(synonyms.select("src", "dst", F.lit("synonym").alias("kind"), F.lit("synonym").alias("relation"), F.concat_ws(" ", F.expr("substring(src, 3)"), F.lit("synonym"), F.expr("substring(dst, 3)")).alias("fact_text")))
    edges = edges.withColumn("edge_id", F.concat_ws("|", "src", "relation", "dst")).dropDuplicates(["edge_id"])
    return nodes, edges.select("edge_id", "src", "dst", "kind", "relation", "fact_text")


def pseudo_edges(nodes: DataFrame) -> DataFrame:
    """Edges from every passage to the pseudo node, for engines that want them as rows; the search treats them as a virtual star."""
    p = nodes.where("kind = 'passage'")
    return p.select(F.concat(F.lit("z|pseudo|"), "node_key").alias("edge_id"), F.lit("z").alias("src"), F.col("node_key").alias("dst"), F.lit("pseudo").alias("kind"), F.lit("pseudo").alias("relation"), F.lit("").alias("fact_text"))


def graph_stats(chunks: DataFrame, nodes: DataFrame, edges: DataFrame) -> DataFrame:
    n = nodes.agg(F.count_if(F.expr("kind = 'entity'")).alias("entities"), F.count_if(F.expr("kind = 'passage'")).alias("passages"))
    e = edges.agg(F.count_if(F.expr("kind = 'relation'")).alias("relations"), F.count_if(F.expr("kind = 'contains'")).alias("contains_edges"), F.count_if(F.expr("kind = 'synonym'")).alias("synonyms"))
    return chunks.agg(F.count("*").alias("chunks")).join(n).join(e)  # one row each


def both_ways(edges: DataFrame) -> DataFrame:
    """Directed view: each undirected edge twice, self-loops once."""
    back = edges.where("src <> dst").withColumns({"src": F.col("dst"), "dst": F.col("src")})
    return edges.unionByName(back)


def write_index(nodes: DataFrame, edges: DataFrame, path: str) -> None:
    """Edges by kind, so a search that wants relations only reads their folder."""
    nodes.write.mode("overwrite").partitionBy("kind").parquet(f"{path}/nodes")
    both_ways(edges).write.mode("overwrite").partitionBy("kind").parquet(f"{path}/edges")


def read_index(spark: SparkSession, path: str, kinds: tuple[str, ...] | None = None) -> tuple[DataFrame, DataFrame]:
    edges = spark.read.parquet(f"{path}/edges")
    return spark.read.parquet(f"{path}/nodes"), edges.where(F.col("kind").isin(*kinds)) if kinds else edges
