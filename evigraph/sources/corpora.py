"""Corpora as (doc_key, text), questions, and the star schema as typed facts."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("doc_key"), "text")


def html_text(html: Column) -> Column:
    """Visible text: scripts, styles, comments and tags go; basic entities are decoded; white space is squeezed."""
    out = F.regexp_replace(html, r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        out = F.replace(out, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(out, r"[ \t\r\n]+", " "))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("string").alias("doc_key"), html_text(F.col("html")).alias("text"))


def conversations(spark: SparkSession, sf_dir: str, roles: tuple[str, ...] = ("assistant", "system")) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").where(F.col("role").isin(*roles))
    return turns.select(F.concat_ws("-", "conv_id", "turn").alias("doc_key"), "text")


def fact_questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W1: benchmark items; evidence is every document that holds the item verbatim.

    The items travel as a broadcast condition; they are one small table of questions, not the corpus.
    """
    items = table(spark, sf_dir, "benchmark")
    docs = documents(spark, sf_dir)
    hits = docs.join(F.broadcast(items), F.contains(docs["text"], items["text"])).groupBy("item_id").agg(F.array_sort(F.collect_set("doc_key")).alias("evidence"))
    return items.join(hits, "item_id", "left").select(
        F.col("item_id").alias("qid"), "text", F.lit(None).cast("string").alias("gold"), F.coalesce("evidence", F.array().cast("array<string>")).alias("evidence"), F.lit(None).cast("string").alias("label")
    )


def reasoning_questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W2: a user turn followed by an assistant turn, the first of each conversation; gold is that answer."""
    from pyspark.sql import Window

    w = Window.partitionBy("conv_id").orderBy("turn")
    turns = table(spark, sf_dir, "conversations").withColumns({"next_role": F.lead("role").over(w), "gold": F.lead("text").over(w), "gold_turn": F.lead("turn").over(w)})
    pairs = turns.where("role = 'user' and next_role = 'assistant'").withColumn("r", F.row_number().over(w)).where("r = 1")
    return pairs.select(
        F.col("conv_id").alias("qid"), "text", "gold", F.array(F.concat_ws("-", "conv_id", "gold_turn")).alias("evidence"), F.lit(None).cast("string").alias("label")
    )


def class_texts(spark: SparkSession, sf_dir: str, label: str = "lang") -> tuple[DataFrame, DataFrame]:
    """W5, W6: (corpus with one text a label, test texts with their label)."""
    docs = table(spark, sf_dir, "documents").where("text is not null")
    if label in ("quality", "toxic"):
        docs = docs.join(table(spark, sf_dir, "labels").where(f"{label} is not null").select("doc_id", F.col(label).cast("string").alias("name")), "doc_id")
    else:
        docs = docs.withColumn("name", F.col("lang") if label == "lang" else F.concat_ws("/", "lang", "source"))
    rows = docs.select("doc_id", "text", F.col("name").alias("label"))
    first = rows.groupBy("label").agg(F.min("doc_id").alias("doc_id"))
    corpus = rows.join(first.select("doc_id"), "doc_id", "left_semi").select(F.col("doc_id").cast("string").alias("doc_key"), "text", "label")
    tests = rows.join(first.select("doc_id"), "doc_id", "left_anti").select(
        F.col("doc_id").alias("qid"), "text", F.col("label").alias("gold"), F.array().cast("array<string>").alias("evidence"), "label"
    )
    return corpus, tests


def star_edges(spark: SparkSession, sf_dir: str, orders: bool = True, parts: bool = False) -> DataFrame:
    """W9: the star schema as undirected facts (src, relation, dst, kind, weight), one row a pair."""
    t = {n: table(spark, sf_dir, n) for n in ("nation", "customer", "supplier")}

    def edge(df: DataFrame, a: str, x: str, rel: str, b: str, y: str, weight: Column | None = None) -> DataFrame:
        one = F.lit(1).cast("long") if weight is None else weight
        return df.select(F.concat(F.lit(a), F.col(x)).alias("src"), F.lit(rel).alias("relation"), F.concat(F.lit(b), F.col(y)).alias("dst"), one.alias("weight"))

    frames = [
        edge(t["nation"], "n:", "n_nationkey", "in", "r:", "n_regionkey"),
        edge(t["customer"], "c:", "c_custkey", "in", "n:", "c_nationkey"),
        edge(t["supplier"], "s:", "s_suppkey", "in", "n:", "s_nationkey"),
    ]
    if orders:
        frames.append(edge(table(spark, sf_dir, "orders"), "c:", "o_custkey", "placed", "o:", "o_orderkey"))
    if parts:
        li = table(spark, sf_dir, "lineitem")
        frames.append(edge(li.groupBy("l_orderkey", "l_partkey").agg(F.count("*").alias("m")), "o:", "l_orderkey", "has", "p:", "l_partkey", F.col("m")))
        frames.append(edge(li.groupBy("l_suppkey", "l_partkey").agg(F.count("*").alias("m")), "s:", "l_suppkey", "supplies", "p:", "l_partkey", F.col("m")))
    return reduce(DataFrame.unionByName, frames).select(F.concat_ws("|", "src", "relation", "dst").alias("edge_id"), "src", "dst", F.lit("relation").alias("kind"), "relation", "weight")
