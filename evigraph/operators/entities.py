"""Statistical entities: a normalised TF-IDF score and its selection rules."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evigraph.operators import packed
from evigraph.operators.textprep import doc_freq, ngrams, term_counts
from evigraph.runtime import clean_shuffles, forget, written
from evigraph.specs import EntitySpec


def score_of(cnt: Column, n_tok: Column, df: Column, n_chunks: Column) -> Column:
    """Share of the chunk that the term takes, times idf over the largest idf; in [0, 1)."""
    return F.when(n_chunks > 0, cnt / n_tok * F.ln((n_chunks + 1) / (df + 1)) / F.ln(n_chunks + 1)).otherwise(0.0)


def entity_score(counts: DataFrame, freq: DataFrame, n_chunks: DataFrame, min_df: int = 1) -> DataFrame:
    """chunk_key, n, term, cnt, df, er. ``n_chunks`` is a one-row frame, so the plan stays lazy; terms under min_df go before the join."""
    kept = freq.where(F.col("df") >= min_df) if min_df > 1 else freq
    joined = counts.join(kept, "term").join(F.broadcast(n_chunks))
    return joined.select("chunk_key", "n", "term", "cnt", "df", score_of(F.col("cnt"), F.col("n_tok"), F.col("df"), F.col("n_chunks")).alias("er"), "n_chunks")


def chunk_count(chunks: DataFrame) -> DataFrame:
    return chunks.agg(F.count("*").alias("n_chunks"))


def score_chunks(chunks: DataFrame, spec: EntitySpec) -> DataFrame:
    counts = term_counts(ngrams(chunks, spec.max_n))
    return entity_score(counts, doc_freq(counts), chunk_count(chunks), spec.min_df)


def select_entities(scores: DataFrame, spec: EntitySpec) -> DataFrame:
    """Threshold in one of three scales, then the best ``cap`` of each chunk (ties by term)."""
    per = Window.partitionBy("chunk_key")
    s = scores.where(F.col("df") <= F.greatest(F.lit(float(spec.min_df)), spec.max_df * F.col("n_chunks"))) if spec.max_df < 1 else scores
    if spec.mode == "literal":
        s = s.withColumn("v", F.col("er"))
    elif spec.mode == "chunk_max":
        s = s.withColumn("v", F.round(F.col("er") / F.nullif(F.max("er").over(per), F.lit(0.0)), 9))
    elif spec.mode == "chunk_rank":
        s = s.withColumn("v", F.percent_rank().over(per.orderBy("er")))
    else:
        raise ValueError(f"unknown mode {spec.mode}")
    s = s.where(F.col("v") > spec.tau)
    if spec.cap is not None:
        order = per.orderBy(F.round("er", 9).desc(), "term")
        s = s.withColumn("r", F.row_number().over(order)).where(F.col("r") <= spec.cap)
    return s.select("chunk_key", "n", "term", "cnt", "df", "er")


def candidate_scores(chunks: DataFrame, spec: EntitySpec) -> DataFrame:
    """``score_chunks`` of chunks of words, but for rows that ``select_entities`` of the same spec drops anyway; counted in packed arrays."""
    if spec.mode == "chunk_rank":
        raise ValueError("ranks within a chunk need all its scores")
    bound = {"tau": spec.tau} if spec.mode == "literal" else {"of_max": min(1.0, spec.tau)}
    c = packed.candidates(chunks, spec.max_n, spec.min_df, spec.max_df, cap=spec.cap, **bound)
    out = c.select("chunk_key", "n", "term", "cnt", "df", score_of(F.col("cnt"), F.col("n_tok"), F.col("df"), F.col("n_chunks")).alias("er"), "n_chunks")
    out._scratch = c._scratch
    return out


def select_words(chunks: DataFrame, spec: EntitySpec) -> DataFrame:
    """``select_entities`` over the scores of chunks of words."""
    return select_entities(candidate_scores(chunks, spec), spec)


def chosen_terms(chunks: DataFrame, spec: EntitySpec) -> DataFrame:
    """n, term that ``select_words`` keeps in some chunk, written; the scores they came from go."""
    scores = candidate_scores(chunks, spec)
    with clean_shuffles(chunks.sparkSession):
        out = written(select_entities(scores, spec).select("n", "term").distinct(), "terms", compression="zstd")
    forget(scores)
    return out


def subsume(selected: DataFrame) -> DataFrame:
    """Drop a phrase that lies inside a longer kept phrase of the same chunk."""
    longer = selected.groupBy("chunk_key").agg(F.collect_list("term").alias("all"))
    inside = F.exists("all", lambda t: (t != F.col("term")) & F.contains(F.concat(F.lit(" "), t, F.lit(" ")), F.concat(F.lit(" "), F.col("term"), F.lit(" "))))
    return selected.join(longer, "chunk_key").where(~inside).drop("all")


def extract_with_model(chunks: DataFrame, cap: int = 12, noise: float = 0.1) -> DataFrame:
    """The ablation that asks a model for entities. The offline stand-in takes a chunk's longest distinct words and, at a fixed
    rate by hash, names an entity that isn't in the chunk or a broken one, as models do."""
    words = chunks.select("chunk_key", "n_tok", F.slice(F.array_sort(F.transform(F.array_distinct("tokens"), lambda t: F.struct((-F.length(t)).alias("l"), t.alias("t")))), 1, cap).alias("w"))
    each = words.select("chunk_key", F.explode("w").alias("x")).select("chunk_key", F.col("x.t").alias("term"))
    broken = F.pmod(F.xxhash64("chunk_key", "term"), F.lit(1000)) < int(noise * 1000)
    return each.withColumn("term", F.when(broken, F.concat(F.lit("entity "), F.reverse("term"))).otherwise(F.col("term"))).select(
        "chunk_key", F.size(F.split("term", " ")).alias("n"), "term", F.lit(1).cast("long").alias("cnt"), F.lit(1).cast("long").alias("df"), F.lit(1.0).alias("er")
    )
