"""Tokens, overlapping chunks, n-grams and their counts (data preparation)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evigraph.specs import ChunkSpec

WORD = r"[\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    """Lower-case runs of letters and digits."""
    return F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(0))


def units(text: Column, unit: str) -> Column:
    if unit == "word":
        return tokens(text)
    if unit == "char":
        return F.regexp_extract_all(text, F.lit(r"(?s)."), F.lit(0))
    if unit == "sentence":
        return F.regexp_extract_all(text, F.lit(r"[^.!?]+[.!?]*"), F.lit(0))
    raise ValueError(f"unknown unit {unit}")


def chunk(df: DataFrame, spec: ChunkSpec = ChunkSpec(), key: str = "doc_key", text: str = "text") -> DataFrame:
    """chunk_key, doc_key, chunk_no, tokens, n_tok. Narrow: one stage with the scan. Empty or null text gives no chunk."""
    stride = spec.length - spec.overlap
    if stride <= 0:
        raise ValueError("overlap must be less than length")
    whole = df.select(F.col(key).alias("doc_key"), units(F.col(text), spec.unit).alias("_t")).where(F.size("_t") > 0)
    last = F.greatest(F.ceil((F.size("_t") - spec.length) / stride).cast("int"), F.lit(0))
    cut = whole.select("doc_key", F.explode(F.sequence(F.lit(0), last)).alias("chunk_no"), "_t")
    part = cut.select("doc_key", "chunk_no", F.slice("_t", F.col("chunk_no") * stride + 1, F.lit(spec.length)).alias("tokens"))
    return part.select(F.concat_ws(":", "doc_key", "chunk_no").alias("chunk_key"), "doc_key", "chunk_no", "tokens", F.size("tokens").alias("n_tok"))


def ngrams(chunks: DataFrame, max_n: int = 3) -> DataFrame:
    """chunk_key, n_tok, n, term: every run of 1 to max_n words."""

    def of(n: Column) -> Column:
        starts = F.when(F.col("n_tok") >= n, F.sequence(F.lit(1), F.col("n_tok") - n + 1)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.struct(n.alias("n"), F.array_join(F.slice("tokens", i, n), " ").alias("term")))

    grams = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(max_n)), of))
    return chunks.select("chunk_key", "n_tok", F.explode(grams).alias("g")).select("chunk_key", "n_tok", "g.n", "g.term")


def term_counts(grams: DataFrame) -> DataFrame:
    return grams.groupBy("chunk_key", "n_tok", "n", "term").agg(F.count("*").alias("cnt"))


def doc_freq(counts: DataFrame) -> DataFrame:
    """Chunks that hold a term; counts has one row a chunk and term."""
    return counts.groupBy("term").agg(F.count("*").alias("df"))
