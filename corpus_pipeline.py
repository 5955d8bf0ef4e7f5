"""A corpus for training: language, lines, near duplicates, mixture, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, with the columns of documents in all stages but the last. Every stage works on all
that its predecessor kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.llm import op2_language, op3_byte_bpe, op4_probminhash, op9_fuzzy_lines, op10_mixture
from evigraph.llm.common import documents, saved

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is told apart; a missing language is filled in. Rejected documents go."""
    model = op2_language.fit(docs.where(~F.coalesce(op2_language.held_out(), F.lit(True))))
    documents(spark, sf_dir)  # bounds Arrow batches, whichever way the stages are run
    told = op2_language.identify(docs.select(*COLUMNS), model).where(~F.col("rejected"))
    return told.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without lines that stand, alike, earlier in the corpus; a document may be left with an empty text."""
    kept = op9_fuzzy_lines.dedup_lines(docs.select(*COLUMNS))
    return kept.withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates."""
    return op4_probminhash.deduplicated(docs.select(*COLUMNS))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What the mix takes of each document, a row for each pass."""
    return op10_mixture.mixed(docs.select(*COLUMNS))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each row of the mix, checked by decoding."""
    return op3_byte_bpe.public_codec(spark).digests(docs, "text", ["doc_id", "lang", "source"])


STAGES = [("language", language), ("lines", lines), ("near_duplicates", near_duplicates), ("mixture", mixture), ("tokens", tokens)]

#: Compression, MinHash and byte-pair merges have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are written to the shared folder and read again."""
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir), f"stage_{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
