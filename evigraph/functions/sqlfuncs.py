"""Names for SQL text: a table function that cuts text into chunks, and formulas as SQL expressions."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

#: Formulas over columns cnt, n_tok, df, n_chunks and over a cosine ms; text, so Catalyst sees plain expressions.
ENTITY_SCORE = "cnt / n_tok * ln((n_chunks + 1) / (df + 1)) / ln(n_chunks + 1)"
EDGE_COST = "(1 - ms) / 2"

_WORD = re.compile(r"[^\W_]+")


class ChunkText:
    """Rows (chunk_no, n_tok) of one text."""

    def eval(self, text: str, length: int, overlap: int):
        n = len(_WORD.findall((text or "").lower()))
        at = no = 0
        while n and (at == 0 or at < n - overlap):
            yield no, min(length, n - at)
            at += length - overlap
            no += 1


def register(spark: SparkSession) -> None:
    spark.udtf.register("chunk_text", F.udtf(ChunkText, returnType="chunk_no int, n_tok int"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_cost(ms DOUBLE) RETURNS DOUBLE RETURN (1 - ms) / 2")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION entity_score(cnt DOUBLE, n_tok DOUBLE, df DOUBLE, n_chunks DOUBLE) RETURNS DOUBLE RETURN cnt / n_tok * ln((n_chunks + 1) / (df + 1)) / ln(n_chunks + 1)")
