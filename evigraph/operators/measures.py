"""Accuracy and cost measures."""

from __future__ import annotations

import time
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from evigraph.operators.textprep import tokens


def accuracy_exact(preds: DataFrame) -> DataFrame:
    """Share of predictions that equal their gold label (a null prediction is wrong)."""
    return preds.agg(F.avg(F.coalesce(F.col("pred") == F.col("gold"), F.lit(False)).cast("double")).alias("accuracy"))


def token_f1(a: Column, b: Column) -> Column:
    """F1 of distinct words."""
    both = F.size(F.array_intersect(a, b)) * 2.0
    return both / F.greatest(F.size(F.array_distinct(a)) + F.size(F.array_distinct(b)), F.lit(1))


def graded(ans: Column, gold: Column, low: float = 0.3, high: float = 0.8) -> Column:
    """0, 0.5 or 1: the offline judge cuts word F1 at two points."""
    f = token_f1(tokens(F.coalesce(ans, F.lit(""))), tokens(F.coalesce(gold, F.lit(""))))
    return F.when(f >= high, 1.0).when(f >= low, 0.5).otherwise(0.0)


def accuracy_graded(rows: DataFrame) -> DataFrame:
    return rows.agg(F.avg(graded(F.col("answer"), F.col("gold"))).alias("accuracy"))


def macro_recall(preds: DataFrame) -> DataFrame:
    """Mean over gold classes of the share of a class that is found."""
    per = preds.groupBy("gold").agg(F.avg(F.coalesce(F.col("pred") == F.col("gold"), F.lit(False)).cast("double")).alias("recall"))
    return per.agg(F.avg("recall").alias("macro_recall"))


def lcs(a: list[str], b: list[str]) -> int:
    row = [0] * (len(b) + 1)
    for x in a:
        left = 0
        for j, y in enumerate(b, 1):
            keep = row[j]
            row[j] = left + 1 if x == y else max(row[j], row[j - 1])
            left = keep
    return row[-1]


@F.pandas_udf(DoubleType())
def lcs_ratio(gen: pd.Series, gold: pd.Series) -> pd.Series:
    """Longest common subsequence of words over the number of generated words."""

    def one(g, y):
        g, y = (g or "").lower().split(), (y or "").lower().split()
        return lcs(g, y) / len(g) if g else 0.0

    return pd.Series([one(g, y) for g, y in zip(gen, gold)])


def lcs_fold(gen: Column, gold: Column) -> Column:
    """The same for short texts without Python: a fold over words that keeps one row of the table."""
    a, b = F.split(F.lower(gen), " +"), F.split(F.lower(gold), " +")
    row = F.aggregate(
        a,
        F.transform(b, lambda _: F.lit(0)),
        lambda r, x: F.aggregate(
            F.zip_with(b, r, lambda y, up: F.struct(y.alias("y"), up.alias("up"))),
            F.struct(F.array().cast("array<int>").alias("out"), F.lit(0).alias("diag"), F.lit(0).alias("left")),
            lambda s, c: _lcs_cell(s, c, x),
        )["out"],
    )
    return F.coalesce(F.element_at(row, -1) / F.size(a), F.lit(0.0))


def _lcs_cell(s: Column, c: Column, x: Column) -> Column:
    v = F.when(c["y"] == x, s["diag"] + 1).otherwise(F.greatest(c["up"], s["left"]))
    return F.struct(F.concat(s["out"], F.array(v)).alias("out"), c["up"].alias("diag"), v.alias("left"))


def coverage(evidence: Column, response: Column) -> Column:
    """Share of required evidences whose words all occur in the response."""
    r = tokens(F.coalesce(response, F.lit("")))
    hit = F.filter(evidence, lambda e: F.forall(tokens(e), lambda w: F.array_contains(r, w)))
    return F.when(F.size(evidence) > 0, F.size(hit) / F.size(evidence))


def claims(answer: Column) -> Column:
    return F.filter(F.transform(F.split(answer, r"[.!?\n]+"), lambda c: F.trim(c)), lambda c: c != "")


def faithfulness(answer: Column, context: Column) -> Column:
    """Share of an answer's sentences that the context contains."""
    c = claims(F.coalesce(answer, F.lit("")))
    return F.when(F.size(c) > 0, F.size(F.filter(c, lambda x: F.contains(context, x))) / F.size(c))


def out_of_label_rate(preds: DataFrame, labels: DataFrame) -> DataFrame:
    """Share of predictions that aren't in the label set."""
    known = labels.select(F.col("label").alias("pred")).distinct().withColumn("known", F.lit(1))
    return preds.join(known, "pred", "left").agg(F.avg(F.when(F.col("known").isNull(), 1.0).otherwise(0.0)).alias("out_of_label_rate"))


def token_cost(rows: DataFrame) -> DataFrame:
    """Mean words in and out of a question; rows: prompt, answer."""
    return rows.agg(F.avg(F.size(tokens(F.coalesce("prompt", F.lit(""))))).alias("tok_in"), F.avg(F.size(tokens(F.coalesce("answer", F.lit(""))))).alias("tok_out"))


def hit_rate(retrieved: DataFrame, gold: DataFrame, k: int) -> DataFrame:
    """Share of questions with gold documents of which one is among the first k, and the mean reciprocal rank. gold: qid, doc_key."""
    found = retrieved.where(F.col("rk") <= k).withColumn("doc_key", F.substring_index("chunk_key", ":", 1)).join(gold, ["qid", "doc_key"], "left_semi")
    first = found.groupBy("qid").agg(F.min("rk").alias("rk"))
    return gold.select("qid").distinct().join(first, "qid", "left").agg(F.avg(F.when(F.col("rk").isNull(), 0.0).otherwise(1.0)).alias("hit_rate"), F.avg(F.coalesce(1 / F.col("rk"), F.lit(0.0))).alias("mrr"), F.count("*").alias("questions"))


class Stopwatch:
    """Seconds by stage on the driver's clock."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str):
        at = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - at
