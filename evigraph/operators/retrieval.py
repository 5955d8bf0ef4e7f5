"""Vector and keyword retrieval, their mixture, and prompts."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from math import ceil

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evigraph.operators.textprep import tokens
from evigraph.runtime import clean_shuffles, written
from evigraph.specs import FuseSpec

#: A batch of questions that is broadcast to every task has at most so many rows; larger batches run in slices.
MOST_QUERIES = 20_000


def cosine(a: Column, b: Column) -> Column:
    """Of two arrays, in the JVM; for matrix sizes use top_vectors."""

    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.nullif(F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)), F.lit(0.0))


def best(scores: DataFrame, k: int, score: str, tie: str, by: str = "qid", digits: int = 6) -> DataFrame:
    """The k best of each group by (rounded score, tie); Spark limits groups before the shuffle."""
    w = Window.partitionBy(by).orderBy(F.round(score, digits).desc(), tie)
    return scores.withColumn("rk", F.row_number().over(w)).where(F.col("rk") <= k)


def collected_queries(queries: DataFrame, vec: str = "qvec") -> tuple[list[int], np.ndarray]:
    rows = queries.select("qid", vec).orderBy("qid").limit(MOST_QUERIES + 1).collect()
    if len(rows) > MOST_QUERIES:
        raise ValueError(f"more than {MOST_QUERIES} questions in one batch; run them in slices")
    return [r[0] for r in rows], np.array([r[1] for r in rows], np.float32).reshape(len(rows), -1)


def sliced(queries: DataFrame, run: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``run`` over slices of the questions that a broadcast can hold."""
    parts = ceil(1.25 * queries.count() / MOST_QUERIES)
    if parts < 2:
        return run(queries)
    return reduce(DataFrame.unionByName, [run(queries.where(F.pmod(F.xxhash64("qid"), F.lit(parts)) == i)) for i in range(parts)])


def kept_facts(top: DataFrame, floor: float, named: Column | None = None) -> DataFrame:
    """Of each question's ranked facts (qid, ms, rk), those that the offline judge keeps: close enough or naming a word; else the closest."""
    fine = F.col("ms") >= floor
    ok = top.withColumn("_ok", fine if named is None else fine | named)
    some = ok.groupBy("qid").agg(F.bool_or("_ok").alias("_some"))
    return ok.join(some, "qid").where("_ok or (not _some and rk = 1)").drop("_ok", "_some")


#: A task scores so many questions against so many items at once.
QUESTIONS, ITEMS = 1024, 2048


class Best:
    """The k best items of each question by (score, name) of the blocks that a task has seen."""

    def __init__(self, n: int, k: int):
        self.k, self.least = k, np.full(n, -np.inf)  # once there are k items, the last one's score
        self.pool: list[tuple[np.ndarray, ...]] = []
        self.size, self.kept = 0, 0

    def add(self, first: int, scores: np.ndarray, names: np.ndarray, *more: np.ndarray) -> None:
        """``scores`` and ``more``: a row for each question from number ``first`` on, a column for each of the names."""
        least = self.least[first : first + len(scores)]
        if scores.shape[1] > self.k:
            fresh = np.flatnonzero(least == -np.inf)
            if len(fresh):
                least[fresh] = np.partition(scores[fresh], scores.shape[1] - self.k, axis=1)[:, scores.shape[1] - self.k]
        q, j = np.nonzero((scores >= least[:, None]) & (scores > -np.inf))  # minus infinity: no item of this question
        self.pool.append((q + first, names[j], scores[q, j], *(x[q, j] for x in more)))
        self.size += len(q)
        if self.size > 2 * self.kept + 500_000:
            self._cut()

    def _cut(self) -> None:
        parts = [np.concatenate(x) for x in zip(*self.pool)]
        order = np.lexsort((pd.factorize(parts[1], sort=True)[0], -parts[2], parts[0]))
        q = parts[0][order]
        new = np.flatnonzero(np.diff(q, prepend=-1))
        place = np.arange(len(q)) - np.repeat(new, np.diff(new, append=len(q)))
        last = order[place == self.k - 1]
        self.least[parts[0][last]] = parts[2][last]
        self.pool = [tuple(x[order[place < self.k]] for x in parts)]
        self.size = self.kept = len(self.pool[0][0])

    def rows(self) -> Iterator[tuple[np.ndarray, ...]]:
        """Numbers of questions, names, scores and more, in pieces."""
        if self.pool:
            self._cut()
            for at in range(0, self.size, 10_000):
                yield tuple(x[at : at + 10_000] for x in self.pool[0])


def top_vectors(queries: DataFrame, items: DataFrame, k: int, key: str, vec: str = "vec", qvec: str = "qvec") -> DataFrame:
    """qid, key, ms, rk: exact k nearest items by cosine. The question matrix is broadcast in slices, each task keeps its own k best
    of each question, and one small shuffle by question ends it."""
    return sliced(queries, lambda q: _top_vectors(q, items, k, key, vec, qvec))


def _top_vectors(queries: DataFrame, items: DataFrame, k: int, key: str, vec: str, qvec: str) -> DataFrame:
    qids, q = collected_queries(queries, qvec)
    shared = items.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), q / np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-12)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, mat = shared.value
        held = Best(len(ids), k)
        for pdf in batches:
            for at in range(0, len(pdf) if len(ids) else 0, ITEMS):
                part = pdf.iloc[at : at + ITEMS]
                m = np.array(part["v"].tolist(), np.float32)
                m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)
                names = part["k"].to_numpy()
                for i in range(0, len(ids), QUESTIONS):
                    held.add(i, np.round((mat[i : i + QUESTIONS] @ m.T).astype(float), 6), names)
        for q, name, s in held.rows():
            yield pd.DataFrame({"qid": ids[q], key: name, "ms": s})

    kind = items.schema[key].dataType.simpleString()
    found = items.select(F.col(key).alias("k"), F.col(vec).alias("v")).mapInPandas(run, f"qid long, `{key}` {kind}, ms double")
    return best(found, k, "ms", key)


def bm25(queries: DataFrame, counts: DataFrame, stats: DataFrame, spec: FuseSpec = FuseSpec()) -> DataFrame:
    """qid, chunk_key, bm25 of chunks that share a word. ``counts``: chunk_key, n_tok, term, cnt of single words; ``stats``: one row n_chunks, avg_len."""
    words = queries.select("qid", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    freq = counts.groupBy("term").agg(F.count("*").alias("df"))
    return _bm25_sum(counts.join(words, "term").join(freq, "term").join(F.broadcast(stats)), spec)


def _bm25_sum(hit: DataFrame, spec: FuseSpec) -> DataFrame:
    idf = F.ln(1 + (F.col("n_chunks") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    tf = F.col("cnt") * (spec.k1 + 1) / (F.col("cnt") + spec.k1 * (1 - spec.b + spec.b * F.col("n_tok") / F.col("avg_len")))
    return hit.select("qid", "chunk_key", (idf * tf).alias("x")).groupBy("qid", "chunk_key").agg(F.sum("x").alias("bm25"))


def bm25_of_chunks(queries: DataFrame, chunks: DataFrame, spec: FuseSpec = FuseSpec()) -> DataFrame:
    """``bm25`` from chunks of words. Only words that a question asks for leave the scan, as one array of numbers a chunk; they are dealt out by chunk once,
    and counts, scores and sums stay where they are. Questions are one small table, broadcast with the frequencies of their words."""
    spark = chunks.sparkSession
    words = queries.select("qid", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    asked = words.select("term").distinct().select("term", F.row_number().over(Window.orderBy("term")).alias("id"))
    words = written(words.join(F.broadcast(asked), "term"), "words")
    asked = F.broadcast(words.select("term", "id").distinct())
    hit = chunks.select("chunk_key", "n_tok", F.explode("tokens").alias("term")).join(asked, "term")
    held = hit.groupBy("chunk_key").agg(F.collect_list(F.col("n_tok").cast("long") * 2**32 + F.col("id")).alias("x"))
    counts = held.select("chunk_key", F.explode("x").alias("x")).groupBy("chunk_key", "x").agg(F.count("*").alias("cnt"))
    counts = counts.select("chunk_key", F.expr("x div 4294967296").alias("n_tok"), (F.col("x") % 2**32).alias("id"), "cnt")
    with clean_shuffles(spark):
        freq = written(counts.groupBy("id").agg(F.count("*").alias("df")), "freq")
        stats = written(chunk_stats(chunks), "stats")
    hit = counts.join(F.broadcast(freq), "id").join(F.broadcast(stats)).join(F.broadcast(words.select("qid", F.col("id").cast("long").alias("id"))), "id")
    return _bm25_sum(hit, spec)


def chunk_stats(chunks: DataFrame) -> DataFrame:
    return chunks.agg(F.count("*").alias("n_chunks"), F.avg("n_tok").alias("avg_len"))


def scaled(sparse: DataFrame, how: str) -> DataFrame:
    per = Window.partitionBy("qid")
    if how == "raw":
        return sparse
    top = F.max("bm25").over(per)
    if how == "query_max":
        return sparse.withColumn("bm25", F.col("bm25") / F.nullif(top, F.lit(0.0)))
    low = F.min("bm25").over(per)
    return sparse.withColumn("bm25", F.coalesce((F.col("bm25") - low) / F.nullif(top - low, F.lit(0.0)), F.lit(1.0)))


def fuse(dense: DataFrame, sparse: DataFrame, spec: FuseSpec = FuseSpec()) -> DataFrame:
    """qid, chunk_key, ms, bm25, hs: weighted mean of both scores; a missing one counts 0."""
    both = dense.join(scaled(sparse, spec.bm25_scale), ["qid", "chunk_key"], "full")
    both = both.select("qid", "chunk_key", F.coalesce("ms", F.lit(0.0)).alias("ms"), F.coalesce("bm25", F.lit(0.0)).alias("bm25"))
    return both.withColumn("hs", (1 - spec.weight) * F.col("ms") + spec.weight * F.col("bm25"))


def fused_top(queries: DataFrame, chunks: DataFrame, counts: DataFrame, spec: FuseSpec = FuseSpec()) -> DataFrame:
    """Exact k best of the mixture over all chunks: a chunk's words ride along with its vector, so no pair that can win is lost."""
    return sliced(queries, lambda q: _fused_top(q, chunks, counts, spec))


def _fused_top(queries: DataFrame, chunks: DataFrame, counts: DataFrame, spec: FuseSpec) -> DataFrame:
    if spec.bm25_scale == "raw":
        return _keyword_top(queries, chunks, counts, spec, spec.weight, spec.k)
    sparse = scaled(bm25(queries, counts, chunk_stats(chunks), spec), spec.bm25_scale)
    ride = sparse.groupBy("chunk_key").agg(F.collect_list(F.struct("qid", "bm25")).alias("hits"))
    rows = chunks.select("chunk_key", "vec").join(ride, "chunk_key", "left")
    qids, q = collected_queries(queries)
    shared = chunks.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), q))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, mat = shared.value
        no = {int(x): i for i, x in enumerate(ids)}
        for pdf in batches:
            if not len(pdf) or not len(ids):
                continue
            m = np.array(pdf["vec"].tolist(), np.float32)
            ms = (mat @ m.T).astype(float)
            b = np.zeros_like(ms)
            for j, hits in enumerate(pdf["hits"]):
                if hits is not None:
                    for h in hits:
                        b[no[h["qid"]], j] = h["bm25"]
            hs = np.round((1 - spec.weight) * ms + spec.weight * b, 6)
            names = pdf["chunk_key"].to_numpy()
            rank = np.argsort(names, kind="stable")
            for i in range(len(ids)):
                top = rank[np.argsort(-hs[i][rank], kind="stable")[: spec.k]]
                yield pd.DataFrame({"qid": ids[i], "chunk_key": names[top], "ms": ms[i][top], "bm25": b[i][top], "hs": hs[i][top]})

    return best(rows.mapInPandas(run, "qid long, chunk_key string, ms double, bm25 double, hs double"), spec.k, "hs", "chunk_key")


#: So many words, those that most pairs of a question and a chunk share, are columns of a matrix; the others are added pair by pair.
COMMON = 512


def keyword_top(queries: DataFrame, chunks: DataFrame, counts: DataFrame, spec: FuseSpec, k: int) -> DataFrame:
    """qid, chunk_key, bm25, rk: the k best chunks that share a word with the question."""
    return sliced(queries, lambda q: _keyword_top(q, chunks, counts, spec, 1.0, k)).select("qid", "chunk_key", "bm25", "rk")


def mixture_among(queries: DataFrame, chunks: DataFrame, counts: DataFrame, groups: DataFrame, asked: DataFrame, weight: float, k: int) -> DataFrame:
    """qid, chunk_key, hs, rk: the k best of the mixture, keyword scores as a share of the question's largest, among chunks (groups: chunk_key, label) of the groups
    that each question asks for (asked: qid, label)."""

    def run(q: DataFrame) -> DataFrame:
        return _keyword_top(q, chunks.join(groups, "chunk_key"), counts, FuseSpec(), weight, k, asked, _keyword_top(q, chunks, counts, FuseSpec(), 1.0, 1), chunks)

    return sliced(queries, run).select("qid", "chunk_key", "hs", "rk")


def _keyword_top(queries: DataFrame, chunks: DataFrame, counts: DataFrame, spec: FuseSpec, weight: float, k: int, asked_groups: DataFrame | None = None, largest: DataFrame | None = None, corpus: DataFrame | None = None) -> DataFrame:
    """qid, chunk_key, ms, bm25, hs, rk: the k best of the mixture. No row is made for a question and a chunk that share a word, as most do: chunks carry the
    numbers and counts of their asked words to tasks that hold all words of the questions, and keyword scores are products of both.
    At ``weight`` 1, chunks that share no word are left out. With ``asked_groups`` only chunks of those labels count (a chunk has one), and keyword scores are
    divided by the question's ``largest``; ``corpus`` then has all chunks."""
    words = queries.select("qid", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    freq = counts.join(words.select("term").distinct(), "term", "left_semi").groupBy("term").agg(F.count("*").alias("df"))
    asked = written(freq.select("term", "df", (F.row_number().over(Window.orderBy("term")) - 1).alias("id")), "asked")
    hits = counts.join(asked.select("term", "id"), "term").groupBy("chunk_key").agg(F.collect_list("id").alias("ids"), F.collect_list("cnt").alias("cnts"))
    rows = chunks.select("chunk_key", "n_tok", "vec", *(["label"] if asked_groups is not None else [])).join(hits, "chunk_key", "left")
    stats = chunk_stats(chunks if corpus is None else corpus).first()
    qids, q = collected_queries(queries)
    df = np.array(asked.select("id", "df").toArrow().sort_by("id")["df"], float)
    pairs = words.join(asked.select("term", "id"), "term").select("qid", "id").toArrow().sort_by([("id", "ascending"), ("qid", "ascending")])
    asker, term = np.searchsorted(np.array(qids, np.int64), pairs["qid"].to_numpy()).astype(np.int32), pairs["id"].to_numpy().astype(np.int32)
    idf = np.log(1 + (stats.n_chunks - df + 0.5) / (df + 0.5))
    share, label_of, wants = np.ones(len(qids)), {}, np.zeros((0, 2), np.int64)
    if asked_groups is not None:
        top = largest.select("qid", "bm25").toArrow()
        share[np.searchsorted(qids, top["qid"].to_numpy())] = 1 / top["bm25"].to_numpy()
        own = asked_groups.join(queries.select("qid"), "qid", "left_semi").distinct().toArrow()
        label_of = {x: i for i, x in enumerate(own["label"].unique().to_pylist())}
        wants = np.array([[label_of[x] for x in own["label"].to_pylist()], np.searchsorted(qids, own["qid"].to_numpy())], np.int64).T
        wants = wants[np.lexsort((wants[:, 1], wants[:, 0]))]
    shared = chunks.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), q, asker, term, idf, df, share, label_of, wants))
    grouped = asked_groups is not None
    avg_len = stats.avg_len

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, mat, asker, term, idf, df, share, label_of, wants = shared.value
        if grouped:
            mat = mat / np.maximum(np.linalg.norm(mat.astype(float), axis=1, keepdims=True), 1e-12)
        start = np.searchsorted(term, np.arange(len(idf) + 1))
        common = np.argsort(-df * np.diff(start), kind="stable")[:COMMON]
        column = np.full(len(idf), -1)
        column[common] = np.arange(len(common))
        own = column[term] >= 0
        asks = np.zeros((len(ids), len(common)))
        asks[asker[own], column[term[own]]] = idf[term[own]]
        held = Best(len(ids), k)
        for pdf in batches:
            for at in range(0, len(pdf) if len(ids) else 0, ITEMS // 8):
                part = pdf.iloc[at : at + ITEMS // 8]
                names, m = part["chunk_key"].to_numpy(), np.array(part["vec"].tolist(), np.float32)
                if grouped:
                    m = m / np.maximum(np.linalg.norm(m.astype(float), axis=1, keepdims=True), 1e-12)
                    code, of_code = np.unique([label_of.get(x, -1) for x in part["label"]], return_inverse=True)
                    fits = np.zeros((len(ids), len(code)), bool)
                    for c, x in enumerate(code):
                        if x >= 0:
                            fits[wants[slice(*np.searchsorted(wants[:, 0], (x, x + 1))), 1], c] = True
                some = [([], []) if x is None else (x, y) for x, y in zip(part["ids"], part["cnts"])]
                j = np.repeat(np.arange(len(part)), [len(x) for x, _ in some])
                t, cnt = (np.concatenate([np.asarray(x[c], np.int64) for x in some]) for c in (0, 1))
                tf = cnt * (spec.k1 + 1) / (cnt + spec.k1 * (1 - spec.b + spec.b * part["n_tok"].to_numpy()[j] / avg_len))
                inside = column[t] >= 0
                has = np.zeros((len(common), len(part)))
                has[column[t[inside]], j[inside]] = tf[inside]
                j, t, tf = j[~inside], t[~inside], tf[~inside]
                many = start[t + 1] - start[t]
                at_pair = np.repeat(start[t] - np.cumsum(many) + many, many) + np.arange(many.sum())
                who, of, x = asker[at_pair], np.repeat(j, many), np.repeat(tf * idf[t], many)
                order = np.argsort(who, kind="stable")
                who, of, x = who[order], of[order], x[order]
                for i in range(0, len(ids), QUESTIONS):
                    b, mine = asks[i : i + QUESTIONS] @ has, slice(*np.searchsorted(who, (i, i + QUESTIONS)))
                    b += np.bincount((who[mine] - i) * b.shape[1] + of[mine], weights=x[mine], minlength=b.size).reshape(b.shape)
                    ms = (mat[i : i + QUESTIONS] @ m.T).astype(float)
                    b *= share[i : i + QUESTIONS, None]
                    hs = np.round((1 - weight) * ms + weight * b, 6)
                    if grouped:
                        hs = np.where(fits[i : i + QUESTIONS][:, of_code], hs, -np.inf)
                    held.add(i, np.where(b > 0, hs, -np.inf) if weight == 1 else hs, names, ms, b)
        for n, name, hs, ms, b in held.rows():
            yield pd.DataFrame({"qid": ids[n], "chunk_key": name, "ms": ms, "bm25": b, "hs": hs})

    return best(rows.mapInPandas(run, "qid long, chunk_key string, ms double, bm25 double, hs double"), k, "hs", "chunk_key")


def candidate_labels(retrieved: DataFrame, labels: DataFrame) -> DataFrame:
    """qid and the sorted labels of its retrieved chunks; labels: chunk_key, label."""
    return retrieved.join(labels, "chunk_key").groupBy("qid").agg(F.array_sort(F.collect_set("label")).alias("labels"))


def build_prompt(question: Column, graph: Column, passages: Column, instruction: str) -> Column:
    return F.concat_ws("\n", F.lit(instruction), F.concat(F.lit("Question: "), question), F.concat(F.lit("Evidence: "), F.coalesce(graph, F.lit(""))), F.concat(F.lit("Passages: "), F.coalesce(F.array_join(passages, " || "), F.lit(""))))


def word_count(text: Column) -> Column:
    return F.size(tokens(F.coalesce(text, F.lit("")))).cast("long")
