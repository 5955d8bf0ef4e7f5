"""Near-duplicate documents by ProbMinHash.

A text is the weighted set of its five-word shingles (weight: how often one occurs). Each shingle is a Poisson process whose
rate is its weight; an arrival falls into a random register, which keeps the shingle of its earliest arrival; a
shingle stops once its next arrival is later than every register. Two texts agree in a register with the probability Jaccard
similarity, which for plain sets is the Jaccard similarity and doesn't change when a text is repeated.

BANDS bands of ROWS registers find candidates: at similarity 0.8 a pair shares a band with probability 1 - (1 - 0.8**5)**24,
over 0.9999. Equal texts are one node. Every two nodes of a bucket are held against each other on whole texts by the exact similarity, unless both are
already in one class: the pairs of small buckets as rows, once each, those of large buckets inside blocks (`blocks`). Links are joined by
distributed union-find.

Defined cases: a text under five words is one shingle; texts without words match equal texts only; a null text is a class of its own; a
null id is replaced by a negative number made from the text; rows that repeat an id and text are in the same class, and one of them stays; unequal texts with one id
are different nodes: the class of each is named by its own least id and told apart by class_md5, the checksum of the text that stays; an empty
table gives an empty result; extra columns stay, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.llm import blocks
from evigraph.llm.blocks import similarity
from evigraph.llm.common import documents, forget, free, saved
from evigraph.llm.components import components, joined_on
from evigraph.llm.hashing import U, mix, shingles, word_hashes

WORDS, THRESHOLD = 5, 0.8
BANDS, ROWS = 24, 5
REGISTERS = BANDS * ROWS
BATCH = 120_000


def weighted(text: str) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(shingles(word_hashes(text), WORDS), return_counts=True)


def signatures(sets: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """One row of registers for each weighted set; sets must not be empty."""
    count = len(sets)
    doc = np.repeat(np.arange(count), [len(e) for e, _ in sets])
    item = np.concatenate([e for e, _ in sets])
    rate = np.concatenate([w for _, w in sets]).astype(float)
    first = np.full(count * REGISTERS, np.inf)
    held = np.zeros(count * REGISTERS, U)
    at, turn = np.zeros(len(item)), 0
    while len(item):
        turn += 1
        h = mix(item ^ U(turn * 0xA24BAED4963EE407 % 2**64))
        at = at - np.log(((h >> U(11)).astype(float) + 0.5) * 2.0**-53) / rate
        cell = doc * REGISTERS + (((h & U(2047)) * U(REGISTERS)) >> U(11)).astype(np.int64)
        np.minimum.at(first, cell, at)
        won = first[cell] == at
        held[cell[won]] = item[won]
        live = at <= first.reshape(count, REGISTERS).max(axis=1)[doc]
        doc, item, rate, at = doc[live], item[live], rate[live], at[live]
    return held.reshape(count, REGISTERS)


def bands(registers: np.ndarray) -> np.ndarray:
    out = np.zeros((len(registers), BANDS), U)
    for r in range(ROWS):
        out = mix(out + registers[:, r::ROWS] + U(r + 1))
    return mix(out + np.arange(BANDS, dtype=U) * U(0x9FB21C651E98DF25)).view(np.int64)


SIGNED = "id long, key binary, bands array<long>"


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["id", "key", "bands"]
    for batch in batches:
        ids, keys, texts = batch.columns
        todo: list[tuple[int, tuple]] = []

        def rows(at: list[int], found: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([ids.take(at), keys.take(at), pa.array(found, pa.list_(pa.int64()))], names=names)

        held = 0
        for i in range(batch.num_rows):
            own = weighted(texts[i].as_py())
            if not len(own[0]):
                yield rows([i], [[]])
                continue
            todo.append((i, own))
            held += len(own[0])
            if held > BATCH:
                yield rows([i for i, _ in todo], list(bands(signatures([s for _, s in todo]))))
                todo, held = [], 0
        if todo:
            yield rows([i for i, _ in todo], list(bands(signatures([s for _, s in todo]))))


def with_id(df: DataFrame, key: str, text: str, name: str = "_id") -> DataFrame:
    missing = -1 - F.xxhash64(F.coalesce(F.col(text), F.lit(""))).bitwiseAND((1 << 62) - 1)
    return df.withColumn(name, F.coalesce(F.col(key).cast("long"), missing))


def checksum(text: str):
    return F.unhex(F.md5(F.col(text).cast("binary")))


def _verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Pairs (a, b) whose exact similarity is at the threshold; a set is kept while rows of the same b follow each other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple = (None, None)
        for batch in batches:
            a, b, s, t = batch.columns
            near = []
            for i in range(batch.num_rows):
                other = b[i].as_py()
                if held[0] != other:
                    held = (other, weighted(t[i].as_py()))
                if similarity(weighted(s[i].as_py()), held[1]) >= THRESHOLD:
                    near.append(i)
            at = pa.array(near, pa.int64())
            yield pa.RecordBatch.from_arrays([a.take(at), b.take(at)], names=["a", "b"])

    left = texts.select(F.col("node").alias("a"), F.col("t").alias("s"))
    right = texts.select(F.col("node").alias("b"), "t")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "s", "t").mapInArrow(run, "a long, b long")


def _roots(nodes: DataFrame, keyed: DataFrame, most: int, chars: int) -> DataFrame:
    """node, root of every node that is like another; nodes: key, id, node, bands; keyed: id, key, t."""
    banded = nodes.select("node", F.explode("bands").alias("b"))
    shared = banded.groupBy("b").agg(F.count("*").alias("n")).where("n > 1")
    met = saved(banded.hint("merge").join(shared, "b"), "members", light=True)
    wanted = nodes.join(met.select("node").distinct(), "node", "left_semi").select("node", "id", "key")
    texts = saved(keyed.join(wanted, ["key", "id"]).groupBy("key", "id", "node").agg(F.first("t").alias("t")).select("node", "t"), "texts")
    links = saved(_verified(blocks.pairs(met), texts), "links")
    dealt = saved(blocks.parted(met, texts, most, chars), "dealt", light=True)
    crowd = saved(blocks.within(dealt, texts, weighted, THRESHOLD), "crowd")
    roots = saved(components(links.unionByName(crowd), "a", "b"), "roots", light=True)
    if not dealt.where("parts > 1").isEmpty():
        rest = saved(blocks.across(dealt, roots, texts, weighted, THRESHOLD), "rest")
        roots = saved(joined_on(roots, rest), "roots", light=True)
    forget(met, texts, links, dealt, crowd)
    return roots


def _told(rows: DataFrame, text: str, most: int, chars: int) -> tuple[DataFrame, DataFrame]:
    """Saved tables of rows with a text (id, key: its checksum) and of distinct texts (key, class_id, class_key)."""
    keyed = rows.where(F.col(text).isNotNull()).select(F.col("_id").alias("id"), checksum(text).alias("key"), F.col(text).alias("t"))
    signed = saved(keyed.mapInArrow(_sign, SIGNED), "signatures")
    # One node for equal texts: its bands are the same in all rows, so any row's will do. Written, the numbers stand.
    one = signed.groupBy("key").agg(F.min("id").alias("id"), F.first("bands").alias("bands"))
    nodes = saved(one.withColumn("node", F.monotonically_increasing_id()), "nodes")
    roots = _roots(nodes, keyed, most, chars)
    tied = nodes.join(roots, "node").select("root", "key", "id")
    first = tied.groupBy("root").agg(F.min(F.struct("id", "key")).alias("f"))
    named = tied.join(first, "root").select("key", F.col("f.id").alias("class_id"), F.col("f.key").alias("class_key"))
    every = nodes.select("key", "id").join(named, "key", "left").select("key", F.coalesce("class_id", "id").alias("class_id"), F.coalesce("class_key", "key").alias("class_key"))
    every = saved(every, "named", light=True)
    forget(nodes, roots)
    return signed.select("id", "key"), every


def classes(df: DataFrame, key: str = "doc_id", text: str = "text", most: int = blocks.MEMBERS, chars: int = blocks.CHARS) -> DataFrame:
    """_id, _key (checksum of the text), class_id, class_key of every row: the least id of the class and, of that id, the least checksum."""
    rows = with_id(df.select(F.col(key), F.col(text)), key, text)
    signed, every = _told(rows, text, most, chars)
    # Both sides are plain tables, so a key that many rows share is split by the adaptive join.
    found = signed.join(every, "key").select(F.col("id").alias("_id"), F.col("key").alias("_key"), "class_id", "class_key")
    none = F.lit(None).cast("binary")
    return found.unionByName(rows.where(F.col(text).isNull()).select("_id", none.alias("_key"), F.col("_id").alias("class_id"), none.alias("class_key")))


def deduplicated(docs: DataFrame, key: str = "doc_id", text: str = "text", most: int = blocks.MEMBERS, chars: int = blocks.CHARS) -> DataFrame:
    """One row of each class: that of its least id. Rows with a null text stay."""
    signed, every = _told(with_id(docs.select(F.col(key), F.col(text)), key, text), text, most, chars)
    a, b = free(docs, "_id"), free(docs, "_key")
    out = signed.join(every, "key").where("id <> class_id or key <> class_key").select(F.col("id").alias(a), F.col("key").alias(b)).distinct()
    out = saved(out, "dropped", light=True)
    rows = with_id(docs, key, text, a).withColumn(b, F.when(F.col(text).isNotNull(), checksum(text)))
    left = rows.join(out, [a, b], "left_anti")
    if signed.groupBy("id", "key").count().where("count > 1").isEmpty():
        return left.drop(a, b)
    some = left.where(F.col(text).isNotNull()).dropDuplicates([a, b])
    return some.unionByName(left.where(F.col(text).isNull())).drop(a, b)


def op4_probminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class of every document."""
    kept = F.coalesce((F.col("_id") == F.col("class_id")) & (F.col("_key") == F.col("class_key")), F.lit(True))
    return classes(documents(spark, sf_dir)).select(F.col("_id").alias("doc_id"), "class_id", kept.alias("kept"), F.lower(F.hex("class_key")).alias("class_md5"))


QUERIES = {"op4_probminhash": op4_probminhash}
