"""Synonym edges: pairs of vectors whose cosine exceeds a threshold."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import acos, ceil, log, log2, pi

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.runtime import clean_shuffles, written

#: Members of a block of a bucket; a larger bucket is dealt into parts that meet two by two.
BLOCK = 1024
#: Vectors of a block where blocks are compared whole, and so many compared pairs cost as much as a vector sent to a bucket.
MEMBERS, PAIRS_A_ROW = 16384, 1000
#: Bands that vectors are sent to at a time, so that no more copies are on disk.
BANDS = 8
#: A row is a pair of blocks there, so one goes into a batch.
ONE_PAIR = {"spark.sql.execution.arrow.maxRecordsPerBatch": "1"}


def tuned(n: int, phi: float, recall: float = 0.99) -> tuple[int, int]:
    """bands, bits: buckets of some 32 unrelated vectors, and as many bands as a pair at the threshold needs for the recall."""
    bits = min(16, max(4, ceil(log2(max(n, 2) / 32))))
    same = (1 - acos(min(1.0, phi)) / pi) ** bits
    return max(1, ceil(log(1 - recall) / log(1 - same))) if same < 1 else 1, bits


def signs(vecs: DataFrame, key: str, bands: int, bits: int, seed: int = 7, own: slice = slice(None)) -> DataFrame:
    """k, vec, band: signs of random projections in bands, or in those of ``own``. A pair at angle a shares a band with probability (1 - a / pi)**bits."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if not len(pdf):
                continue
            m = np.array(pdf["vec"].tolist(), np.float32)
            b = codes(m, bands, bits, seed).astype(np.int64) + (np.arange(bands) << bits)
            yield pd.DataFrame({"k": pdf["k"], "bands": list(b[:, own]), "vec": pdf["vec"]})

    kind = vecs.schema[key].dataType.simpleString()
    found = vecs.select(F.col(key).alias("k"), "vec").mapInPandas(run, f"k {kind}, bands array<long>, vec array<float>")
    return found.select("k", "vec", F.explode("bands").alias("band"))


def edges_lsh(vecs: DataFrame, phi: float, key: str = "node_key", recall: float = 0.99, block: int = BLOCK, whole: bool | None = None) -> DataFrame:
    """src, dst, cos of pairs above phi that share a band. Bands and bits follow from phi, the number of vectors and the recall at phi. ``whole`` sets the way
    to the same pairs, else their cost: by buckets, which send a vector to each of its bands, or, where these are too many, by products of whole blocks."""
    n = vecs.count()
    bands, bits = tuned(n, phi, recall)
    if n <= PAIRS_A_ROW * 2 * bands if whole is None else whole:
        with clean_shuffles(vecs.sparkSession, **ONE_PAIR):
            return written(met_in_blocks(vecs, phi, key, n, bands, bits).where("met").drop("met"), "pairs", compression="zstd")
    with clean_shuffles(vecs.sparkSession):
        passes = [written(_by_buckets(vecs, phi, key, bands, bits, block, slice(at, at + BANDS)), "pairs", compression="zstd") for at in range(0, bands, BANDS)]
    return reduce(DataFrame.unionByName, passes).groupBy("src", "dst").agg(F.max("cos").alias("cos"))


def recall_of_bands(vecs: DataFrame, phi: float, key: str = "node_key", recall: float = 0.99) -> DataFrame:
    """One row pairs, recall: the number of pairs above phi and the share of them that ``edges_lsh`` finds. Pairs are counted where they are found."""
    n = vecs.count()
    with clean_shuffles(vecs.sparkSession, **ONE_PAIR):
        return written(met_in_blocks(vecs, phi, key, n, *tuned(n, phi, recall)).agg(F.count("*").alias("pairs"), F.avg(F.col("met").cast("int")).alias("recall")), "recall")


def met_in_blocks(vecs: DataFrame, phi: float, key: str, n: int, bands: int, bits: int) -> DataFrame:
    """src, dst, cos, met of all pairs above phi, met if they share a band. Vectors are written once, in blocks; a row is a pair of blocks,
    read from that table. Keys are distinct."""
    blocks = max(1, ceil(n / min(MEMBERS, max(1024, (1 << 25) // bands))), min(8, n // 1024))
    dealt = vecs.where("vec is not null").select(F.col(key).alias("k"), "vec", F.pmod(F.xxhash64(key), F.lit(blocks)).alias("i"))
    held = written(dealt.groupBy("i").agg(F.collect_list("k").alias("k"), F.flatten(F.collect_list("vec")).alias("v")), "blocks")
    other = held.toDF(*[f"{c}2" for c in held.columns])
    kind = vecs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                i, j = b["i"][r].as_py(), b["i2"][r].as_py()
                k, p, c = one = side(b["k"][r].values, b["v"][r].values)
                l, q, d = one if i == j else side(b["k2"][r].values, b["v2"][r].values)
                q32 = q.astype(np.float32).T
                for at in range(0, len(p), BLOCK):
                    x, y = np.nonzero(p[at : at + BLOCK].astype(np.float32) @ q32 > phi - 1e-5)
                    x += at
                    if i == j:
                        x, y = x[x < y], y[x < y]
                    for z in range(0, len(x), 1 << 16):
                        yield above(k, l, p, q, c, d, x[z : z + (1 << 16)], y[z : z + (1 << 16)])

    def side(keys: pa.Array, values: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        m = values.to_numpy(zero_copy_only=False).reshape(len(keys), -1)
        unit = m.astype(float)
        return keys, unit / np.maximum(np.linalg.norm(unit, axis=1, keepdims=True), 1e-12), codes(m, bands, bits)

    def above(k, l, p, q, c, d, x, y) -> pa.RecordBatch:
        cos = np.einsum("ij,ij->i", p[x], q[y])
        x, y, cos = x[cos > phi], y[cos > phi], cos[cos > phi]
        met, open_ = np.zeros(len(x), bool), np.arange(len(x))
        for at in range(0, bands, 64):  # most pairs meet in the first bands
            same = (c[x[open_], at : at + 64] == d[y[open_], at : at + 64]).any(axis=1)
            met[open_[same]] = True
            open_ = open_[~same]
        u, v = k.take(pa.array(x)), l.take(pa.array(y))
        apart = pc.not_equal(u, v)
        u, v, cos, met = u.filter(apart), v.filter(apart), cos[apart.to_numpy(zero_copy_only=False)], met[apart.to_numpy(zero_copy_only=False)]
        low = pc.less(u, v)
        return pa.RecordBatch.from_arrays([pc.if_else(low, u, v), pc.if_else(low, v, u), pa.array(cos), pa.array(met)], names=["src", "dst", "cos", "met"])

    return held.hint("shuffle_replicate_nl").join(other, F.col("i") <= F.col("i2")).mapInArrow(run, f"src {kind}, dst {kind}, cos double, met boolean")


def codes(m: np.ndarray, bands: int, bits: int, seed: int = 7) -> np.ndarray:
    """Which sides of random planes vectors lie on, in bands of ``bits`` planes; a row a vector."""
    planes, out = np.random.default_rng(seed).standard_normal((m.shape[1], bands * bits)).astype(np.float32), np.zeros((len(m), bands), np.uint16)
    m, power = np.asarray(m, np.float32), (1 << np.arange(bits)).astype(np.float32)
    for at in range(0, len(m), BLOCK):
        for b in range(0, bands, 64):
            side = (m[at : at + BLOCK] @ planes[:, b * bits : (b + 64) * bits] > 0).astype(np.float32)
            out[at : at + BLOCK, b : b + 64] = (side.reshape(-1, bits) @ power).reshape(len(side), -1)
    return out


def _by_buckets(vecs: DataFrame, phi: float, key: str, bands: int, bits: int, block: int, own: slice) -> DataFrame:
    """A bucket is a task's matrix product, a large one is dealt into parts that meet two by two, so only pairs above phi are ever rows."""
    rows = signs(vecs, key, bands, bits, own=own)
    sizes = rows.groupBy("band").agg(F.count("*").alias("n")).where("n > 1").select("band", F.ceil(F.col("n") / block).cast("int").alias("parts"))
    dealt = rows.join(sizes, "band").withColumn("part", F.pmod(F.xxhash64("k"), "parts").cast("int"))
    met = dealt.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("band", F.least("part", "o").alias("i"), F.greatest("part", "o").alias("j"), "part", "k", "vec")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        for pdf in batches:
            if not len(pdf):
                continue
            g = pdf[["band", "i", "j"]].to_numpy()
            if held and (held[-1][["band", "i", "j"]].to_numpy()[-1] != g[0]).any():
                yield above(pd.concat(held))
                held = []
            cuts = [0, *(np.flatnonzero((g[1:] != g[:-1]).any(axis=1)) + 1).tolist(), len(g)]
            for a, z in zip(cuts[:-2], cuts[1:-1]):
                yield above(pd.concat([*held, pdf.iloc[a:z]]))
                held = []
            held.append(pdf.iloc[cuts[-2] :])
        if held:
            yield above(pd.concat(held))

    def above(pdf: pd.DataFrame) -> pd.DataFrame:
        m = np.array(pdf["vec"].tolist(), float)
        m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)
        s = m @ m.T
        x, y = np.nonzero(s > phi)
        k, part = pdf["k"].to_numpy(), pdf["part"].to_numpy()
        own = k[x] < k[y]
        if pdf["i"].iloc[0] != pdf["j"].iloc[0]:
            own &= part[x] != part[y]
        x, y = x[own], y[own]
        return pd.DataFrame({"src": k[x], "dst": k[y], "cos": s[x, y]})

    kind = vecs.schema[key].dataType.simpleString()
    found = met.repartition("band", "i", "j").sortWithinPartitions("band", "i", "j").mapInPandas(run, f"src {kind}, dst {kind}, cos double")
    return found.groupBy("src", "dst").agg(F.max("cos").alias("cos"))


def pairs_exact(vecs: DataFrame, phi: float, key: str, blocks: int = 8) -> DataFrame:
    """All pairs u < v above phi by block products: each pair of blocks is one task's matrix product. For tests and small tables."""
    b = vecs.select(F.col(key).alias("k"), F.col("vec"), F.pmod(F.xxhash64(key), F.lit(blocks)).alias("block"))
    left = b.select("*", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other")).select("k", "vec", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block")
    # Each row meets every block once: its copies go to the tasks (i, j) of its block.
    kind = vecs.schema[key].dataType.simpleString()

    def product(pdf: pd.DataFrame) -> pd.DataFrame:
        i, j = int(pdf["i"].iloc[0]), int(pdf["j"].iloc[0])
        x, y = pdf[pdf["block"] == i], pdf[pdf["block"] == j]
        if not len(x) or not len(y):
            return pd.DataFrame({"u": [], "v": [], "cos": []})
        p, q = np.array(x["vec"].tolist(), float), np.array(y["vec"].tolist(), float)
        p /= np.maximum(np.linalg.norm(p, axis=1, keepdims=True), 1e-12)
        q /= np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-12)
        s = p @ q.T
        r, c = np.nonzero(s > phi)
        a, z = x["k"].to_numpy()[r], y["k"].to_numpy()[c]
        keep = a < z if i == j else np.ones(len(a), bool)
        return pd.DataFrame({"u": np.minimum(a, z)[keep], "v": np.maximum(a, z)[keep], "cos": s[r, c][keep]})

    return left.groupBy("i", "j").applyInPandas(product, f"u {kind}, v {kind}, cos double")
