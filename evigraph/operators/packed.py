"""Document frequencies of word n-grams without a row for each occurrence.

Chunks are written once in blocks. For each n, and for one class of hashes after the other, a block sends the 128-bit hashes of its n-grams as packed
arrays, dealt by hash; a part counts equal ones and sends the frequencies back in the order received. So all n-grams are counted, but only a share of
them is on disk at a time, at 16 bytes each. Equal hashes count as equal n-grams, as md5 does for texts.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pandas.util import hash_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.runtime import clean_shuffles, forget, written

#: Rows of a block, and classes of hashes that are counted one after the other.
ROWS, CLASSES = 1000, 2
#: What the names of blocks of known terms begin with.
KNOWN = "known "
PACKED = "block string, keys array<string>, texts array<string>"
#: Keys of the two halves of a word's SipHash, and odd factors that mix them into those of n-grams.
SIP = ("evigraph packed0", "evigraph packed1")
ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F], np.uint64)


def small_batches(spark: SparkSession, rows: int = 64):
    """Rows here are blocks, so few go into a batch."""
    return clean_shuffles(spark, **{"spark.sql.execution.arrow.maxRecordsPerBatch": str(rows)})


def blocks(chunks: DataFrame) -> DataFrame:
    """block, keys, texts: chunks of words in runs of some ROWS; chunks of one key lie in one block, as those of one size count as one."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys: list[str] = []
        texts: list[str] = []
        last = None

        def made() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().hex]), pa.array([keys], pa.list_(pa.string())), pa.array([texts], pa.list_(pa.string()))], names=["block", "keys", "texts"])

        for b in batches:
            for k, _, t in zip(*(c.to_pylist() for c in b.columns)):
                if len(keys) >= ROWS and k != last:
                    yield made()
                    keys, texts = [], []
                keys.append(k)
                texts.append(t)
                last = k
        if keys:
            yield made()

    rows = chunks.select("chunk_key", "n_tok", F.array_join("tokens", " ").alias("text")).repartition("chunk_key").sortWithinPartitions("chunk_key", "n_tok")
    with small_batches(chunks.sparkSession, ROWS):
        return written(rows.mapInArrow(cut, PACKED), "blocks", compression="zstd", **{"parquet.block.size": 16 << 20})


class Block:
    """Words of a block as a matrix of codes, a row a chunk, with the owner (distinct key and size) of each row."""

    def __init__(self, keys: list[str], texts: pa.Array):
        lists = pc.split_pattern(texts, " ")
        enc = lists.flatten().dictionary_encode()
        self.size = np.diff(lists.offsets.to_numpy())
        self.vocab = enc.dictionary
        self.code = np.zeros((len(self.size), int(self.size.max())), np.int32)
        self.code[np.arange(self.code.shape[1]) < self.size[:, None]] = enc.indices.to_numpy()
        words = self.vocab.to_numpy(zero_copy_only=False)
        self.hash = np.column_stack([hash_array(words, hash_key=k, categorize=False) for k in SIP])
        no: dict[tuple, int] = {}
        self.owner = np.array([no.setdefault(x, len(no)) for x in zip(keys, self.size.tolist())])
        self.keys, self.owners = [k for k, _ in no], len(no)
        self.own_size = np.array([n for _, n in no])

    def grams(self, n: int) -> tuple[np.ndarray, ...]:
        """owner, row, position, count, and both halves of the hash of each distinct n-gram of each owner, by owner."""
        width = self.code.shape[1] - n + 1
        if width < 1:
            return *(np.zeros(0, np.int64) for _ in range(4)), *(np.zeros(0, np.uint64) for _ in range(2))
        half = []
        for lane in (0, 1):
            word, acc = self.hash[:, lane].copy(), np.full((len(self.code), width), n, np.uint64)
            for j in range(n):
                acc ^= acc >> np.uint64(29)
                acc *= ODD[lane]
                acc += word[self.code[:, j : j + width]]
            acc ^= acc >> np.uint64(32)
            acc *= ODD[1 - lane]
            half.append(acc ^ (acc >> np.uint64(29)))
        fine = np.arange(width) <= (self.size - n)[:, None]
        if self.owners == len(self.code):
            hi = np.where(fine, half[0], np.uint64(2**64 - 1))
            at = np.argsort(hi, axis=1)
            hi, lo, fine = (np.take_along_axis(x, at, 1) for x in (hi, half[1], fine))
            same = hi[:, 1:] == hi[:, :-1]
            if not (same & fine[:, 1:] & fine[:, :-1] & (lo[:, 1:] != lo[:, :-1])).any() and not (fine[:, 1:] & ~fine[:, :-1]).any():
                new = fine.copy()
                new[:, 1:] &= ~same
                row, col = np.nonzero(new)
                start = np.flatnonzero(new[fine])  # valid cells in order, row by row
                cnt = np.diff(np.append(start, int(fine.sum())))
                return row, row, at[row, col], cnt, hi[row, col], lo[row, col]
            fine = np.arange(width) <= (self.size - n)[:, None]
        row, col = np.nonzero(fine)
        own, hi, lo = self.owner[row], half[0][row, col], half[1][row, col]
        o = np.lexsort((lo, hi, own))
        row, col, own, hi, lo = (x[o] for x in (row, col, own, hi, lo))
        new = np.ones(len(own), bool)
        new[1:] = (own[1:] != own[:-1]) | (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1])
        start = np.flatnonzero(new)
        return own[start], row[start], col[start], np.diff(np.append(start, len(own))), hi[start], lo[start]

    def terms(self, n: int, row: np.ndarray, pos: np.ndarray) -> pa.Array:
        words = [self.vocab.take(pa.array(self.code[row, pos + j])) for j in range(n)]
        return pc.binary_join_element_wise(*words, " ") if n > 1 else words[0]


def of_batch(b: pa.RecordBatch) -> Iterator[tuple[int, Block]]:
    keys, texts = b.column(b.schema.get_field_index("keys")), b.column(b.schema.get_field_index("texts"))
    for i in range(b.num_rows):
        yield i, Block(keys[i].as_py(), texts[i].values)


def bucket(hi: np.ndarray, lo: np.ndarray, parts: int) -> np.ndarray:
    """Class and part of each hash, as one number."""
    return ((hi >> np.uint64(40)) % np.uint64(CLASSES) * np.uint64(parts) + lo % np.uint64(parts)).astype(np.int64)


def sent(blocked: DataFrame, n: int, own: int, parts: int) -> DataFrame:
    """part, block, hashes of one class: what the parts count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, block in of_batch(b):
                hi, lo = block.grams(n)[4:]
                k = bucket(hi, lo, parts)
                o = np.argsort(k, kind="stable")
                k, hi, lo = k[o], hi[o], lo[o]
                cuts = np.searchsorted(k, own * parts + np.arange(parts + 1))
                rows = [(r, hi[x:y].tobytes() + lo[x:y].tobytes()) for r, (x, y) in enumerate(zip(cuts[:-1], cuts[1:])) if y > x]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array([r for r, _ in rows], pa.int32()), pa.array([b.column(0)[i].as_py()] * len(rows)), pa.array([h for _, h in rows], pa.binary())], names=["part", "block", "hashes"])

    return blocked.mapInArrow(run, "part int, block string, hashes binary").repartition(parts, "part").sortWithinPartitions("part")


def by_part(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[str], np.ndarray, np.ndarray, list[int]]]:
    """Part, its blocks, both halves of their hashes and the number of each block."""

    def made(rows):
        sizes = [len(h) // 16 for _, h in rows]
        return [k for k, _ in rows], *(np.concatenate([np.frombuffer(h, np.uint64)[s * m : s * (m + 1)] for (_, h), s in zip(rows, sizes)]) for m in (0, 1)), sizes

    now, rows = None, []
    for b in batches:
        for part, k, h in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
            if part != now and rows:
                yield now, *made(rows)
                rows = []
            now = part
            rows.append((k, h))
    if rows:
        yield now, *made(rows)


def counted(hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order in which equal hashes lie together, and where each run starts."""
    o = np.argsort(hi)
    a, b = hi[o], lo[o]
    if ((a[1:] == a[:-1]) & (b[1:] != b[:-1])).any():
        o = np.lexsort((lo, hi))
        a, b = hi[o], lo[o]
    new = np.ones(len(o), bool)
    new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    return o, np.flatnonzero(new)


def n_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def frequencies(blocked: DataFrame, max_n: int, parts: int, known: dict[int, DataFrame] | None = None) -> list[DataFrame]:
    """Tables (block, n, bucket, bytes, df): frequencies of a block's n-grams in the order of their buckets, as packed numbers. With ``known``, blocks of terms
    of n words each, df is instead 1 for n-grams that are such terms and else 0."""
    marks, at = known is not None, dict.fromkeys(range(1, max_n + 1), blocked)
    if marks:
        at = {n: blocked.unionByName(known[n].withColumn("block", F.concat(F.lit(KNOWN), "block"))) for n in range(1, max_n + 1)}

    def run(own: int, n: int):
        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part, names, hi, lo, sizes in by_part(batches):
                o, start = counted(hi, lo)
                runs = np.diff(np.append(start, len(o)))
                df = np.empty(len(o), np.uint32)
                if not marks:
                    df[o] = np.repeat(runs, runs)
                else:
                    own_blocks = [not x.startswith(KNOWN) for x in names]
                    term = np.repeat(~np.array(own_blocks), sizes)
                    df[o] = np.repeat(np.maximum.reduceat(term[o], start), runs)
                    df, names, sizes = df[~term], [x for x, y in zip(names, own_blocks) if y], [x for x, y in zip(sizes, own_blocks) if y]
                    if not names:
                        continue
                kept = [x.astype(np.uint8) if x.max() < 256 else x.astype(np.uint16) if x.max() < 65536 else x for x in np.split(df, np.cumsum(sizes)[:-1])]
                m = len(names)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(names), pa.array([n] * m, pa.int32()), pa.array([own * parts + part] * m, pa.int32()), pa.array([x.itemsize for x in kept], pa.int32()), pa.array([x.tobytes() for x in kept], pa.binary())],
                    names=["block", "n", "bucket", "bytes", "df"],
                )

        return each

    with small_batches(blocked.sparkSession):
        return [written(sent(at[n], n, own, parts).mapInArrow(run(own, n), "block string, n int, bucket int, bytes int, df binary"), "df", compression="zstd") for n in range(1, max_n + 1) for own in range(CLASSES)]


def gram_totals(chunks: DataFrame, max_n: int) -> DataFrame:
    """n, pairs, occurrences, terms: (chunk, n-gram) pairs, all occurrences and distinct n-grams of each n."""
    spark, blocked = chunks.sparkSession, blocks(chunks)
    parts = n_parts(spark)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, block in of_batch(b):
                cnt = [np.maximum(block.size - n + 1, 0).sum() for n in range(1, max_n + 1)]
                yield pa.RecordBatch.from_arrays([pa.array(range(1, max_n + 1), pa.int32()), pa.array([0] * max_n, pa.int64()), pa.array(cnt, pa.int64()), pa.array([0] * max_n, pa.int64())], names=["n", "pairs", "occurrences", "terms"])

    def distinct(n: int):
        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for _, _, hi, lo, _ in by_part(batches):
                yield pa.RecordBatch.from_arrays([pa.array([n], pa.int32()), pa.array([len(hi)], pa.int64()), pa.array([0], pa.int64()), pa.array([len(counted(hi, lo)[1])], pa.int64())], names=["n", "pairs", "occurrences", "terms"])

        return each

    kind = "n int, pairs long, occurrences long, terms long"
    with small_batches(spark):
        done = [written(blocked.mapInArrow(local, kind), "totals")]
        done += [written(sent(blocked, n, own, parts).mapInArrow(distinct(n), kind), "totals") for n in range(1, max_n + 1) for own in range(CLASSES)]
    forget(blocked)
    rows = reduce(DataFrame.unionByName, done)
    return rows.groupBy("n").agg(*[F.sum(c).alias(c) for c in ("pairs", "occurrences", "terms")]).where("occurrences > 0")


def scored(chunks: DataFrame, max_n: int, kind: str, use, known: dict[int, DataFrame] | None = None) -> DataFrame:
    """Rows of ``kind`` that ``use(block, n_chunks, [(owner, row, position, count, df, n)])`` gives as a record batch for each block; ``known`` as in ``frequencies``."""
    spark, blocked = chunks.sparkSession, blocks(chunks)
    parts = n_parts(spark)
    n_chunks = blocked.agg(F.coalesce(F.sum(F.size("keys")), F.lit(0))).first()[0]
    df = frequencies(blocked, max_n, parts, known)
    width = {1: np.uint8, 2: np.uint16, 4: np.uint32}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, block in of_batch(b):
                got: dict[int, list] = {n: [] for n in range(1, max_n + 1)}
                for x in b.column(b.schema.get_field_index("x"))[i].as_py():
                    got[x["n"]].append((x["bucket"], np.frombuffer(x["df"], width[x["bytes"]])))
                found = []
                for n, rows in got.items():
                    own, row, pos, cnt, hi, lo = block.grams(n)
                    if len(own):
                        d = np.empty(len(own), np.int64)
                        d[np.argsort(bucket(hi, lo, parts), kind="stable")] = np.concatenate([v for _, v in sorted(rows, key=lambda r: r[0])])
                        found.append((own, row, pos, cnt, d, n))
                yield use(block, n_chunks, found)

    held = reduce(DataFrame.unionByName, df).groupBy("block").agg(F.collect_list(F.struct("n", "bucket", "bytes", "df")).alias("x"))
    with small_batches(spark, 8):
        out = written(blocked.join(held, "block").mapInArrow(run, kind), "scored", compression="zstd")
    forget(blocked, *df)
    return out


def er_of(block: Block, own: np.ndarray, cnt: np.ndarray, df: np.ndarray, n_chunks: int) -> np.ndarray:
    return cnt / block.own_size[own] * np.log((n_chunks + 1) / (df + 1)) / np.log(n_chunks + 1)


def summaries(chunks: DataFrame, max_n: int) -> DataFrame:
    """chunk_key, terms, top, low, dfs: number of n-grams, largest and least score, sum of frequencies of each owner (chunk key and size)."""

    def use(block: Block, n_chunks: int, found: list) -> pa.RecordBatch:
        own, cnt, df = (np.concatenate([f[i] for f in found]) for i in (0, 3, 4))
        o = np.argsort(own, kind="stable")
        own, er, df = own[o], er_of(block, own, cnt, df, n_chunks)[o], df[o]
        start = np.searchsorted(own, np.arange(block.owners))
        cols = [pa.array(block.keys), pa.array(np.diff(np.append(start, len(own)))), pa.array(np.maximum.reduceat(er, start)), pa.array(np.minimum.reduceat(er, start)), pa.array(np.add.reduceat(df, start))]
        return pa.RecordBatch.from_arrays(cols, names=["chunk_key", "terms", "top", "low", "dfs"])

    return scored(chunks, max_n, "chunk_key string, terms long, top double, low double, dfs long", use)


def candidates(chunks: DataFrame, max_n: int, min_df: int = 1, max_df: float = 1.0, tau: float | None = None, of_max: float | None = None, cap: int | None = None) -> DataFrame:
    """chunk_key, n_tok, n, term, cnt, df, n_chunks of every n-gram that a selection can keep: by frequencies, over ``tau`` or ``of_max`` of the owner's largest
    score, among its ``cap`` best. Bounds give way by 1e-8 and more, so that ties and the last digits are left to the selection."""

    def use(block: Block, n_chunks: int, found: list) -> pa.RecordBatch:
        top = max(float(min_df), max_df * n_chunks) if max_df < 1 else np.inf
        cut = []
        for own, row, pos, cnt, df, n in found:
            ok = (df >= min_df) & (df <= top)
            cut.append([x[ok] for x in (own, row, pos, cnt, df)] + [np.full(int(ok.sum()), n)])
        own, row, pos, cnt, df, n = (np.concatenate([c[i] for c in cut]) for i in range(6))
        er = er_of(block, own, cnt, df, n_chunks)
        o = np.lexsort((-er, own))
        own, row, pos, cnt, df, n, er = (x[o] for x in (own, row, pos, cnt, df, n, er))
        keep = np.ones(len(own), bool)
        start = np.searchsorted(own, own)  # first, so the best, of the same owner
        if tau is not None:
            keep &= er > tau - 1e-8
        if of_max is not None and len(own):
            keep &= er >= of_max * er[start] - 1e-6
        if cap is not None and len(own):
            end = np.searchsorted(own, own, side="right")
            keep &= er >= er[np.minimum(start + cap, end) - 1] - 1e-8
        own, row, pos, cnt, df, n = (x[keep] for x in (own, row, pos, cnt, df, n))
        o = np.argsort(n, kind="stable")
        own, row, pos, cnt, df, n = (x[o] for x in (own, row, pos, cnt, df, n))
        terms = [block.terms(int(k), row[n == k], pos[n == k]) for k in np.unique(n)]
        cols = [pa.array(block.keys).take(pa.array(own)), pa.array(block.own_size[own], pa.int32()), pa.array(n, pa.int32()), pa.concat_arrays(terms) if terms else pa.array([], pa.string()), pa.array(cnt, pa.int64()), pa.array(df, pa.int64()), pa.array(np.full(len(own), n_chunks, np.int64))]
        return pa.RecordBatch.from_arrays(cols, names=["chunk_key", "n_tok", "n", "term", "cnt", "df", "n_chunks"])

    return scored(chunks, max_n, "chunk_key string, n_tok int, n int, term string, cnt long, df long, n_chunks long", use)


def holding(chunks: DataFrame, terms: DataFrame, max_n: int) -> DataFrame:
    """chunk_key, terms: the number of distinct terms (n, term) of at most ``max_n`` words that occur anywhere in the chunks of a key, if there is one.
    Terms go to the parts that the n-grams of all chunks go to, as packed hashes like theirs, and a bit for each n-gram comes back."""

    def use(block: Block, n_chunks: int, found: list) -> pa.RecordBatch:
        no: dict[str, int] = {}
        key = np.array([no.setdefault(k, len(no)) for k in block.keys])
        total = np.zeros(len(no), np.int64)
        twice = np.bincount(key)[key] > 1
        for own, row, pos, _, df, n in found:
            has = df > 0
            total += np.bincount(key[own[has & ~twice[own]]], minlength=len(no))
            has &= twice[own]  # chunks of one key in several sizes share their terms
            if has.any():
                both = set(zip(key[own[has]].tolist(), block.terms(n, row[has], pos[has]).to_pylist()))
                total += np.bincount([k for k, _ in both], minlength=len(no))
        held = total > 0
        return pa.RecordBatch.from_arrays([pa.array(list(no), pa.string()).filter(pa.array(held)), pa.array(total[held])], names=["chunk_key", "terms"])

    each = written(terms.select("n", "term").distinct(), "terms")
    known = {n: blocks(each.where(F.col("n") == n).select(F.col("term").alias("chunk_key"), F.col("n").cast("int").alias("n_tok"), F.split("term", " ").alias("tokens"))) for n in range(1, max_n + 1)}
    out = scored(chunks, max_n, "chunk_key string, terms long", use, known)
    forget(each, *known.values())
    return out
