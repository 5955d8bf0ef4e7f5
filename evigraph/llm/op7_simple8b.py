"""Token ids in Simple-8b files.

A 64-bit word has a 4-bit selector on top and 60 bits of values, the first value lowest. Selectors
2 to 15 pack from 60 one-bit to one 60-bit value; selector 1 is unused;
selector 0 is an escape: the next word is one raw 64-bit value.

A file row is a block of whole documents in ascending id order: their ids and lengths, the number of token ids before
the block in its part, the packed words. Parts are ranges of ids, so one small sum over parts gives every start.

Defined cases: null or empty text has only the end id; the string of a special token is that token, as in the library's plain call; equal doc_ids keep
both rows, in the order of the table's files; null doc_ids come first;
an empty table gives no block; a document longer than a block is a block of its own.
"""

from __future__ import annotations

import functools
import os
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.llm.common import documents, saved
from evigraph.llm.splitting import shared

#: Selector, values in a word, bits of a value.
LAYOUT = [(2, 60, 1), (3, 30, 2), (4, 20, 3), (5, 15, 4), (6, 12, 5), (7, 10, 6), (8, 8, 7), (9, 7, 8), (10, 6, 10), (11, 5, 12), (12, 4, 15), (13, 3, 20), (14, 2, 30), (15, 1, 60)]
END, BLOCK_IDS, CACHE = 0, 1 << 16, 600_000
U = np.uint64


def _bits(v: np.ndarray) -> np.ndarray:
    """Bits of each value, 1 at least; from 2**53 on perhaps one more."""
    return np.maximum(np.frexp(v.astype(float))[1], 1).astype(np.uint8)


def pack(values: np.ndarray) -> np.ndarray:
    """Greedy packing: at each position the selector that takes most values."""
    v = np.asarray(values, U)
    n = len(v)
    if n == 0:
        return np.zeros(0, U)
    bits = _bits(v)
    choice = np.full(n, 255, np.uint8)
    most, count = bits, 1  # most bits of the next count values
    for k in range(len(LAYOUT) - 1, -1, -1):
        _, take, width = LAYOUT[k]
        while count < take and len(most) > 1:
            most = np.maximum(most[:-1], bits[count:])
            count += 1
        if count < take:
            break
        choice[: len(most)][most <= width] = k
    step = np.array([c for _, c, _ in LAYOUT] + [1], np.uint8)[np.minimum(choice, len(LAYOUT))].tobytes()
    heads, p = [], 0
    while p < n:
        heads.append(p)
        p += step[p]
    head = np.array(heads)
    kind = choice[head]
    size = np.where(kind == 255, 2, 1)
    place = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), U)
    for k, (selector, count, width) in enumerate(LAYOUT):
        own = kind == k
        if own.any():
            h, word = head[own], np.full(int(own.sum()), selector << 60, U)
            for i in range(count):
                word |= v[h + i] << U(i * width)
            out[place[own]] = word
    raw = kind == 255
    out[place[raw] + 1] = v[head[raw]]
    return out


def unpack(words: np.ndarray) -> np.ndarray:
    """All values of a block; each selector's words are decoded together."""
    w = np.asarray(words, U)
    if len(w) == 0:
        return w
    selector = (w >> U(60)).astype(np.int64)
    live = np.ones(len(w), bool)
    if (selector == 0).any():
        p = 0
        marks = np.flatnonzero(selector == 0).tolist()
        for m in marks:  # an escape hides the word after it
            if m >= p:
                live[m + 1] = False
                p = m + 2
    count = np.zeros(16, np.int64)
    count[0] = 1
    for s, c, _ in LAYOUT:
        count[s] = c
    each = np.where(live, count[selector], 0)
    place = np.cumsum(each) - each
    out = np.zeros(int(each.sum()), U)
    for s, c, width in LAYOUT:
        own = live & (selector == s)
        if own.any():
            at, word, mask = place[own], w[own], U((1 << width) - 1)
            for i in range(c):
                out[at + i] = word >> U(i * width) & mask
    raw = np.flatnonzero(live & (selector == 0))
    out[place[raw]] = w[raw + 1]
    return out


class Known(dict):
    """Ids of a word as little-endian uint32 bytes, by the library's model when first met; beyond CACHE words nothing more is kept."""

    def __init__(self, model):
        self.tokenize = model.tokenize
        # Byte-level vocabularies write a byte as a printable character: itself where it is one, else the next from 256 on.
        plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
        others = iter(range(256, 512))
        self.letters = {b: chr(b if b in plain else next(others)) for b in range(256)}

    def __missing__(self, word: str) -> bytes:
        written = word.encode("utf-8", "surrogatepass").decode("latin-1").translate(self.letters)
        ids = array("I", [t.id for t in self.tokenize(written)]).tobytes()
        if len(self) < CACHE:
            self[word] = ids
        return ids


class WordCache:
    """Ids of a text as little-endian uint32 bytes.

    Byte-level BPE treats each match of the pre-tokeniser's pattern alone, so a text's ids are those of its
    matches. The standard library's patterns split as
    the tokeniser does but for a few numerals, control characters and what lies beyond 16 bits; a text with one of those, or with the string of
    a special token, is encoded whole by the library.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.known = Known(self.tokenizer.model)
        self.splitter = shared()

    def encode(self, text: str) -> bytes:
        if self.splitter.odd(text) or any(t in text for t in self.special):
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        return b"".join(map(self.known.__getitem__, self.splitter.plain(text)))


@functools.cache
def _cache(path: str) -> WordCache:
    return WordCache(path)


FILE = "part int, block int, before long, doc_ids array<long>, lengths array<int>, n_ids long, words binary"


def write_files(df: DataFrame, path: str, key: str = "doc_id", text: str = "text", name: str = "token_files") -> DataFrame:
    """Encode texts and write their ids in id order; returns the stored files as a table."""
    schema = pa.schema([("part", pa.int32()), ("block", pa.int32()), ("before", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int32())), ("n_ids", pa.int64()), ("words", pa.binary())])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, part = _cache(path), TaskContext.get().partitionId()
        before = block = held = 0
        ids, lengths, chunks = [], [], []

        def flush():
            nonlocal before, block, held, ids, lengths, chunks
            v = np.frombuffer(b"".join(chunks), "<u4").astype(U)
            row = pa.RecordBatch.from_pylist([{"part": part, "block": block, "before": before, "doc_ids": ids, "lengths": lengths, "n_ids": len(v), "words": pack(v).astype("<u8").tobytes()}], schema=schema)
            before, block, held, ids, lengths, chunks = before + len(v), block + 1, 0, [], [], []
            return row

        end = np.array([END], "<u4").tobytes()
        for batch in batches:
            keys, texts = batch.column(0), batch.column(1)
            for i in range(batch.num_rows):
                raw = cache.encode(texts[i].as_py() or "") + end
                ids.append(keys[i].as_py())
                lengths.append(len(raw) // 4)
                chunks.append(raw)
                held += len(raw) // 4
                if held >= BLOCK_IDS:
                    yield flush()
        if ids:
            yield flush()

    # The row's number deals rows of one id, or of none, to several tasks.
    rows = df.select(F.col(key).cast("long").alias("k"), F.monotonically_increasing_id().alias("n"), F.col(text).alias("t"))
    ordered = rows.repartitionByRange("k", "n").sortWithinPartitions("k", "n").select("k", "t")
    return saved(ordered.mapInArrow(encode, FILE), name)


def read_files(files: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 and the ids' checksum, decoded from stored blocks."""
    parts = files.groupBy("part").agg(F.sum("n_ids").alias("n"))
    # One row for each part of the file set, so the window and the broadcast are as small as the list of files.
    base = parts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids = unpack(np.frombuffer(row["words"], "<u8")).astype("<u4")
                ends = np.cumsum(row["lengths"])
                starts = ends - np.array(row["lengths"])
                view, first = memoryview(ids.tobytes()), row["base"] + row["before"]
                crc = [zlib.crc32(view[4 * a : 4 * z]) for a, z in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(starts + first), pa.array(row["lengths"], pa.int64()), pa.array(crc, pa.int64())], schema=schema)

    return files.join(F.broadcast(base), "part").select("base", "before", "doc_ids", "lengths", "words").mapInArrow(decode, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op7_simple8b(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text's ids, written to Simple-8b files in id order and read back."""
    import public_tokenizers

    return read_files(write_files(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json")))


QUERIES = {"op7_simple8b": op7_simple8b}
