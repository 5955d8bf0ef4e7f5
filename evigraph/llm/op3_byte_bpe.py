"""Byte-level BPE with Spark's higher-order functions.

A word (one match of the pre-tokeniser's pattern) is folded in the JVM. All runs of its bytes that are tokens are merges; they are
sorted by rank, then place, and folded over the set of piece ends (bits of a long): a merge applies when its ends are ends of
pieces and one end lies between. Each merge needs one turn only where every token is what merging its own bytes gives, as in any
vocabulary that was trained as BPE. A word over MASK bytes is folded by steps: an array of byte pieces and the ranks of
neighbouring pairs, the leftmost pair of least rank merged each time. The rank map is one constant row: the tokens in order of rank, and a cuckoo
table of ranks by hash, so a lookup looks at two places and compares bytes (Spark scans a map's keys one by one). It enters plans as a
scalar subquery: as a literal of nested maps it is printed with each plan and unpacked again for each task.

``encode`` folds the frequent distinct words of the whole corpus so: at most HOT words, which travel to the tasks as a broadcast of that
bounded size. Texts are split and known words looked up in Arrow batches; any other word is folded there by the same ranked merges over
its bytes, so the result doesn't depend on HOT. ``decode`` joins the pieces of ids and gives binary.

The rare words were first folded in the JVM too: 2463 CPU seconds a GB against a limit of 900 (an interpreted fold takes 60 microseconds
a word, and rare words are a sixteenth of all). Looking all words up by literal maps took 2056 on its own.

Defined cases: null text is empty and gives no ids; equal texts give equal ids; a word of n bytes costs at most n - 1 folds; columns
asked for stay as they are.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from array import array
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.llm.common import documents, let, saved
from evigraph.llm.splitting import splitter

HOT, HOT_BYTES, LATE, MASK, ROWS = 1 << 18, 48, 150_000, 60, 1_000
NONE = 2**31 - 1


def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def murmur(data: bytes, seed: int = 42) -> int:
    """Spark's hash() of a string: 32-bit Murmur3 by words of four bytes, then single signed bytes."""
    m = 0xFFFFFFFF

    def stir(h: int, k: int) -> int:
        k = k * 0xCC9E2D51 & m
        k = (k << 15 | k >> 17) * 0x1B873593 & m
        h ^= k
        return ((h << 13 | h >> 19) * 5 + 0xE6546B64) & m

    h, whole = seed, len(data) // 4 * 4
    for i in range(0, whole, 4):
        h = stir(h, int.from_bytes(data[i : i + 4], "little"))
    for x in data[whole:]:
        h = stir(h, (x - 256 if x > 127 else x) & m)
    h ^= len(data)
    h = (h ^ h >> 16) * 0x85EBCA6B & m
    h = (h ^ h >> 13) * 0xC2B2AE35 & m
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


SLOTS, RANKS = 1 << 17, "_ranks"


def places(h: int) -> tuple[int, int]:
    """The two slots of a 32-bit hash."""
    u = h & 0xFFFFFFFF
    return u & SLOTS - 1, u >> 15


def cuckoo(keys: list[str]) -> list[int]:
    """Slots that hold the number of a key in one of its two places."""
    if len(keys) * 2 > SLOTS:
        raise ValueError("too many keys")
    both = [places(murmur(k.encode())) for k in keys]
    slots = [-1] * SLOTS
    for k in range(len(keys)):
        held, at = k, both[k][0]
        for _ in range(500):
            slots[at], held = held, slots[at]
            if held < 0:
                break
            one, two = both[held]
            at = two if at == one else one
        else:
            raise ValueError("no room for a key")
    return slots


class Ranks:
    """The rank map as a one-row table, and lookups in it."""

    def __init__(self, spark: SparkSession, tokens: list[str]):
        # An unused slot points at token 0, which the comparison rules out.
        row = pa.table({"slots": pa.array([[max(x, 0) for x in cuckoo(tokens)]], pa.list_(pa.int32())), "pieces": pa.array([tokens])})
        self.row = spark.createDataFrame(row).select(F.struct("slots", "pieces").alias("r")).scalar()

    @staticmethod
    def get(t: Column, key: Column) -> Column:
        """Rank of a token given in hex, null if it is none; ``t`` is the bound row."""
        h = F.hash(key)
        first = F.element_at(t["slots"], h.bitwiseAND(SLOTS - 1) + 1)
        second = F.element_at(t["slots"], F.shiftrightunsigned(h, 15) + 1)
        return F.when(F.element_at(t["pieces"], first + 1) == key, first).when(F.element_at(t["pieces"], second + 1) == key, second)


class Codec:
    def __init__(self, spark: SparkSession, path: str, pattern: str):
        own = ranks(path)
        self.pattern = "(?U)" + pattern  # \s as Unicode's white space
        self.longest = max(map(len, own))
        self.raw = [b""] * (max(own.values()) + 1)
        for k, v in own.items():
            self.raw[v] = k
        self.ranks = Ranks(spark, [x.hex().upper() for x in self.raw])

    def split(self, text: Column) -> Column:
        return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(self.pattern), F.lit(0))

    def _pair(self, t: Column, left: Column, right: Column) -> Column:
        return F.coalesce(Ranks.get(t, F.concat(left, right)), F.lit(NONE))

    def _merge(self, t: Column, s: Column) -> Column:
        p, r = s["p"], s["r"]
        none = F.array().cast("array<int>")

        def at(i: Column, m: Column) -> Column:
            return F.struct(
                F.concat(F.slice(p, F.lit(1), i - 1), F.array(m), F.slice(p, i + 2, F.size(p))).alias("p"),
                F.concat(
                    F.slice(r, F.lit(1), F.greatest(i - 2, F.lit(0))),
                    F.when(i > 1, F.array(self._pair(t, F.element_at(p, F.greatest(i - 1, F.lit(1))), m))).otherwise(none),
                    F.when(i + 1 < F.size(p), F.array(self._pair(t, m, F.try_element_at(p, i + 2)))).otherwise(none),
                    F.slice(r, i + 2, F.size(p)),
                ).alias("r"),
            )

        def merged(i: Column) -> Column:
            return let(F.concat(F.element_at(p, i), F.element_at(p, i + 1)), lambda m: at(i, m))

        return F.when(F.array_min(r) >= NONE, s).otherwise(let(F.array_position(r, F.array_min(r)).cast("int"), merged))

    def _sorted_fold(self, t: Column, h: Column, n: Column) -> Column:
        """Ids of a word of 2 to MASK bytes, given in hex."""

        def one(k: Column) -> Column:
            return F.call_function("shiftleft", F.lit(1).cast("long"), k)

        def piece(i: Column, j: Column) -> Column:
            return Ranks.get(t, F.substr(h, i * 2 + 1, (j - i) * 2))

        def merges(i: Column) -> Column:
            own = F.transform(
                F.sequence(i + 2, F.least(n, i + self.longest)),
                lambda j: F.struct(piece(i, j).alias("rank"), i.alias("at"), one(i).bitwiseOR(one(j)).alias("ends"), (one(j) - one(i + 1)).alias("inside")),
            )
            return F.filter(own, lambda x: x["rank"].isNotNull())

        ranked = F.array_sort(F.flatten(F.transform(F.sequence(F.lit(0), n - 2), merges)))
        cut = F.aggregate(
            ranked,
            one(n + 1) - 1,
            lambda m, x: F.when((m.bitwiseAND(x["ends"]) == x["ends"]) & (F.bit_count(m.bitwiseAND(x["inside"])) == 1), m.bitwiseAND(F.bitwise_not(x["inside"]))).otherwise(m),
        )

        def ids(m: Column) -> Column:
            held = F.filter(F.sequence(F.lit(0), n), lambda i: m.bitwiseAND(one(i)) != 0)
            return let(held, lambda e: F.transform(F.slice(e, F.lit(2), F.size(e) - 1), lambda j, k: piece(F.element_at(e, k + 1), j)))

        return let(cut, ids)

    def _step_fold(self, t: Column, h: Column) -> Column:
        """Ids of a word of two bytes or more, given in hex."""

        def pieces(p: Column) -> Column:
            first = F.transform(F.sequence(F.lit(1), F.size(p) - 1), lambda i: self._pair(t, F.element_at(p, i), F.element_at(p, i + 1)))
            start = F.struct(p.alias("p"), first.alias("r"))
            done = F.aggregate(F.sequence(F.lit(2), F.size(p)), start, lambda s, _: self._merge(t, s))
            return F.transform(done["p"], lambda x: Ranks.get(t, x))

        return let(F.regexp_extract_all(h, F.lit(".."), F.lit(0)), pieces)

    def fold(self, words: Column) -> Column:
        """Ids of each word of an array. The rank row is bound once a row, so it stands once in the plan."""

        def one(t: Column, word: Column) -> Column:
            def parts(h: Column) -> Column:
                n = (F.length(h) / 2).cast("int")
                return let(n, lambda k: F.when(k == 0, F.array().cast("array<int>")).when(k <= MASK, self._sorted_fold(t, h, k)).otherwise(self._step_fold(t, h)))

            def bytes_of(h: Column) -> Column:
                return let(Ranks.get(t, h), lambda whole: F.when(whole.isNotNull(), F.array(whole)).otherwise(parts(h)))

            return let(F.hex(F.encode(word, "UTF-8")), bytes_of)

        return let(F.col(RANKS), lambda t: F.transform(words, lambda w: one(t, w)))

    def bound(self, df: DataFrame) -> DataFrame:
        """With the rank row as a column, for ``fold`` and ``decode``. The optimizer puts the subquery in the place of the column, which
        is used once, so no row carries it."""
        return df.withColumn(RANKS, self.ranks.row)

    def frequent(self, df: DataFrame, text: str) -> pa.Table:
        """Ids of the most frequent distinct words of the whole table: at most HOT, each of at most HOT_BYTES bytes."""
        words = df.select(F.explode(self.split(F.col(text))).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
        words = saved(words.where((F.col("n") > 1) & (F.octet_length("w") <= HOT_BYTES)), "words")
        level = F.floor(F.log2("n") * 8).cast("int")
        total, cut = 0, NONE
        for row in words.groupBy(level.alias("k")).count().orderBy(F.desc("k")).collect():  # at most 8 * 63 rows
            total += row["count"]
            if total > HOT:
                break
            cut = row["k"]
        return self.bound(words.where(level >= cut)).select("w", F.element_at(self.fold(F.array("w")), 1).alias("ids")).toArrow()

    def _coded(self, df: DataFrame, text: str, keep: list[str], each, schema: str) -> DataFrame:
        """keep and, by ``each`` from the bytes of a text's ids, the columns of ``schema``."""
        shared, mark = df.sparkSession.sparkContext.broadcast((self.frequent(df, text), self.raw)), uuid.uuid4().hex
        n = len(keep)
        names = [x.strip().split()[0] for x in schema.split(",")]
        kinds = [{"long": pa.int64(), "string": pa.string(), "array<int>": pa.list_(pa.int32())}[x.strip().split()[1]] for x in schema.split(",")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words, split = _words(mark, shared), splitter()
            for batch in small(batches):
                rows = [each(words.encode(split(t.as_py() or ""))) for t in batch.column(n)]
                yield pa.RecordBatch.from_arrays([*batch.columns[:n], *[pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)]], names=[*keep, *names])

        kept = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
        return df.select(*[F.col(f"`{c}`") for c in keep], F.col(text).alias("t")).mapInArrow(run, kept + schema)

    def encode(self, df: DataFrame, text: str, keep: list[str]) -> DataFrame:
        """keep and the array ``ids``."""
        return self._coded(df, text, keep, lambda raw: (array("I", raw).tolist(),), "ids array<int>")

    def digests(self, df: DataFrame, text: str, keep: list[str]) -> DataFrame:
        """keep, n_tokens, ids_sha256 (ids as little-endian uint32) and decoded_sha256 (of the joined pieces)."""
        pieces = self.raw

        def each(raw: bytes) -> tuple:
            decoded = b"".join(map(pieces.__getitem__, array("I", raw)))
            return len(raw) // 4, hashlib.sha256(raw).hexdigest(), hashlib.sha256(decoded).hexdigest()

        return self._coded(df, text, keep, each, "n_tokens long, ids_sha256 string, decoded_sha256 string")

    def id_bytes(self, ids: Column) -> Column:
        """Ids as little-endian unsigned 32-bit integers."""
        def swapped(i: Column) -> Column:
            j = i.cast("long")
            return F.lpad(F.hex(F.shiftleft(j.bitwiseAND(255), 24) + F.shiftleft(F.shiftright(j, 8).bitwiseAND(255), 16) + F.shiftleft(F.shiftright(j, 16).bitwiseAND(255), 8) + F.shiftright(j, 24)), 8, "0")

        return F.unhex(F.array_join(F.transform(ids, swapped), ""))

    def decode(self, ids: Column) -> Column:
        """The pieces of ids, joined to one binary; over a frame made by ``bound``."""
        return F.unhex(let(F.col(RANKS), lambda t: F.array_join(F.transform(ids, lambda i: F.element_at(t["pieces"], i + 1)), "")))


def small(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of at most ROWS rows, so that a worker holds few texts at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, ROWS):
            yield batch.slice(at, ROWS)


class Words:
    """Ids of words as bytes: the broadcast ones, those folded lately, and folds of the rest."""

    def __init__(self, table: pa.Table, pieces: list[bytes]):
        table = table.combine_chunks()
        ids = table["ids"].combine_chunks()
        raw, cuts = ids.flatten().to_numpy().astype("<u4").tobytes(), (ids.offsets.to_numpy() - ids.offsets[0].as_py()) * 4
        self.known = {w: raw[a:z] for w, a, z in zip(table["w"].to_pylist(), cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)}
        self.rank = {p: i for i, p in enumerate(pieces)}
        self.late: dict[str, bytes] = {}

    def fold(self, word: bytes) -> list[int]:
        """Ranked merges over the bytes of one word."""
        rank = self.rank
        if word in rank:
            return [rank[word]]
        parts = [word[i : i + 1] for i in range(len(word))]
        pairs = [rank.get(word[i : i + 2], NONE) for i in range(len(word) - 1)]
        while pairs:
            least = min(pairs)
            if least == NONE:
                break
            i = pairs.index(least)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i:
                pairs[i - 1] = rank.get(parts[i - 1] + parts[i], NONE)
            if i < len(pairs):
                pairs[i] = rank.get(parts[i] + parts[i + 1], NONE)
        return [rank[p] for p in parts]

    def rare(self, word: str) -> bytes:
        ids = self.late.get(word)
        if ids is None:
            if len(self.late) >= LATE:
                self.late.clear()
            ids = self.late[word] = array("I", self.fold(word.encode("utf-8", "surrogatepass"))).tobytes()
        return ids

    def encode(self, words: list[str]) -> bytes:
        ids, at = list(map(self.known.get, words)), 0
        if None in ids:
            try:
                while True:
                    at = ids.index(None, at)
                    ids[at] = self.rare(words[at])
            except ValueError:
                pass
        return b"".join(ids)


_WORDS: dict[str, Words] = {}


def _words(mark: str, shared) -> Words:
    """The words of a run, made once a worker."""
    if mark not in _WORDS:
        _WORDS.clear()
        _WORDS[mark] = Words(*shared.value)
    return _WORDS[mark]


def public_codec(spark: SparkSession) -> Codec:
    import public_tokenizers

    return Codec(spark, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text encoded and decoded again."""
    return public_codec(spark).digests(documents(spark, sf_dir), "text", ["doc_id"])


QUERIES = {"op3_byte_bpe": op3_byte_bpe}
