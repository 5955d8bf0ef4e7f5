"""Line deduplication by MinHash.

A line (between line feeds, outer white space off) is the set of its K-character shingles. One-permutation MinHash gives REGISTERS
minima from one hash of each shingle; empty registers borrow by a fixed random order. BANDS bands of three registers
find candidates: at Jaccard 0.8 a pair shares a band with probability 1 - (1 - 0.8**3)**10, over 0.999. Every two lines of a bucket
are held against each other by the exact Jaccard of whole lines, unless both are already in one component: the pairs of small buckets as rows, once each, those
of large buckets inside blocks (`blocks`). Links and equal
lines are joined by distributed union-find, and of each component only the occurrence least by (document id, text hash, line number) stays.

Bands, and places of lines, go to the tasks that compare them as packed arrays, dealt by hash into at least PARTS parts: a row for each part of
some BLOCK lines. Of each line a block sends only the first place; the others go. A part of more band values than a task may hold is
handed to Spark row by row. A pair whose bit tables of shingles show that too few can be shared is not worked out (an upper bound, so no link is lost).

Texts of candidate lines are fetched by a second scan that passes only lines whose hash is in a bit table of fixed
size; a full table costs time, not results. Lines are named by 64-bit hashes (chance of any clash: n * n / 2**65).

Defined cases: blank lines stay; null texts stay null; a line under K characters is one shingle; a document is an id and a text, so
unequal texts with one id, or without an id, are different documents, and rows that repeat both are one (a line is kept in each of them); a null id counts as
less than all others; an empty table gives an empty result; extra columns stay, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.llm import blocks
from evigraph.llm.common import documents, forget, free, saved
from evigraph.llm.components import components, joined_on
from evigraph.llm.hashing import U, char_shingles, code_points, code_values, mix, prefix, runs, spans

K, THRESHOLD = 8, 0.8
REGISTERS, BANDS, ROWS = 32, 10, 3
CHUNK, SEEN, TABLE = 1 << 16, 1 << 17, 1 << 19
PAIRED = 1 << 20  # characters of pairs that are held against each other at a time
PARTS, BLOCK, HELD = 1024, 1 << 15, 1 << 22  # parts of the buckets at least, lines packed together, band values that a task holds of a part
NO_ID = -(2**63)

#: What a packed row holds.
PLACE, REPEAT, ROOT = 1, 2, 3
PACKED = "part int, kind byte, x binary"


def line_hash(line: str) -> int:
    h = xxhash.xxh3_64_intdigest(line.encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def _shingles(values: np.ndarray, begin: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Number of the line and hash of each shingle, line by line, of lines that lie one after the other; a line under K characters is one shingle."""
    count = np.maximum(n - K + 1, 0)
    line = np.repeat(np.arange(len(n)), count)
    at = np.arange(len(line)) + np.repeat(begin - np.cumsum(count) + count, count)
    h = mix(runs(values, K)[at]) if len(at) else np.zeros(0, U)
    short = np.flatnonzero(count == 0)
    if len(short):
        whole = spans(prefix(values), begin[short], begin[short] + n[short])
        line, h = np.concatenate([line, short]), np.concatenate([h, whole])
        order = np.argsort(line, kind="stable")
        line, h = line[order], h[order]
    return line, h


def _chunks(lines: list[str]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of lines of about CHUNK characters: where they begin and end, and the shingles of each (`_shingles`)."""
    value = code_values()
    size = np.array([len(x) for x in lines])
    end = np.cumsum(size)
    lo = 0
    while lo < len(lines):
        hi = max(lo + 1, int(np.searchsorted(end, end[lo] - size[lo] + CHUNK, side="right")))
        n = size[lo:hi]
        yield lo, hi, *_shingles(value[code_points("".join(lines[lo:hi]))], np.cumsum(n) - n, n)
        lo = hi


def registers(lines: list[str]) -> np.ndarray:
    """Minima of each line; lines must not be empty."""
    out = np.full(len(lines) * REGISTERS, U(2**64 - 1))
    for lo, _, cell, h in _chunks(lines):
        cell *= REGISTERS
        cell += lo * REGISTERS
        cell += (h >> U(59)).astype(np.int64)
        h &= U(2**59 - 1)
        np.minimum.at(out, cell, h)
    out = out.reshape(-1, REGISTERS)
    empty = out == U(2**64 - 1)
    r, c = np.nonzero(empty)
    for turn in range(1, 200):
        if not len(r):
            break
        source = (mix(c.astype(U) + U(turn * 1000)) % U(REGISTERS)).astype(np.int64)
        full = ~empty[r, source]
        out[r[full], c[full]] = out[r[full], source[full]] + U(turn)
        r, c = r[~full], c[~full]
    if len(r):
        out[r, c] = out[r].min(axis=1)
    return out


def bands(lines: list[str]) -> np.ndarray:
    regs = registers(lines)
    out = np.zeros((len(lines), BANDS), U)
    for i in range(ROWS):
        out = mix(out + regs[:, i * BANDS : (i + 1) * BANDS] + U(i + 1))
    return mix(out + np.arange(BANDS, dtype=U) * U(0x9FB21C651E98DF25)).view(np.int64)


def distinct(x: np.ndarray) -> np.ndarray:
    """Distinct values in order; `np.unique` goes by a hash table, which takes several times as long."""
    x = np.sort(x)
    new = np.ones(len(x), bool)
    np.not_equal(x[1:], x[:-1], out=new[1:])
    return x[new]


def bag(line: str) -> blocks.Bag:
    """Distinct shingles of a line, all of one weight."""
    items = distinct(char_shingles(line, K))
    return items, np.ones(len(items), np.int64)


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two arrays of distinct values."""
    every = np.sort(np.concatenate([a, b]))
    both = np.count_nonzero(every[1:] == every[:-1])
    return both / max(1, len(a) + len(b) - both)


class Seen(set):
    """Hashes that this task has handled; emptied when full, which costs repeated rows only."""

    def new(self, h: int) -> bool:
        if h in self:
            return False
        if len(self) >= SEEN:
            self.clear()
        self.add(h)
        return True


def lines_of(text: str | None):
    """Number and text of each line that isn't blank."""
    if text:
        for i, x in enumerate(text.split("\n")):
            if x := x.strip():
                yield i, x


def _packed(parts: int, kind: int, *columns: np.ndarray) -> pa.RecordBatch:
    """part, kind, x: arrays of 64-bit numbers dealt by the first of them; a row for each part that has any."""
    part = (columns[0].view(U) % U(parts)).astype(np.int64)
    order = np.argsort(part, kind="stable")
    part, table = part[order], np.stack([c[order] for c in columns])
    cuts = np.flatnonzero(np.diff(part, prepend=-1)).tolist()
    rows = [table[:, x:y].tobytes() for x, y in zip(cuts, [*cuts[1:], len(part)])]
    return pa.RecordBatch.from_arrays([pa.array(part[cuts], pa.int32()), pa.array([kind] * len(rows), pa.int8()), pa.array(rows, pa.binary())], names=["part", "kind", "x"])


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, pa.Scalar]]:
    for batch in batches:
        yield from zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2))


def _array(x: pa.Scalar, columns: int) -> np.ndarray:
    return np.frombuffer(x.as_buffer(), np.int64).reshape(columns, -1)


def _parts(df: DataFrame) -> int:
    return max(PARTS, 4 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def _dealt(rows: DataFrame) -> DataFrame:
    return rows.repartition("part").sortWithinPartitions("part")


def _band_rows(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """Bands and hashes of the lines, packed."""
    seen, names, lines, size = Seen(), [], [], 0
    told: list[np.ndarray] = []

    def work():
        nonlocal lines, size
        told.append(bands(lines).ravel())
        lines, size = [], 0

    def flush():
        nonlocal names
        if lines:
            work()
        row = _packed(parts, 0, np.concatenate(told), np.repeat(np.array(names, np.int64), BANDS))
        told.clear()
        names = []
        return row

    for batch in batches:
        for text in batch.column(0):
            for _, x in lines_of(text.as_py()):
                if len(x) > K and seen.new(h := line_hash(x)):
                    names.append(h)
                    lines.append(x)
                    size += len(x)
            if size > 400_000:
                work()
            if len(names) >= BLOCK:
                yield flush()
    if names:
        yield flush()


def _shared(b: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """b, h and n: distinct members of buckets of at least two, with the number of the bucket's members."""
    order = np.argsort(b)
    b, h = b[order], h[order]
    same = np.zeros(len(b) + 1, bool)
    same[1:-1] = b[1:] == b[:-1]
    b, h = b[same[1:] | same[:-1]], h[same[1:] | same[:-1]]
    order = np.lexsort((h, b))
    b, h = b[order], h[order]
    new = np.ones(len(b), bool)
    new[1:] = (b[1:] != b[:-1]) | (h[1:] != h[:-1])
    b, h = b[new], h[new]
    _, which, n = np.unique(b, return_inverse=True, return_counts=True)
    n = n[which]
    return b[n > 1], h[n > 1], n[n > 1]


def _met(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.RecordBatch]:
    """b, node, n of a part's buckets. Members of a part of over most are told without n, and more than once, as they come."""
    held: list[np.ndarray] = []
    size, last, over = 0, None, False

    def told():
        b, h = np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held])
        if not over:
            b, h, n = _shared(b, h)
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array(b), pa.array(h), pa.nulls(len(b), pa.int64()) if over else pa.array(n.astype(np.int64))], names=["b", "node", "n"])

    for part, _, x in _unpacked(batches):
        if part != last:
            if held:
                yield told()
            size, last, over = 0, part, False
        held.append(_array(x, 2))
        size += held[-1].shape[1]
        if size > most:
            over, size = True, 0
            yield told()
    if held:
        yield told()


def _members(docs: DataFrame, held: int) -> DataFrame:
    """b, node, n: the buckets of at least two lines."""
    parts = _parts(docs)
    dealt = _dealt(docs.mapInArrow(lambda x: _band_rows(x, parts), PACKED))
    members = saved(dealt.mapInArrow(lambda x: _met(x, held), "b long, node long, n long"), "line_members")
    if members.where("n is null").isEmpty():
        return members
    rest = members.where("n is null").select("b", "node").distinct()
    counted = rest.groupBy("b").agg(F.count("*").alias("n")).where("n > 1")
    every = saved(members.where("n is not null").unionByName(rest.join(counted, "b")), "line_members")
    forget(members)
    return every


def _first(h: np.ndarray, *place: np.ndarray) -> tuple[np.ndarray, ...]:
    """Columns in order of h and place (id, th, no), and which rows are the first of their h and which are of another place than that."""
    order = np.lexsort((*place[::-1], h))
    h, place = h[order], tuple(c[order] for c in place)
    new = np.ones(len(h), bool)
    new[1:] = h[1:] != h[:-1]
    at = np.maximum.accumulate(np.where(new, np.arange(len(h)), 0))
    return h, *place, new, np.any([c != c[at] for c in place], axis=0)


def _places(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """Places of lines, packed: the first of each line in a block (kind PLACE), and those that another in the block comes before (kind REPEAT)."""
    held: list[tuple[np.ndarray, ...]] = []

    def flush():
        h, i, th, no, new, late = _first(*(np.concatenate(c) for c in zip(*held)))
        held.clear()
        yield _packed(parts, PLACE, h[new], i[new], th[new], no[new])
        if late.any():
            yield _packed(parts, REPEAT, i[late], th[late], no[late])

    size = 0
    for batch in batches:
        rows, nos, names = [], [], []
        for row, text in enumerate(batch.column(2)):
            for i, x in lines_of(text.as_py()):
                rows.append(row)
                nos.append(i)
                names.append(line_hash(x))
        at = np.array(rows, np.int64)
        held.append((np.array(names, np.int64), batch.column(0).to_numpy()[at], batch.column(1).to_numpy()[at], np.array(nos, np.int64)))
        size += len(rows)
        if size >= BLOCK:
            yield from flush()
            size = 0
    if size:
        yield from flush()


def _rooted(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            yield _packed(parts, ROOT, batch.column(0).to_numpy(), batch.column(1).to_numpy())


def _repeats(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """root, id, th, no: places of lines that stand elsewhere before (root is null), and the first place of each line that has a root."""

    def row(place: tuple[np.ndarray, ...], root: np.ndarray | None = None):
        g = pa.nulls(len(place[0]), pa.int64()) if root is None else pa.array(root)
        return pa.RecordBatch.from_arrays([g, pa.array(place[0]), pa.array(place[1]), pa.array(place[2].astype(np.int32))], names=["root", "id", "th", "no"])

    held: dict[int, list[np.ndarray]] = {PLACE: [], ROOT: []}

    def told():
        if held[PLACE]:
            h, *place, new, late = _first(*np.concatenate(held[PLACE], axis=1))
            yield row(tuple(c[late] for c in place))
            if held[ROOT]:
                node, root = np.concatenate(held[ROOT], axis=1)
                order = np.argsort(node)
                node, root = node[order], root[order]
                at = np.minimum(np.searchsorted(node, h), len(node) - 1)
                tied = new & (node[at] == h)
                yield row(tuple(c[tied] for c in place), root[at[tied]])
        for x in held.values():
            x.clear()

    last = None
    for part, kind, x in _unpacked(batches):
        if part != last:
            yield from told()
            last = part
        if kind == REPEAT:
            yield row(tuple(_array(x, 3)))
        else:
            held[kind].append(_array(x, 4 if kind == PLACE else 2))
    yield from told()


def _texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """h and line of wanted hashes: those that hit a bit table of TABLE 64-bit words (a fixed size), then an exact join."""
    bit = F.expr("shiftleft(1L, cast(h & 63 as int))")
    words = wanted.groupBy(F.shiftrightunsigned("h", 6).bitwiseAND(TABLE - 1).alias("w")).agg(F.bit_or(bit).alias("x")).toPandas()
    table = np.zeros(TABLE, np.int64)
    table[words["w"].to_numpy(np.int64)] = words["x"].to_numpy(np.int64)
    shared = docs.sparkSession.sparkContext.broadcast(table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, seen = shared.value, Seen()
        for batch in batches:
            every = [x for text in batch.column(0) for _, x in lines_of(text.as_py())]
            h = np.array([line_hash(x) for x in every], np.int64)
            u = h.view(U)
            hit = np.flatnonzero(bits.view(U)[(u >> U(6)) & U(TABLE - 1)] >> (u & U(63)) & U(1))
            hit = [i for i in hit.tolist() if seen.new(int(h[i]))]
            names, lines = h[hit], [every[i] for i in hit]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(lines, pa.string())], names=["h", "line"])

    found = docs.select("t").mapInArrow(run, "h long, line string")
    return found.join(wanted, "h", "left_semi").groupBy("h").agg(F.first("line").alias("line"))


class Lines:
    """Shingles of lines, repeats counted, and a bit table of each line."""

    def __init__(self, lines: list[str]):
        hashes, signs, sizes = [], [], []
        for lo, hi, line, h in _chunks(lines):
            signs.append(blocks.signs(hi - lo, line, h))
            sizes.append(np.bincount(line, minlength=hi - lo))
            hashes.append(h)
        self.hash, self.sign, self.size = np.concatenate(hashes), np.concatenate(signs), np.concatenate(sizes)
        self.end = np.cumsum(self.size)
        self.sets: dict[int, np.ndarray] = {}

    def set(self, i: int) -> np.ndarray:
        if i not in self.sets:
            self.sets[i] = distinct(self.hash[self.end[i] - self.size[i] : self.end[i]])
        return self.sets[i]

    def near(self, x: np.ndarray, y: np.ndarray) -> list[int]:
        """Which of the pairs x, y are at the threshold; only those that bit tables leave open are worked out."""
        most = blocks.at_most(self.sign[x], self.sign[y], self.size[x], self.size[y])
        return [i for i in np.flatnonzero(most >= THRESHOLD - blocks.BOUND).tolist() if jaccard(self.set(x[i]), self.set(y[i])) >= THRESHOLD]


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        size = np.cumsum(pc.add(pc.utf8_length(batch.column(2)), pc.utf8_length(batch.column(3))).to_numpy().astype(np.int64)) // PAIRED
        for run in np.split(np.arange(batch.num_rows), np.flatnonzero(np.diff(size)) + 1):
            if not len(run):
                continue
            part = batch.slice(run[0], len(run))
            a, b = (part.column(i).to_numpy() for i in (0, 1))
            _, first, which = np.unique(np.concatenate([a, b]), return_index=True, return_inverse=True)
            lines = pa.chunked_array([part.column(2), part.column(3)]).take(pa.array(first)).to_pylist()
            near = Lines(lines).near(which[: len(a)], which[len(a) :])
            yield pa.RecordBatch.from_arrays([pa.array(a[near]), pa.array(b[near])], names=["a", "b"])


def _roots(docs: DataFrame, most: int, chars: int, held: int) -> DataFrame:
    """h and root of every line that is like an unequal one; docs: t."""
    members = _members(docs, held)
    texts = saved(_texts_of(docs, members.select(F.col("node").alias("h")).distinct()).select(F.col("h").alias("node"), F.col("line").alias("t")), "line_texts")
    left, right = texts.select(F.col("node").alias("a"), F.col("t").alias("s")), texts.select(F.col("node").alias("b"), "t")
    links = blocks.pairs(members).join(left, "a").join(right, "b").select("a", "b", "s", "t").mapInArrow(_verify, "a long, b long")
    links = saved(links, "line_links")
    dealt = saved(blocks.parted(members, texts, most, chars), "line_parts", light=True)
    crowd = saved(blocks.within(dealt, texts, bag, THRESHOLD), "line_crowd")
    roots = saved(components(links.unionByName(crowd), "a", "b"), "line_roots", light=True)
    if not dealt.where("parts > 1").isEmpty():
        rest = saved(blocks.across(dealt, roots, texts, bag, THRESHOLD), "line_rest")
        roots = saved(joined_on(roots, rest), "line_roots", light=True)
    forget(members, texts, links, dealt, crowd)
    return roots.withColumnRenamed("node", "h")


def repeats(df: DataFrame, key: str, text: str, most: int = blocks.MEMBERS, chars: int = blocks.CHARS, held: int = HELD) -> DataFrame:
    """id, th (hash of the text) and the numbers of the lines that go."""
    docs = df.select(F.coalesce(F.col(key).cast("long"), F.lit(NO_ID)).alias("id"), F.xxhash64(F.col(text)).alias("th"), F.col(text).alias("t")).where(F.col("t").isNotNull())
    roots = _roots(docs.select("t"), most, chars, held)
    parts = _parts(df)
    dealt = _dealt(docs.mapInArrow(lambda x: _places(x, parts), PACKED).unionByName(roots.select("h", "root").mapInArrow(lambda x: _rooted(x, parts), PACKED)))
    told = saved(dealt.mapInArrow(_repeats, "root long, id long, th long, no int"), "line_repeats")
    tied = told.where("root is not null").withColumn("x", F.struct("id", "th", "no"))
    late = tied.join(tied.groupBy("root").agg(F.min("x").alias("first")), "root").where("x <> first")
    return told.where("root is null").unionByName(late.select(told.columns)).groupBy("id", "th").agg(F.collect_set("no").alias("gone"))


def dedup_lines(df: DataFrame, key: str = "doc_id", text: str = "text", **sizes: int) -> DataFrame:
    """Replaces the text by its lines that stay; adds n_lines and n_removed (of lines that aren't blank)."""

    @F.pandas_udf("text string, n_lines int, n_removed int")
    def rebuilt(texts: pd.Series, gone: pd.Series) -> pd.DataFrame:
        rows = []
        for t, s in zip(texts, gone, strict=True):
            if t is None:
                rows.append((None, 0, 0))
                continue
            lines = t.split("\n")
            full = sum(1 for x in lines if x.strip())
            if s is None:
                rows.append((t, full, 0))
                continue
            out = set(s.tolist())
            rows.append(("\n".join([x for i, x in enumerate(lines) if i not in out]), full, len(out)))
        return pd.DataFrame(rows, columns=["text", "n_lines", "n_removed"])

    a, b, c = free(df, "_id"), free(df, "_th"), free(df, "_gone")
    gone = repeats(df, key, text, **sizes).toDF(a, b, c)
    own = [x for x in df.columns if x not in ("n_lines", "n_removed")]
    keyed = df.withColumns({a: F.coalesce(F.col(key).cast("long"), F.lit(NO_ID)), b: F.xxhash64(F.col(text))})
    made = free(keyed, "_made")
    done = keyed.join(gone, [a, b], "left").withColumn(made, rebuilt(F.col(text), F.col(c)))
    return done.select(*[F.col(f"{made}.text").alias(x) if x == text else F.col(f"`{x}`") for x in own], f"{made}.n_lines", f"{made}.n_removed")


def op9_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the lines that stay."""
    return dedup_lines(documents(spark, sf_dir).select("doc_id", "text"))


QUERIES = {"op9_fuzzy_lines": op9_fuzzy_lines}
