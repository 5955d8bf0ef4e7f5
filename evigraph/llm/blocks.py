"""Exact links inside buckets, block by block.

Buckets of up to SMALL members give their pairs as rows (at most (SMALL - 1) / 2 for a member). A larger bucket is dealt by hash into
parts of about MEMBERS members and CHARS characters; a part is one task's group, and only links that join something leave it, so no
group is ever emitted as pairs. In a part each member in turn is held against all that are still in another class, by counts over
the part's own item numbers, which is exact and costs about a microsecond a pair; a group of copies falls together after its first member. A bucket
of one part is done then. Each part of a larger bucket also holds the bucket's hub, and what is still of different classes after that meets
part against part.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SMALL, MEMBERS, CHARS = 16, 2048, 1 << 22
BOUND = 1e-9  # slack for rounding where bounds decide
SIGNS, FEW = 2048, 128  # bits of a set's table (a power of two), sets whose tables are compared at once
Bag = tuple[np.ndarray, np.ndarray]


def similarity(x: Bag, y: Bag) -> float:
    """Exact probability Jaccard: over shared items d, the sum of 1 / sum of max(x'/x_d, y'/y_d) over all items; plain Jaccard where all weights are equal."""
    (a, wa), (b, wb) = x, y
    if not len(a) or not len(b):
        return 0.0
    every = np.union1d(a, b)
    p, q = np.zeros(len(every)), np.zeros(len(every))
    p[np.searchsorted(every, a)], q[np.searchsorted(every, b)] = wa, wb
    with np.errstate(divide="ignore"):
        ratio = np.where(q > 0, p / q, np.inf)
    order = np.argsort(ratio, kind="stable")
    ratio, p, q = ratio[order], p[order], q[order]
    below, above = np.cumsum(q), p.sum() - np.cumsum(p)
    last = np.searchsorted(ratio, ratio, side="right") - 1
    both = (p > 0) & (q > 0)
    total = above[last] + np.where(both, ratio, 0) * below[last]
    return float((p[both] / total[both]).sum())


def signs(sets: int, owner: np.ndarray, item: np.ndarray) -> np.ndarray:
    """A bit table of each set, by the numbers or hashes of its items."""
    table = np.zeros((sets, SIGNS), bool)
    table[owner, (item & item.dtype.type(SIGNS - 1)).astype(np.int64)] = True
    return np.packbits(table, axis=1).view(np.uint64)


def at_most(x: np.ndarray, y: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """What the plain Jaccard of sets with bit tables x and y, of at most n and m items, can be at most.

    Each bit of x that y lacks is an item of x that y lacks. So at most n - bits are shared, and at least n and the bits that x lacks are in
    either, which is least favourable where n is as large as it can be; and the same from y's side.
    """
    both = np.bitwise_count(x & y).sum(axis=-1, dtype=np.int64)
    own, other = (np.bitwise_count(z).sum(axis=-1, dtype=np.int64) - both for z in (x, y))
    return np.minimum((n - own) / (n + other), (m - other) / (m + own))


class Block:
    """Weighted sets whose items are numbered together, so that one is held against many by array operations."""

    def __init__(self, bags: list[Bag]):
        self.plain = np.array([w.min() == w.max() for _, w in bags])
        self.bags = [(e, np.ones(len(w), np.int64)) if p else (e, w) for (e, w), p in zip(bags, self.plain)]  # a set's scale doesn't count
        self.size = np.array([len(e) for e, _ in bags])
        self.end = np.cumsum(self.size)
        self.item = np.unique(np.concatenate([e for e, _ in bags]), return_inverse=True)[1].astype(np.int32)
        self.weight = np.concatenate([w for _, w in self.bags]).astype(float)
        self.share = np.concatenate([w / w.sum() for _, w in self.bags])
        self.mark = np.zeros(int(self.item.max()) + 1, np.int32)
        self.mass = np.zeros(len(self.mark))
        self.sign = signs(len(bags), np.repeat(np.arange(len(bags)), self.size), self.item)
        self.most: np.ndarray | None = None

    def against(self, x: int, y: np.ndarray) -> np.ndarray:
        """Similarity of set x with each of the sets y."""
        out, plain = np.zeros(len(y)), self.plain[y] & self.plain[x]
        if plain.any():
            out[plain] = self._shared(x, y[plain])
        if not plain.all():
            out[~plain] = self._weighted(x, y[~plain])
        return out

    def near(self, x: int, y: np.ndarray, threshold: float) -> np.ndarray:
        """Whether the similarity of set x with each of the sets y is at the threshold.

        With p and q the shares of items, the similarity lies between sum(min(p, q)) / sum(max(p, q)) and sum(min(p, q)), as
        max(p_e / p_d, q_e / q_d) is at least each of the two and at most max(p_e, q_e) / min(p_d, q_d). Only weighted sets that
        the bounds leave open are worked out.
        """
        out, plain = np.zeros(len(y), bool), self.plain[y] & self.plain[x]
        own = np.flatnonzero(plain)
        own = own[self._open(x, y[own], threshold)]
        if len(own):
            out[own] = self._shared(x, y[own]) >= threshold
        rest = np.flatnonzero(~plain)
        if len(rest):
            low = self._least(x, y[rest])
            sure = low / (2 - low) >= threshold + BOUND
            out[rest[sure]] = True
            rest = rest[~sure & (low >= threshold - BOUND)]
        if len(rest):
            out[rest] = self._weighted(x, y[rest]) >= threshold
        return out

    def _open(self, x: int, y: np.ndarray, threshold: float) -> np.ndarray:
        """Whether bit tables leave open that plain set x is at the threshold with each of y."""
        if len(self.size) > FEW:
            return at_most(self.sign[x], self.sign[y], self.size[x], self.size[y]) >= threshold - BOUND
        if self.most is None:
            self.most = at_most(self.sign[:, None], self.sign, self.size[:, None], self.size)
        return self.most[x, y] >= threshold - BOUND

    def _least(self, x: int, y: np.ndarray) -> np.ndarray:
        """Sum of the lesser shares of x and each of y."""
        own = slice(self.end[x] - self.size[x], self.end[x])
        self.mass[self.item[own]] = self.share[own]
        pick, at = self._items(y)
        both = np.add.reduceat(np.minimum(self.mass[self.item[pick]], self.share[pick]), at)
        self.mass[self.item[own]] = 0
        return both

    def _items(self, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the items of sets y lie, and where each set begins among them."""
        size = self.size[y]
        at = np.cumsum(size) - size
        return np.arange(int(size.sum())) + np.repeat(self.end[y] - size - at, size), at

    def _shared(self, x: int, y: np.ndarray) -> np.ndarray:
        own = self.item[self.end[x] - self.size[x] : self.end[x]]
        self.mark[own] = 1
        begin, lo, hi = self.end - self.size, int(y.min()), int(y.max())
        if 2 * int(self.size[y].sum()) > self.end[hi] - begin[lo]:  # nearly all of a run: no need to pick
            both = np.add.reduceat(self.mark[self.item[begin[lo] : self.end[hi]]], begin[lo : hi + 1] - begin[lo])[y - lo]
        else:
            pick, at = self._items(y)
            both = np.add.reduceat(self.mark[self.item[pick]], at)
        self.mark[own] = 0
        return both / (self.size[x] + self.size[y] - both)

    def _weighted(self, x: int, y: np.ndarray) -> np.ndarray:
        """The sum of `similarity` for all of y at once: items of each set in the order of x's weight over its own."""
        own = slice(self.end[x] - self.size[x], self.end[x])
        pick, at = self._items(y)
        self.mass[self.item[own]] = self.weight[own]
        p, q = self.mass[self.item[pick]], self.weight[pick]
        self.mass[self.item[own]] = 0
        ratio, size = p / q, self.size[y]
        order = np.lexsort((ratio, np.repeat(np.arange(len(y)), size)))
        p, q, ratio = p[order], q[order], ratio[order]
        p_to, q_to = np.cumsum(p), np.cumsum(q)
        above = self.weight[own].sum() - p_to + np.repeat(p_to[at] - p[at], size)
        below = q_to - np.repeat(q_to[at] - q[at], size)
        return np.add.reduceat(np.divide(p, above + ratio * below, out=np.zeros(len(p)), where=p > 0), at)


def tied(bags: list[Bag], label: np.ndarray, threshold: float, part: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Pairs that join sets of different labels until no pair at the threshold is left apart; with ``part``, of pairs between different parts."""
    label, out, block = label.copy(), [], None
    for x in range(len(bags) - 1):
        far = label[x + 1 :] != label[x]
        if part is not None:
            far &= part[x + 1 :] != part[x]
        y = np.flatnonzero(far) + x + 1
        if not len(y):
            continue
        block = block or Block(bags)
        for k in y[block.near(x, y, threshold)].tolist():
            if label[k] != label[x]:
                out.append((x, k))
                label[label == label[k]] = label[x]
    return out


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Runs of rows that agree in the first columns; a run may go over several batches."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        k = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(keys)])
        cuts = [0, *(np.flatnonzero((k[1:] != k[:-1]).any(axis=1)) + 1).tolist(), len(k)]
        for a, z in zip(cuts, cuts[1:]):
            if held and (k[a] != last).any():
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, z - a))
            last = k[a]
    if held:
        yield pa.Table.from_batches(held)


def _linked(rows: DataFrame, texts: DataFrame, bag: Callable[[str], Bag], threshold: float) -> DataFrame:
    """a, b of links; rows: b, i, j, node, part, root. Rows of one (b, i, j) are a block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _groups(batches, 3):
            node, first = np.unique(table.column("node").to_numpy(), return_index=True)
            table = table.take(first)
            label, part = (table.column(c).to_numpy() for c in ("root", "part"))
            if (label == label[0]).all():
                continue
            crossing = table.column("i")[0].as_py() != table.column("j")[0].as_py()
            found = tied([bag(t.as_py()) for t in table.column("t")], np.unique(label, return_inverse=True)[1], threshold, part if crossing else None)
            if found:
                x, y = np.array(found).T
                yield pa.RecordBatch.from_arrays([pa.array(node[x]), pa.array(node[y])], names=["a", "b"])

    keys = ["b", "i", "j"]
    shipped = rows.join(texts, "node").select(*keys, "node", "part", "root", "t")
    return shipped.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "a long, b long")


def pairs(members: DataFrame) -> DataFrame:
    """a, b (a > b) of members that share a bucket of at most SMALL; members: b, n, node, once for each bucket and node."""
    few = members.where(F.col("n") <= SMALL)
    met = few.select("b", F.col("node").alias("x")).hint("merge").join(few.select("b", F.col("node").alias("y")), "b").where("x > y")
    return met.select(F.col("x").alias("a"), F.col("y").alias("b")).distinct()


def parted(members: DataFrame, texts: DataFrame, most: int = MEMBERS, chars: int = CHARS) -> DataFrame:
    """b, node, pop, parts, part of members of buckets over SMALL; members: b, n, node; pop: members of all buckets that a node is in."""
    large = members.where(F.col("n") > SMALL).join(texts.select("node", F.char_length("t").alias("size")), "node")
    parts = F.greatest(F.ceil(F.first("n") / most), F.ceil(F.sum("size") / chars)).cast("int")
    pop = members.groupBy("node").agg(F.sum("n").alias("pop"))
    return large.join(large.groupBy("b").agg(parts.alias("parts")), "b").join(pop, "node").select("b", "node", "pop", "parts", F.pmod(F.xxhash64("node"), "parts").cast("int").alias("part"))


def within(dealt: DataFrame, texts: DataFrame, bag: Callable[[str], Bag], threshold: float) -> DataFrame:
    """Links inside each part, to which the member of most buckets (the hub) of a bucket of several parts is added."""
    own = dealt.select("b", F.col("part").alias("i"), F.col("part").alias("j"), "node", "part", F.col("node").alias("root"))
    hub = dealt.where("parts > 1").groupBy("b", "parts").agg(F.max(F.struct("pop", "node")).alias("h"))
    lent = hub.select("b", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("i"), F.col("h.node").alias("node"))
    return _linked(own.unionByName(lent.select("b", "i", F.col("i").alias("j"), "node", F.col("i").alias("part"), F.col("node").alias("root"))), texts, bag, threshold)


def across(dealt: DataFrame, roots: DataFrame, texts: DataFrame, bag: Callable[[str], Bag], threshold: float) -> DataFrame:
    """Links between parts of buckets that still hold different roots; roots: node, root of nodes that have links."""
    own = dealt.where("parts > 1").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    mixed = own.groupBy("b").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("b")
    met = own.join(mixed, "b", "left_semi").withColumn("o", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).where("o <> part")
    return _linked(met.select("b", F.least("part", "o").alias("i"), F.greatest("part", "o").alias("j"), "node", "part", "root"), texts, bag, threshold)
