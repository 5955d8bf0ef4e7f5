"""Hilbert-curve sharding with DataFrame functions only.

Metadata columns are quantised to BITS bits each (numbers by quantile cuts, strings by hash), a cell's place on the Hilbert
curve through them is folded from its coordinates, and rows are put in order of (place, hash of id, id). Runs of equal count are
cut from this order, so each shard covers a compact region and min/max statistics prune on every dimension.

The global row number needs no global sort: rows are counted by (cell, salt of the id's hash), at most 4096 * SALTS groups
whatever the table's size; running sums of these counts give each group's first number, and rows are numbered inside their
group. The hash order inside a cell is what lets a hot cell be dealt to SALTS tasks.

Defined cases: null values have coordinate 0; a null text has size 1 and the checksum of empty bytes; equal ids stay apart
as rows in any order; an empty table gives an empty result; shard sizes differ by one row at most.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.llm.common import documents, long_array

BITS, SALTS, SHARDS = 3, 32, 8


def hilbert_index(axes: list[Column], bits: int) -> Column:
    """Place of a point on the Hilbert curve: axes to transposed form (exchange and inversion from the top bit
    down, then Gray code), then the bits of all axes interleaved."""
    n = len(axes)
    steps = F.from_json(F.lit(str([[1 << b, i] for b in range(bits - 1, 0, -1) for i in range(n)])), "array<array<int>>")

    def turn(x: Column, s: Column) -> Column:
        q, i = F.element_at(s, 1), F.element_at(s, 2)
        mask, own, head = q - 1, F.element_at(x, i + 1), F.element_at(x, 1)
        swap = head.bitwiseXOR(own).bitwiseAND(mask)
        flip = own.bitwiseAND(q) != 0
        return F.transform(
            x,
            lambda v, j: F.when(flip & (j == 0), v.bitwiseXOR(mask)).when(flip, v).when((i != 0) & ((j == 0) | (j == i)), v.bitwiseXOR(swap)).otherwise(v),
        )

    point = F.aggregate(steps, F.array(*[a.cast("int") for a in axes]), turn)
    gray = F.aggregate(
        F.sequence(F.lit(2), F.lit(n)), point, lambda x, i: F.transform(x, lambda v, j: F.when(j == i - 1, v.bitwiseXOR(F.element_at(x, i - 1))).otherwise(v))
    )
    powers = F.from_json(F.lit(str([1 << b for b in range(bits - 1, 0, -1)])), "array<int>")

    def spread(x: Column) -> Column:
        t = F.aggregate(powers, F.lit(0), lambda a, q: F.when(F.element_at(x, n).bitwiseAND(q) != 0, a.bitwiseXOR(q - 1)).otherwise(a))
        return F.element_at(F.transform(F.array(t), lambda m: F.transform(x, lambda v: v.bitwiseXOR(m))), 1)

    def woven(x: Column) -> Column:
        places = F.from_json(F.lit(str([[1 << b, i] for b in range(bits - 1, -1, -1) for i in range(n)])), "array<array<int>>")
        return F.aggregate(
            places, F.lit(0).cast("long"), lambda a, s: a * 2 + F.when(F.element_at(x, F.element_at(s, 2) + 1).bitwiseAND(F.element_at(s, 1)) != 0, 1).otherwise(0)
        )

    final = F.element_at(F.transform(F.array(gray), spread), 1)
    return F.element_at(F.transform(F.array(final), woven), 1)


def quantised(df: DataFrame, column: str, bits: int) -> Column:
    """Coordinate of a column: strings by hash, numbers by quantiles of the whole table (2**bits - 1 cut points)."""
    n = 1 << bits
    if dict(df.dtypes)[column] == "string":
        return F.when(F.col(column).isNull(), 0).otherwise(F.pmod(F.xxhash64(column), F.lit(n)))
    cuts = df.agg(F.percentile_approx(F.col(column).cast("long"), [i / n for i in range(1, n)], 10_000)).first()[0] or []
    place = F.size(F.filter(long_array(cuts), lambda c: c <= F.col(column)))
    return F.when(F.col(column).isNull() | F.lit(not cuts), 0).otherwise(place)


def numbered(df: DataFrame, key: str, cell: str, salts: int = SALTS) -> DataFrame:
    """Adds ``pos``, the row number from 0 in order of (cell, hash of key, key), and ``total``."""
    rows = df.withColumn("_h", F.xxhash64(key)).withColumn("_s", F.pmod("_h", F.lit(salts)).cast("int"))
    groups = rows.groupBy(cell, "_s").agg(F.count("*").alias("c"))
    inside = Window.partitionBy(cell).orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    cells = groups.groupBy(cell).agg(F.sum("c").alias("n"))
    # At most 2**(bits * dimensions) rows, whatever the table's size.
    up_to = Window.orderBy(cell).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.orderBy(cell).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    starts = cells.select(cell, F.coalesce(F.sum("n").over(up_to), F.lit(0)).alias("_base"), F.sum("n").over(everything).alias("total"))
    first = groups.withColumn("_in", F.coalesce(F.sum("c").over(inside), F.lit(0))).join(starts, cell).select(cell, "_s", (F.col("_in") + F.col("_base")).alias("_first"), "total")
    own = Window.partitionBy(cell, "_s").orderBy("_h", key)
    ranked = rows.withColumn("_r", F.row_number().over(own) - 1)
    return ranked.join(first, [cell, "_s"]).withColumn("pos", F.col("_first") + F.col("_r")).drop("_h", "_s", "_r", "_first")


def sharded(df: DataFrame, key: str, dimensions: list[str], shards: int = SHARDS, bits: int = BITS) -> DataFrame:
    """Adds hilbert, shard and slot; counts of shards differ by one at most."""
    placed = df.withColumn("hilbert", hilbert_index([quantised(df, c, bits) for c in dimensions], bits))
    shard = F.expr(f"(pos * {shards}) div total")
    return numbered(placed, key, "hilbert").withColumn("shard", shard.cast("int")).withColumn("slot", F.expr(f"pos - ((shard * total + {shards - 1}) div {shards})")).drop("pos", "total")


def op5_hilbert(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in eight runs of the curve through size, id, language and source."""
    docs = documents(spark, sf_dir)
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), "lang", "source")
    return sharded(rows, "doc_id", ["size", "doc_id", "lang", "source"]).select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "hilbert"
    )


QUERIES = {"op5_hilbert": op5_hilbert}
