"""Mixing sources to target weights with DataFrame functions only.

The words of a source, in order of document id, are one stream cut into blocks of BLOCK words; only its last block may be shorter. A
source's target of words becomes draws: slot j of pass e takes block a * j + c mod n (n full blocks, a prime that doesn't divide n, c
by hash), so a pass takes every block once; the short block closes a pass; the last draw is cut so that the target is met to
the word. Each slot draws its output shard by hash, so the source counts of the shards are multinomial draws given the targets, and every
draw carries its shard to the words that it takes.
Draws and documents meet by (source, block). A pass takes no word twice, and targets stop at twice the source, so
no document is taken more than twice.

A hot source is dealt: its running word count is summed by ranges of ids (at most 1024, a fixed number) and then
inside each range; draws are made from chunks of CHUNK slots.

Defined cases: null text has no word; a null source is a source of its own, last in order; empty sources have target 0; equal ids stay
apart as rows; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.llm.common import documents, free, range_cuts, range_of

BLOCK, SHARDS, CHUNK = 256, 8, 4_096
WEIGHTS, SHARE, CAP = (5, 2, 1), 1.5, 2
WORD = r"[^\x20\x09-\x0D]+"
#: Primes above 2**26, for index permutations.
PRIMES = [67108879, 67108913, 67108919, 67108933, 67108957, 67108961, 67108981, 67109023]
SEED = 20_240_917


def targets(sizes: DataFrame) -> DataFrame:
    """s, source_size -> weight and target: shares by weight, each at most CAP times its source, the excess shared again.

    The limit is one level of words per unit of weight, found from the sources sorted by size / weight; the table has one row a source.
    """
    order = Window.orderBy(F.col("s").startswith("n"), "s")
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in WEIGHTS]), F.pmod(F.row_number().over(order) - 1, F.lit(len(WEIGHTS))) + 1)
    t = sizes.withColumn("weight", weight).withColumn("cap", CAP * F.col("source_size").cast("double")).withColumn("ratio", F.col("cap") / F.col("weight"))
    up = Window.orderBy("ratio", "s").rowsBetween(Window.unboundedPreceding, -1)
    rest = Window.orderBy("ratio", "s").rowsBetween(0, Window.unboundedFollowing)
    whole = Window.orderBy("ratio", "s").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.sum("source_size").over(whole) * F.lit(SHARE)
    level = (total - F.coalesce(F.sum("cap").over(up), F.lit(0.0))) / F.sum("weight").over(rest)
    # If the sources before this one are full and this one is not, the level is right; the first such source counts.
    t = t.withColumn("level", F.when(level <= F.col("ratio"), level))
    t = t.withColumn("level", F.first("level", ignorenulls=True).over(whole))
    return t.select("s", "source_size", "weight", F.coalesce(F.least("cap", F.col("weight") * F.col("level")), F.col("cap")).alias("target"))


def streams(docs: DataFrame) -> DataFrame:
    """Adds bucket, rn (a row's number in source and bucket) and start (its first word's place in its source's stream)."""
    rows = docs.withColumn("bucket", range_of(F.col("doc_id"), range_cuts(docs, "doc_id")))
    sums = rows.groupBy("s", "bucket").agg(F.sum("size").alias("n"))
    base = sums.select("s", "bucket", F.coalesce(F.sum("n").over(Window.partitionBy("s").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    own = Window.partitionBy("s", "bucket").orderBy("doc_id", "tie")
    inside = F.coalesce(F.sum("size").over(own.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("rn", F.row_number().over(own)).withColumn("inside", inside).join(base, ["s", "bucket"]).withColumn("start", F.col("base") + F.col("inside")).drop("base", "inside").withColumnRenamed("tie", "tie_key")


def draws(sources: DataFrame, block: int = BLOCK, shards: int = SHARDS) -> DataFrame:
    """Slots of the mix: s, pass, slot, block index, words taken from the block's head, output shard."""
    t = sources.where("source_size > 0").select(
        "s",
        F.col("source_size").alias("n"),
        F.expr(f"source_size div {block}").alias("full"),
        F.round("target").cast("long").alias("want"),
    )
    passes = F.expr("(want + n - 1) div n").cast("int")
    t = t.withColumn("e", F.explode(F.sequence(F.lit(0), passes))).where("e * n < want").withColumn("need", F.expr("least(n, want - e * n)"))
    slots = F.expr(f"(need + {block - 1}) div {block}")
    chunks = t.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"greatest(0, ({slots_sql(block)} - 1) div {CHUNK})"))).alias("k")).repartition("s", "e", "k")
    each = chunks.select("*", F.explode(F.sequence(F.col("k") * CHUNK, F.least((F.col("k") + 1) * CHUNK, slots) - 1)).alias("j")).where("j >= 0")
    fit = F.filter(F.from_json(F.lit(str(PRIMES)), "array<bigint>"), lambda p: F.col("full") % p != 0)
    h = F.xxhash64("s", "e", F.lit(SEED))
    a = F.element_at(fit, (F.pmod(h, F.size(fit)) + 1).cast("int"))
    index = F.when(F.col("j") >= F.col("full"), F.col("full")).otherwise((a * F.col("j") + F.pmod(F.xxhash64("s", "e", F.lit(SEED + 1)), F.col("full"))) % F.col("full"))
    shard = F.pmod(F.xxhash64("s", "e", "j", F.lit(SEED + 2)), F.lit(shards)).cast("int")
    return each.select("s", F.col("e").alias("pass"), "j", shard.alias("shard"), index.alias("block"), F.least(F.lit(block).cast("long"), F.col("need") - F.col("j") * block).alias("words"))


def slots_sql(block: int) -> str:
    return f"((need + {block - 1}) div {block})"


def shard_counts(slots: DataFrame) -> DataFrame:
    """Source counts of each output shard."""
    return slots.groupBy("shard", "s").agg(F.count("*").alias("blocks"), F.sum("words").alias("words"))


def source_key(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("n")).otherwise(F.concat(F.lit("'"), source))


def prepared(df: DataFrame, *keep: str) -> DataFrame:
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), source_key(F.col("source")).alias("s"), size.alias("size"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("tie"), *keep)


def plan(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows in their streams, and sources with targets."""
    sizes = rows.groupBy("s").agg(F.sum("size").alias("source_size"))
    return streams(rows), targets(sizes)


def taken(rows: DataFrame, sources: DataFrame, block: int = BLOCK) -> DataFrame:
    """s, bucket, rn -> spans of the row's words that the mix takes, as (pass, shard, lo, hi) from the row's first word."""
    parts = rows.where("size > 0").select(
        "s", "bucket", "rn", "start", "size", F.explode(F.expr(f"sequence(start div {block}, (start + size - 1) div {block})")).alias("block")
    )
    lo = F.greatest(F.lit(0).cast("long"), F.col("block") * block - F.col("start"))
    hi = F.least(F.col("size"), F.col("block") * block + F.col("words") - F.col("start"))
    # A merge join: the planner can't see how many draws come of a few chunks and would broadcast them.
    return parts.hint("merge").join(draws(sources, block), ["s", "block"]).select("s", "bucket", "rn", "pass", "shard", lo.alias("lo"), hi.alias("hi")).where("hi > lo")


def mixed(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """The mix as documents: a row for each document and pass that takes words of it, with the columns of ``docs``.

    A document taken whole keeps its text; of one taken in part, the words taken stay in order, each with the white space before it.
    """
    rows, sources = plan(prepared(docs))
    # Rows that repeat an id, text and source are told apart by a number, any of them by any.
    key, tie, of, copy, spans_, size_, n_, pass_ = (free(docs, x) for x in ("_key", "_tie", "_s", "_copy", "_spans", "_size", "_n", "_pass"))
    no_id = F.lit(-(2**63))
    alike = Window.partitionBy("doc_id", "tie_key", "s").orderBy("bucket", "rn")
    light = rows.select("s", "bucket", "rn", F.coalesce("doc_id", no_id).alias(key), F.col("tie_key").alias(tie), F.col("size").alias(size_), F.row_number().over(alike).alias(copy))
    spans = taken(rows, sources, block).groupBy("s", "bucket", "rn", "pass").agg(F.array_sort(F.collect_list(F.struct("lo", "hi"))).alias(spans_), F.sum(F.col("hi") - F.col("lo")).alias(n_))
    got = light.join(spans, ["s", "bucket", "rn"]).select(key, tie, F.col("s").alias(of), copy, size_, spans_, n_, F.col("pass").alias(pass_))
    own = docs.withColumns({tie: F.xxhash64(F.coalesce("text", F.lit(""))), of: source_key(F.col("source")), key: F.coalesce(F.col("doc_id").cast("long"), no_id)})
    own = own.withColumn(copy, F.row_number().over(Window.partitionBy(key, tie, of).orderBy(key)))
    both = own.join(got, [key, tie, of, copy])
    pieces = F.regexp_extract_all("text", F.lit(r"[\x20\x09-\x0D]*" + WORD), F.lit(0))
    cut = F.element_at(
        F.transform(F.array(pieces), lambda p: F.array_join(F.flatten(F.transform(spans_, lambda x: F.slice(p, (x["lo"] + 1).cast("int"), (x["hi"] - x["lo"]).cast("int")))), "")), 1
    )
    both = both.withColumn("text", F.when(F.col(n_) >= F.col(size_), F.col("text")).otherwise(F.ltrim(cut)))
    if "n_chars" in docs.columns:
        both = both.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return both.select(*[F.col(f"`{c}`") for c in docs.columns])


def op10_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the mix takes of every document, and by output shard."""
    rows, sources = plan(prepared(documents(spark, sf_dir)))
    by_shard = taken(rows, sources).groupBy("s", "bucket", "rn", "shard").agg(F.sum(F.col("hi") - F.col("lo")).alias("words"))
    words = by_shard.groupBy("s", "bucket", "rn").agg(F.sum("words").alias("taken"), F.array_sort(F.collect_list(F.struct("shard", "words"))).alias("shards"))
    out = rows.join(words, ["s", "bucket", "rn"], "left").join(sources, "s")
    return out.select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), F.coalesce("shards", F.array().cast("array<struct<shard:int,words:long>>")).alias("shards"))


QUERIES = {"op10_mixture": op10_mixture}
