"""Document fingerprints by consistent weighted sampling, with DataFrame functions only.

A text is a set of lower-case words with their counts S. For sample k each word w has r and c from Gamma(2, 1) and b from U(0, 1), drawn from
hashes of (w, k); with t = floor(ln S / r + b) and ln y = r (t - b), the word of least ln c - ln y - r is chosen and the
sample is (w, t). Two texts agree in a sample with the probability sum of min(S) / sum of max(S) over their words.
A fingerprint is SAMPLES such samples as 32-bit hashes; likeness is the share of equal ones.

Texts travel once: rows are dealt by ranges of ids (cut points: a fixed number), the first row of each range is sent to the range before
it too, so a window finds each row's next document; words, counts and minima need no further exchange. Samples are computed PER at a
time for each word, in generated code; the logarithms are shared by a text and its edited twin.

Defined cases: null text is empty; a text without words has the fingerprint of zeros, like only to its own kind; equal ids follow in order of
their texts' checksums; the next of the last document is the first; a single document is its own next; empty table, empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.llm.common import documents, range_cuts, range_of

SAMPLES, PER, PARTS = 32, 4, 256
GROUPS = SAMPLES // PER
TWO32 = float(1 << 32)


def _low(h: Column) -> Column:
    return (h.bitwiseAND((1 << 32) - 1) + F.lit(0.5)) / F.lit(TWO32)


def _high(h: Column) -> Column:
    return (F.shiftrightunsigned(h, 32) + F.lit(0.5)) / F.lit(TWO32)


def _sample(term: str, k: Column, log_counts: dict[str, str], name: str) -> list[Column]:
    """For each column of ln S, a long whose upper half orders samples and whose lower half names (word, t)."""
    h1, h2, h3 = (F.xxhash64(term, k, F.lit(i)) for i in (1, 2, 3))
    r = -F.log(_low(h1) * _high(h1))
    c = F.log(-F.log(_low(h2) * _high(h2)))
    b = _low(h3)
    out = []
    for alias, log_s in log_counts.items():
        t = F.floor(F.col(log_s) / r + b)
        rank = F.floor((c - r * (t - b) - r + F.lit(64.0)) * F.lit(float(1 << 24)))
        rank = F.greatest(F.lit(0), F.least(rank, F.lit((1 << 31) - 1)))
        packed = F.shiftleft(rank, 32).bitwiseOR(F.xxhash64(term, t).bitwiseAND((1 << 32) - 1))
        out.append(F.min(packed).alias(f"{alias}{name}"))
    return out


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def sampled(terms: DataFrame, keys: list[str], log_counts: dict[str, str]) -> DataFrame:
    """keys and, for each entry of log_counts, an array of SAMPLES longs (0 where there's no word)."""
    wide = terms.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(GROUPS - 1))))
    least = wide.groupBy(*keys, "g").agg(*[x for i in range(PER) for x in _sample("term", F.col("g") * PER + i, log_counts, str(i))])
    parts = [F.array(*[F.coalesce(F.col(f"{a}{i}").bitwiseAND((1 << 32) - 1), F.lit(0)) for i in range(PER)]).alias(a) for a in log_counts]
    rows = least.select(*keys, F.struct("g", *parts).alias("x")).groupBy(*keys).agg(F.array_sort(F.collect_list("x")).alias("x"))
    return rows.select(*keys, *[F.flatten(F.transform("x", lambda s: s[a])).alias(a) for a in log_counts])  # noqa: B023


def hexed(samples: Column) -> Column:
    return F.lower(F.array_join(F.transform(samples, lambda x: F.lpad(F.hex(x), 8, "0")), ""))


def likeness(a: Column, b: Column) -> Column:
    same = F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    return same / F.lit(float(SAMPLES))


def with_next(df: DataFrame, key: str, text: str) -> DataFrame:
    """range, rn, copy (a row lent by the following range), id, t and next_t."""
    rows = df.select(
        F.col(key).cast("long").alias("id"),
        F.coalesce(F.col(key).cast("long"), F.lit(-(2**63))).alias("k"),
        F.coalesce(text, F.lit("")).alias("t"),
    ).withColumns({"tie": F.crc32(F.col("t").cast("binary")), "range": range_of(F.col("id"), range_cuts(df.select(F.col(key).cast("long").alias("id")), "id"))})
    firsts = rows.groupBy("range").agg(F.min(F.struct("k", "tie")).alias("f"))
    every = Window.orderBy("range")  # one row a range: at most 1024
    final = F.last("range").over(every.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    lent = firsts.select("range", "f.k", "f.tie", F.coalesce(F.lag("range").over(every), final).alias("to"))
    own = F.struct("range", F.lit(False).alias("copy"))
    both = rows.join(F.broadcast(lent), ["range", "k", "tie"], "left")
    dealt = both.select("id", "k", "tie", "t", F.explode(F.when(F.col("to").isNull(), F.array(own)).otherwise(F.array(own, F.struct(F.col("to").alias("range"), F.lit(True).alias("copy"))))).alias("x"))
    order = Window.partitionBy("range").orderBy("copy", "k", "tie", "id")  # with id, both uses of the exchange read the same columns
    # Many small tasks: a task holds the word counts of its ranges.
    parts = max(PARTS, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    flat = dealt.select("id", "k", "tie", "t", "x.range", "x.copy").repartition(parts, "range")
    return flat.select("range", F.row_number().over(order).alias("rn"), "copy", "id", "t", F.lead("t").over(order).alias("next_t"))


def fingerprints(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    rows = with_next(df, key, text)
    n = F.char_length("t")
    edited = F.concat(F.expr("substring(t, 1, char_length(t) - char_length(t) div 4)"), F.expr("substring(next_t, 1, char_length(t) div 4)"))
    rows = rows.withColumn("e", F.when(F.col("copy"), F.lit("")).otherwise(F.coalesce(edited, "t")))
    both = F.array(F.struct(F.lit(0).alias("w"), F.col("t").alias("x")), F.struct(F.lit(1).alias("w"), F.col("e").alias("x")))
    tokens = rows.select("range", "rn", F.explode(both).alias("s")).select("range", "rn", "s.w", F.explode_outer(words(F.col("s.x"))).alias("word"))
    hashed = tokens.select("range", "rn", "w", F.when(F.col("word").isNotNull(), F.xxhash64("word")).alias("term"))
    counts = hashed.groupBy("range", "rn", "term").agg(F.sum(1 - F.col("w")).alias("s0"), F.sum("w").alias("s1"))
    live = counts.select("range", "rn", "term", *[F.when(F.col("term").isNotNull() & (F.col(s) > 0), F.log(s)).alias(f"l{s}") for s in ("s0", "s1")])
    prints = sampled(live, ["range", "rn"], {"f": "ls0", "e": "ls1"})
    after = prints.withColumn("n", F.lead("f").over(Window.partitionBy("range").orderBy("rn")))
    facts = rows.where("not copy").select("range", "rn", F.col("id").alias(key), n.cast("long").alias("n_chars"), F.sha2(F.encode("e", "UTF-8"), 256).alias("edited_sha256"))
    return facts.join(after, ["range", "rn"]).select(
        key, "n_chars", "edited_sha256",
        hexed(F.col("f")).alias("fingerprint"), hexed(F.col("e")).alias("edited_fingerprint"),
        likeness(F.col("f"), F.col("e")).alias("near_edited"), likeness(F.col("f"), F.col("n")).alias("near_next"),
    )


def op8_weighted_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of every document and of its edited text."""
    return fingerprints(documents(spark, sf_dir).select("doc_id", "text"))


QUERIES = {"op8_weighted_sampling": op8_weighted_sampling}
