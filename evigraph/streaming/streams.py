"""Streams over files: windows, duplicates, joins, late rows, and a growing index."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.runtime import scratch


def replay(spark: SparkSession, rows: DataFrame, parts: list, name: str = "replay") -> DataFrame:
    """A file stream of rows, one file folder a condition, read one at a time in order."""
    path = scratch(spark, name)
    for i, cond in enumerate(parts):
        rows.where(cond).coalesce(1).write.mode("append").option("maxRecordsPerFile", 0).parquet(f"{path}/p={i}")
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(path)


def drain(stream: DataFrame, mode: str = "append", sink: Callable | None = None, name: str = "drain") -> DataFrame | None:
    """Run a stream to the end of its files; returns what it wrote (complete and update modes: the last state by batch)."""
    spark = stream.sparkSession
    out, mark = scratch(spark, name), scratch(spark, "mark")
    if sink is not None:
        q = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", mark).trigger(availableNow=True).start()
        q.awaitTermination()
        return None
    if mode == "append":
        q = stream.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/state")  # the batch id makes a retry replace, not add

    q = stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", mark).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{out}/state")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return e.withColumn("ts", F.col("ts").cast("timestamp"))


def in_thirds(spark: SparkSession, rows: DataFrame, cols: str = "event_id") -> DataFrame:
    """Events replayed in three files by time order of ids."""
    n = rows.agg(F.max(cols)).first()[0] or 0
    a, b = n // 3, 2 * n // 3
    return replay(spark, rows, [F.col(cols) <= a, (F.col(cols) > a) & (F.col(cols) <= b), F.col(cols) > b], "events")


def tumbling(stream: DataFrame, size: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "1 hour") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def upsert_index(spark: SparkSession, docs: DataFrame, path: str) -> Callable:
    """A foreachBatch sink: chunks and term counts of new documents, in a folder of the batch's number, so a repeated batch replaces itself."""
    from evigraph.operators.textprep import chunk, ngrams, term_counts

    def sink(batch: DataFrame, i: int) -> None:
        cut = chunk(batch)
        cut.select("chunk_key", "n_tok").write.mode("overwrite").parquet(f"{path}/chunks/batch={i}")
        term_counts(ngrams(cut, 1)).select("chunk_key", "term", "cnt").write.mode("overwrite").parquet(f"{path}/counts/batch={i}")

    return sink
